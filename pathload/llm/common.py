"""What the training-data operators share: staging in the shared folder, text buffers, packed routing.

Many operators move fixed-width records (fingerprints, positions) between tasks.
Such records travel as one binary block for each (task, bucket) rather than one
row each, so the shuffle is a memory copy and its row count stays small.
"""

from __future__ import annotations

import contextlib
import ctypes
import hashlib
import tempfile
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame, SparkSession, functions as F

#: Bytes of text that a numpy pass holds at once; arrays of 8 bytes a position stay in a few dozen MB.
SLICE_BYTES = 2 << 20
U64 = np.uint64


def free_name(name: str, taken) -> str:
    """The name, with underscores until no column has it, whatever its case."""
    low = {t.lower() for t in taken}
    while name.lower() in low:
        name += "_"
    return name


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shuffle_parts(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def estimated_bytes(df: DataFrame) -> int:
    """Catalyst's size estimate of a frame: the files' size for a scan. Used to choose numbers of groups, never results."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def group_count(df: DataFrame, target_bytes: int = 8 << 20, per_partition: int = 1) -> int:
    """Groups for hashing a frame's rows so that one group holds about target_bytes at any input size."""
    spark = df.sparkSession
    est = estimated_bytes(df)
    by_size = -(-est // target_bytes) if est < 1 << 50 else 0
    return int(max(shuffle_parts(spark) * per_partition, by_size))


def size_groups(df: DataFrame, target_bytes: int) -> int:
    """Groups of about target_bytes by the size alone: blocks go from each group to each other, so more partitions must not mean more groups."""
    est = estimated_bytes(df)
    return int(max(16, -(-est // target_bytes))) if est < 1 << 50 else shuffle_parts(df.sparkSession)


def shared_folder(spark: SparkSession) -> str:
    """A fresh folder below spark.checkpoint.dir; a temporary one only where that setting is unset (tests, local mode)."""
    base = spark.conf.get("spark.checkpoint.dir", None) or f"{tempfile.gettempdir()}/pathload-shared"
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


def staged(df: DataFrame) -> DataFrame:
    """Writes a frame to the shared folder and reads it back: lineage ends there, and any executor can read it."""
    path = shared_folder(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def trim() -> None:
    """Gives freed memory back to the system, so that a worker holds little between groups."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def text_buffer(col) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and offsets (n+1, from 0) of an Arrow string or binary column; null counts as empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
        if isinstance(col, pa.ChunkedArray):
            col = pa.concat_arrays(col.chunks) if col.num_chunks else pa.array([], col.type)
    if len(col) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    if col.null_count:
        col = pc.fill_null(col, b"" if pa.types.is_binary(col.type) or pa.types.is_large_binary(col.type) else "")
    wide = pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type)
    off = np.frombuffer(col.buffers()[1], np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    buf = col.buffers()[2]
    data = np.frombuffer(buf, np.uint8)[off[0] : off[-1]] if buf is not None and off[-1] > off[0] else np.zeros(0, np.uint8)
    return data, off - off[0]


def doc_slices(off: np.ndarray, limit: int = SLICE_BYTES):
    """Ranges [a, b) of documents with about limit bytes each; one longer document stands alone."""
    a, n = 0, len(off) - 1
    while a < n:
        b = int(np.searchsorted(off, off[a] + limit, "right")) - 1
        b = min(n, max(b, a + 1))
        yield a, b
        a = b


def packed(bucket: np.ndarray, records: np.ndarray, extra: dict | None = None) -> pa.RecordBatch:
    """One row (bucket, block) for each bucket that has records; block: its records' bytes."""
    order = np.argsort(bucket, kind="stable")
    b, r = bucket[order], records[order]
    cut = np.flatnonzero(np.diff(b)) + 1
    start = np.concatenate([[0], cut]) if len(b) else np.zeros(0, np.int64)
    size = records.dtype.itemsize
    off = np.append(start, len(b)).astype(np.int64) * size
    blob = pa.py_buffer(np.ascontiguousarray(r).tobytes())
    if len(start) == 0:
        block = pa.array([], pa.binary())
    else:
        block = pa.Array.from_buffers(pa.binary(), len(start), [None, pa.py_buffer(off.astype(np.int32).tobytes()), blob])
    return pa.RecordBatch.from_arrays([pa.array(b[start].astype(np.int32) if len(b) else [], pa.int32()), block], ["bucket", "block"])


PACKED_SCHEMA = "bucket int, block binary"


def unpacked(col, dtype: np.dtype) -> np.ndarray:
    """The records of a column of blocks."""
    data, _ = text_buffer(col)
    return np.frombuffer(data.tobytes(), dtype)


def squeezed(blocks: pa.Array, dtype: np.dtype) -> pa.Array:
    """Blocks with numbers as byte planes, compressed where that is shorter; the first byte says which."""
    press = zstandard.ZstdCompressor(level=1)
    out = []
    for raw in blocks:
        r = np.frombuffer(raw.as_buffer(), dtype)
        fields = (np.ascontiguousarray(r[f]).view(np.uint8).reshape(len(r), dtype[f].itemsize) for f in dtype.names)
        plain = b"".join((x if dtype[f].shape else x.T).tobytes() for f, x in zip(dtype.names, fields, strict=True))
        small = press.compress(plain)
        out.append(b"\1" + small if len(small) < len(plain) else b"\0" + plain)
    return pa.array(out, pa.binary())


def opened(col, dtype: np.dtype) -> tuple[np.ndarray, np.ndarray]:
    """(records, number of records of each block) of squeezed blocks; a null block has none."""
    press = zstandard.ZstdDecompressor()
    parts, count = [np.zeros(0, dtype)], np.zeros(len(col), np.int64)
    for i, value in enumerate(col):
        if not value.is_valid:
            continue
        raw = value.as_py()
        plain = press.decompress(raw[1:]) if raw[0] else raw[1:]
        n = count[i] = len(plain) // dtype.itemsize
        r, at = np.empty(n, dtype), 0
        for f in dtype.names:
            kind = dtype[f]
            x = np.frombuffer(plain, np.uint8, n * kind.itemsize, at)
            r[f] = x.reshape(n, kind.itemsize) if kind.shape else np.ascontiguousarray(x.reshape(kind.itemsize, n).T).view(kind).ravel()
            at += n * kind.itemsize
        parts.append(r)
    return np.concatenate(parts), count


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser over unsigned 64-bit numbers."""
    x = x.astype(U64, copy=True)
    x ^= x >> U64(31)
    x *= U64(0x9E3779B97F4A7C15)
    x ^= x >> U64(29)
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(32)
    return x


def bucket_of(key: np.ndarray, n: int) -> np.ndarray:
    """Bucket 0..n-1 from the upper 31 bits of a mixed 64-bit key."""
    return ((key >> U64(33)) * U64(n) >> U64(31)).astype(np.int64)


#: Words of more bytes go through BLAKE2b, so that no loop is as long as a word.
LONG_WORD = 256
#: Fixed odd factors of the fingerprints' two functions.
FACTORS = (U64(0x9D39247E33776D41), U64(0xA4093822299F31D1))
_LOW_BYTES = np.array([(1 << 8 * i) - 1 for i in range(9)], U64)


_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True


def word_spans(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end byte of each word (runs of other bytes than space and 0x09-0x0D) and the words' offsets by document."""
    n = len(data)
    if n == 0:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(len(off), np.int64)
    inside = ~_SPACE[data]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    bounds = off[(off > 0) & (off < n)]
    first[bounds] = inside[bounds]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    last[bounds - 1] = inside[bounds - 1]
    start, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    return start, end, np.searchsorted(start, off, "left")


def _eights(data: np.ndarray) -> np.ndarray:
    """The eight bytes from each place on as a number; zeros follow the end."""
    return np.ndarray(len(data) + 1, "<u8", np.append(data, np.zeros(8, np.uint8)), strides=(1,))


def word_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray, which: int = 0) -> np.ndarray:
    """A 64-bit fingerprint of each word's bytes: a chain of mixed eight-byte pieces that starts from the length."""
    if len(start) == 0:
        return np.zeros(0, U64)
    eight, size = _eights(data), end - start
    h = mix64(size.astype(U64) * FACTORS[which] + FACTORS[1 - which])
    for i in np.flatnonzero(size > LONG_WORD).tolist():
        h[i] = int.from_bytes(hashlib.blake2b(data[start[i] : end[i]].tobytes(), digest_size=8, person=b"word%d" % which).digest(), "little")
    todo = np.flatnonzero(size <= LONG_WORD)
    at, left = start[todo], size[todo]
    while len(todo):
        h[todo] = mix64((h[todo] * FACTORS[which]) ^ (eight[at] & _LOW_BYTES[np.minimum(left, 8)]))
        go = left > 8
        todo, at, left = todo[go], at[go] + 8, left[go] - 8
    return h


def equal_words(data: np.ndarray, start: np.ndarray, end: np.ndarray, other: np.ndarray) -> np.ndarray:
    """Whether each word has the bytes of the word whose place `other` gives."""
    eight, size = _eights(data), end - start
    good = size == size[other]
    todo = np.flatnonzero(good & (other != np.arange(len(start))))
    long = size[todo] > LONG_WORD
    for i in todo[long].tolist():
        j = int(other[i])
        good[i] = np.array_equal(data[start[i] : end[i]], data[start[j] : end[j]])
    todo = todo[~long]
    x, y, left = start[todo], start[other[todo]], size[todo]
    while len(todo):
        differs = ((eight[x] ^ eight[y]) & _LOW_BYTES[np.minimum(left, 8)]) != 0
        good[todo[differs]] = False
        go = ~differs & (left > 8)
        todo, x, y, left = todo[go], x[go] + 8, y[go] + 8, left[go] - 8
    return good


def word_numbers(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A number for each word, equal for equal bytes and only for those, and one place of each number."""
    key = word_hashes(data, start, end)
    order = np.argsort(key, kind="stable")
    new = np.append(True, key[order][1:] != key[order][:-1]) if len(key) else np.zeros(0, bool)
    number, place = np.empty(len(key), np.int64), order[new]
    number[order] = np.cumsum(new) - 1
    clash = np.flatnonzero(~equal_words(data, start, end, place[number])) if len(key) else number
    if len(clash):  # the bytes themselves tell apart words whose fingerprints are equal
        known: dict[bytes, int] = {}
        extra = []
        for i in clash.tolist():
            k = known.setdefault(data[start[i] : end[i]].tobytes(), len(place) + len(known))
            if k == len(place) + len(extra):
                extra.append(i)
            number[i] = k
        place = np.append(place, extra)
    return number, place


def _over_runs(x: np.ndarray, length: int, join) -> np.ndarray:
    """join folded over each run of length successive values, by doubling."""
    if len(x) < length:
        return x[:0]
    out, done, power = None, 0, 1
    while power <= length:
        if length & power:
            out = x if out is None else join(out[: len(x) - done], x[done:])
            done += power
        power *= 2
        if power <= length:
            x = join(x[: -(power // 2)], x[power // 2 :])
    return out


def run_hashes(h: np.ndarray, length: int, which: int = 0) -> np.ndarray:
    """Fingerprint of each run of length successive hashes (len(h) - length + 1 of them)."""
    return _over_runs(h, length, lambda a, b: mix64((a * FACTORS[which]) ^ b))


def run_numbers(number: np.ndarray, length: int) -> np.ndarray:
    """A number for each run of length successive numbers, equal for equal runs and only for those."""

    def join(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.unique(a * (int(b.max(initial=0)) + 1) + b, return_inverse=True)[1] if len(a) else a

    return _over_runs(number, length, join)


def least_in_window(value: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each width successive values, by doubling."""
    m, have = value, 1
    while have * 2 <= width:
        m = np.minimum(m[:-have], m[have:])
        have *= 2
    if have < width:
        m = np.minimum(m[: len(m) - (width - have)], m[width - have :])
    return m


def with_bucket(df: DataFrame, key: str, n: int, name: str = "part_") -> DataFrame:
    return df.withColumn(name, F.pmod(F.xxhash64(key), F.lit(n)).cast("int"))
