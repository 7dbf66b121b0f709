"""Best-two-fit packing of token sequences.

Documents become token ids, get an end id, and are cut only where they are longer
than a sequence. Packing needs nothing but how many pieces there are of each
length, a table of at most `capacity` rows: it is filled greedily from the longest
length down, then the smallest piece of the bin gives way to the two unpacked
lengths that fill its widened gap best, if they fill it better. The pattern found
is used for as many sequences as the counts allow, so the work on the driver
depends on the number of lengths and not on the number of documents. A rank of
each piece within its length, from counts by group, then says where it goes.

Contracts: null and empty texts are one piece with the end id alone; repeated rows
are packed each; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import functools
import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from pathload.llm.bpe import _LETTER, byte_alphabet, default_path
from pathload.llm.common import SLICE_BYTES, free_name, group_count, staged, table, word_numbers

CAPACITY, END_ID = 4096, 1
#: Words kept with their ids by a worker; the table is emptied when it is full, which never changes results.
WORDS_KEPT = 250_000
#: Texts beyond these letters, with special tokens' marks or with contractions go to the library whole.
_UNUSUAL = re.compile(rf"[^\t-\r\x20-\x7e{_LETTER}]|İ|<\||'(?:[stmdSTMD]|[rRvV][eE]|[lL][lL])")
_SPACE, _LETTERS, _DIGIT, _OTHER = 0, 1, 2, 3
_CLASS = np.full(256, _OTHER, np.uint8)
_CLASS[[9, 10, 11, 12, 13, 32]] = _SPACE
_CLASS[[*range(65, 91), *range(97, 123), *range(128, 256)]] = _LETTERS
_CLASS[48:58] = _DIGIT


class WordIds:
    """A vocabulary file's ids for batches of texts.

    Usual texts are split into words by byte classes in numpy; each distinct word
    of a slice is looked up by its bytes, and only words not seen before go through
    the library's merges.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        self.whole.no_truncation()
        self.whole.no_padding()
        self.spelling = {b: c for c, b in byte_alphabet().items()}
        self._forget()

    def _forget(self) -> None:
        self.kept: dict[bytes, int] = {}
        self.size, self.at, self.flat = array("q"), array("q"), array("I")

    def _learn(self, words: list[bytes]) -> None:
        merges, spelling = self.whole.model.tokenize, self.spelling
        for word in words:
            text = word.decode() if word.isascii() else word.decode("latin-1").translate(spelling)
            ids = [t.id for t in merges(text)]
            self.kept[word] = len(self.kept)
            self.size.append(len(ids))
            self.at.append(len(self.flat))
            self.flat.extend(ids)

    def _library(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.whole.encode_batch_fast(texts, add_special_tokens=False)]

    def _usual(self, texts: list[str]) -> list[np.ndarray]:
        raw = [t.lower().encode() for t in texts]
        off = np.concatenate([[0], np.cumsum([len(r) for r in raw])])
        text = b"".join(raw)
        data = np.frombuffer(text, np.uint8)
        if not len(data):
            return [np.zeros(0, np.uint32) for _ in texts]
        kind = _CLASS[data]
        first = kind == _DIGIT
        first[0] = True
        first[1:] |= kind[1:] != kind[:-1]
        first[off[off < len(data)]] = True
        start = np.flatnonzero(first)
        end = np.append(start[1:], len(data))
        words = kind[start] != _SPACE
        start, end = start[words], end[words]
        number, where = word_numbers(data, start, end)
        if len(self.kept) + len(where) > WORDS_KEPT:
            self._forget()
        found = [text[a:b] for a, b in zip(start[where].tolist(), end[where].tolist(), strict=True)]
        self._learn([w for w in found if w not in self.kept])
        back = np.fromiter(map(self.kept.__getitem__, found), np.int64, len(found))[number]
        size, at = np.frombuffer(self.size, np.int64)[back], np.frombuffer(self.at, np.int64)[back]
        before = np.concatenate([[0], np.cumsum(size)])
        ids = np.frombuffer(self.flat, np.uint32)[np.arange(before[-1]) + np.repeat(at - before[:-1], size)]
        cut = before[np.searchsorted(start, off, "left")]
        return [ids[cut[i] : cut[i + 1]] for i in range(len(texts))]

    def ids(self, texts: list[str]) -> list[np.ndarray]:
        out: list[np.ndarray | None] = [None] * len(texts)
        usual: list[int] = []
        held = 0
        for i, t in enumerate(texts):
            if _UNUSUAL.search(t):
                out[i] = self._library([t])[0]
                continue
            usual.append(i)
            held += len(t)
            if held >= SLICE_BYTES // 4:
                for k, ids in zip(usual, self._usual([texts[k] for k in usual]), strict=True):
                    out[k] = ids
                usual, held = [], 0
        for k, ids in zip(usual, self._usual([texts[k] for k in usual]), strict=True):
            out[k] = ids
        return out


@functools.lru_cache(maxsize=2)
def word_ids(path: str) -> WordIds:
    return WordIds(path)


def token_pieces(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, piece, start, length, ids_crc32) for each piece of each document's ids with the end id."""
    path = path or default_path("word_bpe_49k.json")
    end = np.array([end_id], np.uint32)

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = word_ids(path)
        for b in batches:
            row, piece, start, length, crc = [], [], [], [], []
            for at in range(0, b.num_rows, 1024):
                for i, own in enumerate(tokens.ids([t.as_py() or "" for t in b.column(1).slice(at, 1024)]), at):
                    ids = np.append(own, end)
                    for k, begin in enumerate(range(0, len(ids), capacity)):
                        part = ids[begin : begin + capacity]
                        row.append(i), piece.append(k), start.append(begin), length.append(len(part)), crc.append(zlib.crc32(part.tobytes()))
            yield pa.RecordBatch.from_arrays(
                [b.column(0).take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())],
                [key, "piece", "start", "length", "ids_crc32"],
            )

    kept = docs.select(key, text)
    return kept.mapInArrow(pieces, f"`{key}` {kept.schema[key].dataType.simpleString()}, piece int, start long, length long, ids_crc32 long")


def best_two_fit(counts: dict[int, int], capacity: int = CAPACITY) -> np.ndarray:
    """Places for counts[length] pieces of each length, as rows (length, first_rank, bins, copies, first_bin, offset).

    A row says: the bins first_bin .. first_bin + bins - 1 each hold `copies`
    pieces of this length from `offset` on, taken in order of rank from first_rank.
    """
    left = np.zeros(capacity + 1, np.int64)
    for size, n in counts.items():
        left[size] = n
    used = np.zeros(capacity + 1, np.int64)
    rows, first_bin = [], 0
    while left.any():
        take: dict[int, int] = {}
        gap, limit = capacity, capacity
        there = np.flatnonzero(left)
        while gap > 0:
            k = int(np.searchsorted(there, min(gap, limit), "right")) - 1
            if k < 0:
                break
            size = int(there[k])
            take[size] = int(min(gap // size, left[size]))
            gap -= size * take[size]
            limit = size - 1
        least = min(take)
        if gap > 0 and sum(take.values()) > 1:
            room = gap + least
            rest = left.copy()
            for size, n in take.items():
                rest[size] -= n
            free = np.flatnonzero(rest[: room + 1])
            if len(free):
                mate = np.searchsorted(free, room - free, "right") - 1  # the largest that goes with each
                good = mate >= 0
                a, b = free[good], free[mate[good]]
                twin = (a == b) & (rest[a] < 2)
                if twin.any():  # one piece of that length only: the next smaller one goes with it
                    lower = np.searchsorted(free, a) - 1
                    b = np.where(twin, np.where(lower >= 0, free[np.maximum(lower, 0)], 0), b)
                total = np.where(b > 0, a + b, 0)
                best = int(np.argmax(total)) if len(total) else 0
                if len(total) and total[best] > least:
                    take[least] -= 1
                    if not take[least]:
                        del take[least]
                    for size in (int(a[best]), int(b[best])):
                        take[size] = take.get(size, 0) + 1
        bins = min(int(left[size]) // n for size, n in take.items())
        offset = 0
        for size in sorted(take, reverse=True):
            rows.append((size, int(used[size]), bins, take[size], first_bin, offset))
            offset += size * take[size]
            used[size] += bins * take[size]
            left[size] -= bins * take[size]
        first_bin += bins
    return np.array(rows, np.int64).reshape(-1, 6)


def pack(pieces: DataFrame, capacity: int = CAPACITY, key: str = "doc_id") -> DataFrame:
    """Adds sequence_id and offset to pieces (key, piece, start, length, ...)."""
    groups = group_count(pieces, 16 << 20)
    part = free_name("part", pieces.columns)
    names = pieces.columns
    pieces = pieces.withColumn(part, F.pmod(F.xxhash64(key, "piece"), F.lit(groups)).cast("int"))
    # Columns of their own: a cogroup of two frames that share a column's identity loses it where the right side isn't asked for it.
    counts = pieces.groupBy(part, "length").agg(F.count(F.lit(1)).alias("n")).select(F.col(part).alias("to"), F.col("length").alias("size"), "n")
    total = {r["size"]: r["n"] for r in counts.groupBy("size").agg(F.sum("n").alias("n")).collect()}  # at most capacity rows
    plan = best_two_fit(total, capacity)
    plan = plan[np.lexsort((plan[:, 1], plan[:, 0]))]
    before = Window.partitionBy("size").orderBy("to").rowsBetween(Window.unboundedPreceding, -1)
    ranks = counts.select("to", "size", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))

    def place(there: pa.Table, first: pa.Table) -> pa.Table:
        size = there.column("length").to_numpy()
        order = np.argsort(size, kind="stable")
        s = size[order]
        starts = np.flatnonzero(np.diff(s, prepend=-1)) if len(s) else np.zeros(0, np.int64)
        many = np.diff(np.append(starts, len(s)))
        within = np.arange(len(s)) - np.repeat(starts, many)
        by = dict(zip(first.column("size").to_pylist(), first.column("before").to_pylist(), strict=True))
        rank = within + np.array([by[x] for x in s[starts].tolist()], np.int64).repeat(many) if len(s) else within
        shift = np.int64(1) << 44
        at = np.searchsorted(plan[:, 0] * shift + plan[:, 1], s * shift + rank, "right") - 1
        r, copies = rank - plan[at, 1], plan[at, 3]
        sequence, offset = np.empty(len(s), np.int64), np.empty(len(s), np.int64)
        sequence[order] = plan[at, 4] + r // copies
        offset[order] = plan[at, 5] + r % copies * s
        return there.select(names).append_column("sequence_id", pa.array(sequence)).append_column("offset", pa.array(offset))

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema if f.name != part)
    return pieces.groupBy(part).cogroup(ranks.groupBy("to")).applyInArrow(place, f"{schema}, sequence_id long, offset long")


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(staged(token_pieces(table(spark, sf_dir, "documents"))))
