"""Finding repeated windows of words or bytes without moving every window.

Each window of a text has one anchor: its leftmost least k-gram by a hash. Equal
windows have equal anchors, and neighbouring windows mostly share theirs, so a
count-min sketch that hashes a window through its anchor needs a cell for each
occurrence of an anchor and not for each window; two occurrences of a window always
have two occurrences of its anchor, so no count is ever too low. The steps, each one
shuffle of packed blocks:

1. texts, dealt by a hash of their row, make a partition's sketch: the cells of its
   windows in two rows, with counts;
2. owners of cell ranges add the partitions' sketches up and tell each partition
   which of its cells reach two, and which are crowded;
3. texts send the windows whose estimate reaches two, once for each distinct content
   of a partition, to an owner by a hash;
4. owners compare windows exactly and send intervals of repeated places back;
5. texts drop what the intervals cover.

The cells grow with the input and are never gathered, so an estimate is as good at
any size. All steps read the same exchange of the texts, so texts are shuffled once.
Whatever repeats within a partition is settled there, so a window that a third of
the rows hold reaches its owner once for each partition. Rows of a partition are told
apart by their place in the order of key and text; equal rows are interchangeable.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from pathload.llm.common import U64, bucket_of, free_name, least_in_window, mix64, opened, packed, size_groups, squeezed, text_buffer, trim, unpacked

BUCKET, SOURCE, BLOCK, MARKS = "bucket", "source", "block", "marks"
#: Cells of one row of the sketch in an owner's range, cells of a row for each anchor by the input's size, and from how many occurrences an anchor's windows are split further.
WIDTH, ROOM, CROWDED = 1 << 22, 16, 8192
CELL = np.dtype([("cell", "<u4")])  # cell above eight bits of count
INTERVAL = np.dtype([("row", "<u4"), ("start", "<u4"), ("end", "<u4")])
_PLACE = U64((1 << 28) - 1)
#: Windows whose anchors are found in one numpy pass; a longer text takes several passes that overlap.
_PASS = 1 << 20


def anchors_of(h: np.ndarray, width: int) -> np.ndarray:
    """For each run of width successive hashes, the place of its leftmost least one."""
    n = len(h) - width + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    out = np.empty(n, np.int64)
    for a in range(0, n, _PASS):
        b = min(n, a + _PASS)
        part = h[a : b + width - 1]
        least = least_in_window((part & ~_PLACE) | np.arange(len(part), dtype=U64), width)
        out[a:b] = (least & _PLACE).astype(np.int64) + a
    return out


def cover(row: np.ndarray, start: np.ndarray, length: int | np.ndarray) -> np.ndarray:
    """Maximal intervals that windows [start, start + length) cover in each row."""
    if len(row) == 0:
        return np.zeros(0, INTERVAL)
    row, start = row.astype(np.int64), start.astype(np.int64)
    end = start + length
    span = np.int64(1) << 32
    order = np.argsort(row * span + start, kind="stable")
    lo, hi = (row * span + start)[order], (row * span + end)[order]
    reach = np.maximum.accumulate(hi)
    first = np.append(True, lo[1:] > reach[:-1])
    out = np.empty(int(first.sum()), INTERVAL)
    at = np.flatnonzero(first)
    out["row"], out["start"] = (lo[at] >> 32), lo[at] & (span - 1)
    out["end"] = reach[np.append(at[1:] - 1, len(lo) - 1)] & (span - 1)
    return out


class Repeats:
    """What differs between words and bytes; an instance travels to the workers."""

    #: Packed window records.
    record: np.dtype
    #: Bytes of text for each occurrence of an anchor, about.
    spacing: int

    def anchors(self, data: np.ndarray, off: np.ndarray) -> np.ndarray:
        """Hashes of all occurrences of anchors in some texts."""
        raise NotImplementedError

    def windows(self, data: np.ndarray, off: np.ndarray, keys: pa.Array, suspects: np.ndarray, crowded: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(routing hashes, records, intervals settled here) of the windows under suspected anchors; both lists of anchors are sorted."""
        raise NotImplementedError

    def decide(self, records: np.ndarray, source: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(source, interval) of each repeated place among the records of one owner."""
        raise NotImplementedError

    def drop(self, text: bytes, marks: np.ndarray) -> tuple[bytes, int, int, list[tuple[int, int]]]:
        """(what stays, units in all, units dropped, maximal dropped runs)."""
        raise NotImplementedError


def sketch_cells(h: np.ndarray, owners: int) -> list[np.ndarray]:
    """Each hash's cell in either row, out of owners * WIDTH * 2; a range of 2 * WIDTH cells belongs to one owner."""
    out = []
    for row, seed in enumerate((0xA24BAED4963EE407, 0x9FB21C651E98DF25)):
        g = mix64(h ^ U64(seed))
        out.append(((bucket_of(g, owners) * 2 + row) * WIDTH + (g & U64(WIDTH - 1)).astype(np.int64)))
    return out


def partition_sketch(h: np.ndarray, owners: int) -> tuple[np.ndarray, np.ndarray]:
    """(cells that the hashes reach, in order; their counts)."""
    return np.unique(np.concatenate(sketch_cells(h, owners)), return_counts=True)


def merged_sketch(cells: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Whether each record's cell reaches two, and CROWDED, in the sum of all partitions' records of one owner."""
    cell, n = (cells >> np.uint32(8)).astype(np.int64), (cells & np.uint32(255)).astype(np.float64)
    total = np.bincount(cell, n, 2 * WIDTH)[cell] if len(cells) else n
    return total >= 2, total >= CROWDED


def _ordered(rows: pa.Table, key: str, text: str) -> pa.Table:
    return rows.sort_by([(key, "ascending"), (text, "ascending")]).combine_chunks()


def owner_of(key: np.ndarray, owners: int) -> np.ndarray:
    """Anchors are least hashes, so small ones are common: their owner comes from a second mix."""
    return bucket_of(mix64(key), owners)


def _blocks(bucket: np.ndarray, records: np.ndarray, source: int) -> pa.Table:
    made = packed(bucket, records)
    return pa.table({BUCKET: made.column(0), SOURCE: pa.array(np.full(made.num_rows, source, np.int32)), BLOCK: squeezed(made.column(1), records.dtype)})


def without_repeats(docs: DataFrame, kind: Repeats, key: str = "doc_id", text: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """(key, carried columns, kept binary, n_units, n_removed, spans): each row's text without its repeats.

    A result whose name a carried column has gets an underscore more.
    """
    docs = docs.select(key, text, *carry)
    parts, owners = size_groups(docs, 2 << 20), size_groups(docs, 1 << 20)
    ranges = size_groups(docs, kind.spacing * WIDTH // ROOM)
    part = free_name("part", docs.columns)
    results = [free_name(x, (key, *carry)) for x in ("kept", "n_units", "n_removed", "spans")]
    dealt = docs.withColumn(part, F.pmod(F.xxhash64(key, text), F.lit(parts)).cast("int"))

    def send_sketch(name: tuple, rows: pa.Table) -> pa.Table:
        trim()
        data, off = text_buffer(rows.column(text))
        cell, n = partition_sketch(kind.anchors(data, off), ranges)
        records = np.empty(len(cell), CELL)
        records["cell"] = (cell % (2 * WIDTH)) << 8 | np.minimum(n, 255)
        return _blocks(cell // (2 * WIDTH), records, name[0].as_py())

    def merge(rows: pa.Table) -> pa.Table:
        trim()
        records, size = opened(rows.column(BLOCK), CELL)
        flags = np.stack(merged_sketch(records["cell"]), axis=1)
        ends = np.cumsum(size)
        bits = pa.array([np.packbits(flags[b - n : b]).tobytes() for b, n in zip(ends.tolist(), size.tolist(), strict=True)], pa.binary())
        return pa.table({SOURCE: rows.column(SOURCE), BUCKET: rows.column(BUCKET), BLOCK: bits})

    def suspected(h: np.ndarray, replies: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        """The anchors that both rows of the merged sketch estimate at two, and at CROWDED, sorted."""
        cell, _ = partition_sketch(h, ranges)
        many = np.bincount(cell // (2 * WIDTH), minlength=ranges)
        flags = [np.zeros((0, 2), np.uint8)]
        replies = replies.sort_by(BUCKET)
        for owner, bits in zip(replies.column(BUCKET).to_pylist(), replies.column(BLOCK), strict=True):
            flags.append(np.unpackbits(np.frombuffer(bits.as_buffer(), np.uint8), count=2 * int(many[owner])).reshape(-1, 2))
        flags = np.concatenate(flags).astype(bool)
        h = np.unique(h)
        a, b = (flags[np.searchsorted(cell, x)] for x in sketch_cells(h, ranges))
        both = a & b
        return h[both[:, 0]], h[both[:, 1]]

    def send_windows(name: tuple, rows: pa.Table, replies: pa.Table) -> pa.Table:
        trim()
        rows = _ordered(rows, key, text)
        data, off = text_buffer(rows.column(text))
        h = kind.anchors(data, off) if replies.num_rows else np.zeros(0, U64)
        h, records, settled = kind.windows(data, off, rows.column(key).combine_chunks(), *suspected(h, replies))
        source = (name[0].as_py() if name[0].is_valid else 0) if len(name) else 0
        out = _blocks(owner_of(h, owners), records, source)
        out = out.append_column(MARKS, pa.nulls(out.num_rows, pa.binary()))
        if len(settled):
            own = pa.table({BUCKET: pa.array([source % owners], pa.int32()), SOURCE: pa.array([source], pa.int32()), BLOCK: pa.array([None], pa.binary()), MARKS: pa.array([settled.tobytes()], pa.binary())})
            out = pa.concat_tables([out, own])
        return out

    def decide(rows: pa.Table) -> pa.Table:
        trim()
        records, size = opened(rows.column(BLOCK), kind.record)
        source = np.repeat(rows.column(SOURCE).to_numpy(), size)
        made = packed(*kind.decide(records, source))
        out = pa.table({SOURCE: made.column(0), BLOCK: made.column(1)})
        settled = rows.filter(rows.column(MARKS).is_valid())
        return pa.concat_tables([out, pa.table({SOURCE: settled.column(SOURCE), BLOCK: settled.column(MARKS)}, schema=out.schema)])

    def finish(rows: pa.Table, marks: pa.Table) -> pa.Table:
        trim()
        rows = _ordered(rows, key, text)
        data, off = text_buffer(rows.column(text))
        raw, off = data.tobytes(), off.tolist()
        m = unpacked(marks.column(BLOCK), INTERVAL)
        m = cover(m["row"], m["start"], m["end"].astype(np.int64) - m["start"])
        at = np.searchsorted(m["row"], np.arange(len(off)))
        done = [kind.drop(raw[off[i] : off[i + 1]], m[at[i] : at[i + 1]]) for i in range(rows.num_rows)]
        rows = rows.drop_columns([part, text])
        for name, i, t in zip(results, range(3), (pa.binary(), pa.int64(), pa.int64()), strict=False):
            rows = rows.append_column(name, pa.array([d[i] for d in done], t))
        spans = pa.array([[{"start": a, "end": b} for a, b in d[3]] for d in done], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))
        return rows.append_column(results[3], spans)

    sketches = dealt.groupBy(part).applyInArrow(send_sketch, f"{BUCKET} int, {SOURCE} int, {BLOCK} binary")
    replies = sketches.groupBy(BUCKET).applyInArrow(merge, f"{SOURCE} int, {BUCKET} int, {BLOCK} binary")
    windows = dealt.groupBy(part).cogroup(replies.groupBy(SOURCE)).applyInArrow(send_windows, f"{BUCKET} int, {SOURCE} int, {BLOCK} binary, {MARKS} binary")
    marks = windows.groupBy(BUCKET).applyInArrow(decide, f"{SOURCE} int, {BLOCK} binary")
    carried = "".join(f"`{c}` {docs.schema[c].dataType.simpleString()}, " for c in (key, *carry))
    kept, units, removed, spans = (f"`{x}`" for x in results)
    return dealt.groupBy(part).cogroup(marks.groupBy(SOURCE)).applyInArrow(finish, f"{carried}{kept} binary, {units} bigint, {removed} bigint, {spans} array<struct<start:bigint,end:bigint>>")
