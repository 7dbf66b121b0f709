"""Suffix-array dedup with a run-length index.

Bytes of a text are dropped where a string of `length` bytes covers them that also
starts in a text of a smaller id. Windows of bytes that share an anchor form one
super-string of at most 2 * length - k bytes; super-strings under an anchor that
occurs once are unique and stay at home (see anchored). An owner of anchors
collapses equal super-strings and indexes those that differ from another one under
the same anchor (under a crowded anchor: with the same least hashes near both ends
too, so that a common phrase spreads by its surroundings): their suffixes are sorted, the Burrows-Wheeler transform is kept
as runs with a suffix sample at each run's end, and the super-strings are streamed
through it backwards, all at once, one LF step a byte. A step's row says which
class of rows with `length` common bytes the suffix belongs to, that is whether its
matching statistic reaches `length`, and the class says the smallest id.

Contracts: a null text is empty; texts shorter than `length` keep everything; rows
of equal id don't count as smaller than each other; a null id is larger than any
id; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, functions as F

from pathload.llm.anchored import Repeats, anchors_of, cover, without_repeats
from pathload.llm.common import U64, doc_slices, least_in_window, mix64, table
from pathload.llm.windows import _by_source

_LAST = np.iinfo(np.int64).max
#: Bytes of text in one numpy pass.
_STEP = 1 << 18
#: Super-strings that an owner indexes at once; those of one anchor stay together.
_INDEXED = 6_000


class RunLengthIndex:
    """Burrows-Wheeler transform of a set of byte strings, as runs with sampled ends.

    Each string ends with its own mark; marks sort before all bytes and among
    themselves by string. Rows 0 to n-1 are the marks' suffixes.
    """

    def __init__(self, block: np.ndarray, size: np.ndarray, length: int = 50):
        """block: strings as rows of a padded byte matrix; size: their lengths; length: of the common prefix that makes a class."""
        n, width = block.shape
        self.n, self.size = n, size.astype(np.int64)
        self.at = np.concatenate([[0], np.cumsum(self.size + 1)])  # a string's place in the joined text, its mark included
        total = int(self.at[-1])
        valid = np.arange(width + 1) <= self.size[:, None]
        padded = np.zeros((n, width + 9), np.uint16)
        padded[:, :width] = np.where(np.arange(width) < self.size[:, None], block.astype(np.uint16) + 1, 0)
        key = np.zeros((n, width + 1), U64)
        for i in range(7):  # seven symbols of nine bits
            key = (key << U64(9)) | padded[:, i : i + width + 1].astype(U64)
        text = padded[:, : width + 1][valid]
        left = (self.size[:, None] - np.arange(width + 1))[valid]  # bytes before the mark
        rank, span = self._dense(key[valid]), 7
        need = int(self.size.max(initial=0)) + 1
        self.window_class = None
        while True:
            if self.window_class is None and 2 * span >= length:
                self.window_class = rank, span
            if span >= need:
                break
            ahead = np.arange(total) + span
            follow = np.where(left >= span, rank[np.minimum(ahead, total - 1)] + 1, 0)
            rank, span = self._dense(rank.astype(np.int64) * (total + 2) + follow), 2 * span
        order = np.argsort(rank, kind="stable")  # equal suffixes by string
        self.left, self.order_len = left, left[order]
        before = np.concatenate([[0], text[:-1]])
        before[self.at[:-1]] = 0
        bwt = before[order]
        change = np.append(True, bwt[1:] != bwt[:-1])
        self.run_start = np.flatnonzero(change)
        self.run_head = bwt[self.run_start]
        run_size = np.diff(np.append(self.run_start, total))
        self.run_sample = order[self.run_start + run_size - 1]  # where the suffix of a run's last row starts
        by = np.argsort(self.run_head, kind="stable")
        sums = np.cumsum(run_size[by]) - run_size[by]
        self.run_to = np.empty(len(by), np.int64)
        self.run_to[by] = sums  # the LF image of a run's first row: rows are sorted by first byte, then as before
        self.rows = total
        self.run_of = np.repeat(np.arange(len(run_size), dtype=np.int32), run_size)  # a row's run without a search
        prefix, have = self.window_class
        full = self.order_len >= length
        a, b = prefix[order], prefix[np.minimum(order + length - have, total - 1)]
        same = np.append(False, (a[1:] == a[:-1]) & (b[1:] == b[:-1]) & full[1:] & full[:-1])
        self.class_of = np.cumsum(~same) - 1
        self.length = length

    @staticmethod
    def _dense(key: np.ndarray) -> np.ndarray:
        order = np.argsort(key)
        k = key[order]
        out = np.empty(len(key), np.int64)
        out[order] = np.cumsum(np.append(False, k[1:] != k[:-1])) if len(key) else 0
        return out

    def step(self, row: np.ndarray) -> np.ndarray:
        """Rows of the suffixes one byte longer."""
        run = self.run_of[row]
        return self.run_to[run] + row - self.run_start[run]

    def locate(self, row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(string, offset) of rows' suffixes: LF steps lead to a run's end, whose sample is known, or to a string's start."""
        row, moved = row.astype(np.int64).copy(), np.zeros(len(row), np.int64)
        place = np.full(len(row), -1, np.int64)
        ends = np.append(self.run_start[1:], self.rows) - 1
        while (open_ := np.flatnonzero(place < 0)).size:
            r = row[open_]
            run = self.run_of[r]
            done = ends[run] == r
            place[open_[done]] = self.run_sample[run[done]] + moved[open_[done]]
            first = ~done & (self.run_head[run] == 0)  # starts its string: the mark before it is its string's predecessor
            if first.any():
                back = self.run_to[run[first]] + r[first] - self.run_start[run[first]]
                place[open_[first]] = self.at[back] + moved[open_[first]]
            go = ~done & ~first
            row[open_[go]] = self.run_to[run[go]] + r[go] - self.run_start[run[go]]
            moved[open_[go]] += 1
        string = np.searchsorted(self.at, place, "right") - 1
        return string, place - self.at[string]

    def least_ids(self, ids: np.ndarray) -> np.ndarray:
        """For each string and offset, the smallest id of a string with the same `length` bytes there; the largest number where fewer follow.

        ids: a number for each string. All strings stream backwards together.
        """
        width = int(self.size.max(initial=0))
        out = np.full((self.n, max(width - self.length + 1, 0)), _LAST, np.int64)
        if not self.n or width < self.length:
            return out
        row_of_end = np.arange(self.n)  # row i is the suffix that is string i's mark alone
        seen_class, seen_id, seen_at = [], [], []
        row, todo, left = row_of_end.copy(), np.arange(self.n), self.size.copy()
        matched = 0
        while len(todo):
            row, left, matched = self.step(row), left - 1, matched + 1
            if matched >= self.length:
                seen_class.append(self.class_of[row])
                seen_id.append(todo)
                seen_at.append(left)
            go = left > 0
            row, todo, left = row[go], todo[go], left[go]
        c, s, o = (np.concatenate(x) for x in (seen_class, seen_id, seen_at))
        least = np.full(int(self.class_of[-1]) + 1, _LAST, np.int64)
        np.minimum.at(least, c, ids[s])
        out[s, o] = least[c]
        return out


class ByteRepeats(Repeats):
    """Strings of `length` bytes that also start in a text of a smaller id."""

    def __init__(self, length: int = 50, gram: int = 24, whole_characters: bool = False):
        """whole_characters: intervals shrink to UTF-8 character borders, so that what stays is text."""
        self.length, self.gram, self.whole_characters = length, gram, whole_characters
        self.width = 2 * length - gram  # the longest super-string
        self.spacing = max(1, (length - gram + 2) // 2)
        self.record = np.dtype([("doc", "<i8"), ("anchor", "<u8"), ("row", "<u4"), ("at", "<u4"), ("size", "<u2"), ("text", "u1", (self.width,))])

    def _slice(self, data: np.ndarray, off: np.ndarray):
        n = len(data)
        if n < self.length:
            z = np.zeros(0, np.int64)
            return np.zeros(0, U64), z, z, np.zeros(0, bool)
        eight = np.ndarray(n - 7, "<u8", np.ascontiguousarray(data), strides=(1,))
        m = n - self.gram + 1
        h = mix64(eight[self.gram - 8 : self.gram - 8 + m])
        for at in range((self.gram - 1) // 8 * 8 - 8, -1, -8):  # all bytes of a gram, so that a common phrase shorter than it is no anchor that many texts share
            h = mix64(eight[at : at + m] * U64(0x9E3779B97F4A7C15) + h)
        anchor = anchors_of(h, self.length - self.gram + 1)
        inside = np.ones(len(anchor), bool)
        for e in off[1:-1].tolist():
            inside[max(0, e - self.length + 1) : e] = False
        return h, anchor, inside

    def _pieces(self, off: np.ndarray):
        """Pieces (first row, last row + 1, first byte, last byte + 1): short texts together, long ones in steps that overlap by a window."""
        for a, b in doc_slices(off, _STEP):
            lo, hi = int(off[a]), int(off[b])
            for s in range(lo, max(lo + 1, hi - self.length + 1), _STEP) if b == a + 1 else (lo,):
                yield a, b, s, min(hi, s + _STEP + self.length - 1) if b == a + 1 else hi

    def _windows(self, data, off):
        for a, b, s, e in self._pieces(off):
            if e - s < self.length:
                continue
            own = np.array([0, e - s]) if b == a + 1 else off[a : b + 1] - s
            yield a, s, own, *self._slice(data[s:e], own)

    def anchors(self, data, off):
        found = [np.zeros(0, U64)]
        for _, _, _, h, anchor, inside in self._windows(data, off):
            at = anchor[inside]
            if len(at):
                found.append(h[at[np.append(True, at[1:] != at[:-1])]])
        return np.concatenate(found)

    @staticmethod
    def _runs(anchor: np.ndarray, inside: np.ndarray, more: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """First and last window of each run under one anchor; more: further places before which a run ends."""
        change = anchor[1:] != anchor[:-1]
        if more is not None:
            change |= more
        first, last = inside.copy(), inside.copy()
        first[1:] &= change | ~inside[:-1]
        last[:-1] &= change | ~inside[1:]
        return np.flatnonzero(first), np.flatnonzero(last)

    def _crowded(self, h: np.ndarray, anchor: np.ndarray, lo: np.ndarray, hi: np.ndarray, crowded: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
        """(windows under crowded anchors, what parts them by window, changes of that among them): least hashes near the window's start and near its end."""
        if not len(crowded) or not len(lo):
            return None
        hot = np.isin(h[anchor[lo]], crowded)
        if not hot.any():
            return None
        edge = np.zeros(len(anchor) + 1, np.int64)
        np.add.at(edge, lo[hot], 1)
        np.add.at(edge, hi[hot] + 1, -1)
        under = np.cumsum(edge[:-1]) > 0
        grams = self.length - self.gram + 1
        width = max(1, grams // 4)
        least = least_in_window(mix64(h ^ U64(0xC2B2AE3D27D4EB4F)), width)
        apart = mix64(least[: len(anchor)] ^ mix64(least[grams - width : grams - width + len(anchor)]))
        return under, apart, under[1:] & under[:-1] & (apart[1:] != apart[:-1])

    def windows(self, data, off, keys, suspects, crowded):
        docs = pc.fill_null(pc.cast(keys, pa.int64()), _LAST).to_numpy(zero_copy_only=False)
        parts = [np.zeros(0, self.record)]
        for a, s, own, h, anchor, inside in self._windows(data, off) if len(suspects) else ():
            lo, hi = self._runs(anchor, inside)
            split = self._crowded(h, anchor, lo, hi, crowded)
            if split is not None:
                lo, hi = self._runs(anchor, inside, split[2])
            key = h[anchor[lo]]
            at = np.minimum(np.searchsorted(suspects, key), len(suspects) - 1)
            use = suspects[at] == key
            if split is not None:
                key = np.where(split[0][lo], mix64(key ^ split[1][lo]), key)
            lo, size, key = lo[use], hi[use] - lo[use] + self.length, key[use]
            if not len(lo):
                continue
            out = np.zeros(len(lo), self.record)
            doc = np.searchsorted(own, lo, "right") - 1
            out["row"] = doc + a
            out["doc"], out["anchor"], out["size"] = docs[doc + a], key, size
            out["at"] = lo + s - off[doc + a]
            part = np.append(data[s : s + own[-1]], np.zeros(self.width, np.uint8))
            view = np.lib.stride_tricks.as_strided(part, (len(part) - self.width + 1, self.width), (1, 1))
            out["text"] = np.where(np.arange(self.width) < size[:, None], view[lo], 0)
            parts.append(out)
        r = np.concatenate(parts)
        group, _ = self._equal(r)
        least = np.full(int(group.max(initial=-1)) + 1, _LAST, np.int64)
        np.minimum.at(least, group, r["doc"])
        later = r["doc"] > least[group]
        settled = cover(r["row"][later], r["at"][later], r["size"][later].astype(np.int64))
        r = r[~later]
        return r["anchor"], r, settled

    def _equal(self, r: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """A number for each distinct (size, text), and one place of each."""
        if not len(r):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        whole = np.ascontiguousarray(np.concatenate([r["text"], r["size"].astype("<u2").view(np.uint8).reshape(len(r), 2), np.zeros((len(r), -(self.width + 2) % 8), np.uint8)], axis=1)).view(U64)
        a = b = np.zeros(len(r), U64)
        for i in range(whole.shape[1]):
            a = mix64(a + whole[:, i] * U64(0x9E3779B97F4A7C15 + 2 * i))
            b = mix64((b ^ whole[:, i]) * U64(0xD6E8FEB86659FD93 + 2 * i))
        order = np.lexsort((b, a))
        new = np.append(True, (a[order][1:] != a[order][:-1]) | (b[order][1:] != b[order][:-1]))
        group = np.empty(len(r), np.int64)
        group[order] = np.cumsum(new) - 1
        return group, order[new]

    def decide(self, records, source):
        """Anchors in ranges of about _INDEXED super-strings, one index each: equal windows have equal anchors."""
        if not len(records):
            return _by_source(source, np.zeros(0), np.zeros(0), self.length)
        order = np.argsort(records["anchor"], kind="stable")
        anchors = records["anchor"][order]
        cuts = np.unique(np.searchsorted(anchors, anchors[np.arange(0, len(anchors), _INDEXED)], "left"))
        done = [self._decide(records[part], source[part]) for part in np.split(order, cuts[1:])]
        return tuple(np.concatenate(x) for x in zip(*done, strict=True))

    def _decide(self, records, source):
        group, one = self._equal(records)
        least = np.full(len(one), _LAST, np.int64)
        np.minimum.at(least, group, records["doc"])
        anchor = records["anchor"][one]
        _, which, often = np.unique(anchor, return_inverse=True, return_counts=True)
        mixed = often[which] > 1  # super-strings that share an anchor with a different one
        place = np.cumsum(mixed) - 1
        ids = np.zeros((0, 0), np.int64)
        if mixed.any():
            ids = RunLengthIndex(records["text"][one[mixed]], records["size"][one[mixed]], self.length).least_ids(least[mixed])
        rows, starts, sizes, sources = [], [], [], []

        def mark(which_, start, size):
            rows.append(records["row"][which_]), starts.append(start), sizes.append(size), sources.append(source[which_])

        plain = np.flatnonzero(~mixed[group] & (least[group] < records["doc"]))
        mark(plain, records["at"][plain].astype(np.int64), records["size"][plain].astype(np.int64))
        for part in np.array_split(np.flatnonzero(mixed[group]), max(1, len(records) // 50_000)):
            hit = ids[place[group[part]]] < records["doc"][part][:, None] if ids.shape[1] else np.zeros((len(part), 0), bool)
            i, o = np.nonzero(hit)
            mark(part[i], records["at"][part[i]].astype(np.int64) + o, np.full(len(i), self.length, np.int64))
        return _by_source(*(np.concatenate(x) for x in (sources, rows, starts)), np.concatenate(sizes))

    def drop(self, text, marks):
        spans = list(zip(marks["start"].tolist(), marks["end"].tolist(), strict=True))
        if self.whole_characters:
            spans = [s for s in (self._shrunk(text, a, b) for a, b in spans) if s[0] < s[1]]
        if not spans:
            return text, len(text), 0, spans
        out, at = [], 0
        for a, b in spans:
            out.append(text[at:a])
            at = b
        kept = b"".join([*out, text[at:]])
        return kept, len(text), len(text) - len(kept), spans


    @staticmethod
    def _shrunk(text: bytes, a: int, b: int) -> tuple[int, int]:
        while a < b and text[a] & 0xC0 == 0x80:
            a += 1
        while a < b < len(text) and text[b] & 0xC0 == 0x80:
            b -= 1
        return a, b


def drop_repeated_bytes(docs: DataFrame, length: int = 50, key: str = "doc_id", text: str = "text", carry: tuple[str, ...] = (), whole_characters: bool = False) -> DataFrame:
    """Each text without the bytes that a text of smaller id has too: (key, carried, kept binary, n_units, n_removed, spans)."""
    return without_repeats(docs, ByteRepeats(length, whole_characters=whole_characters), key, text, carry)


def op1_runlength(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = drop_repeated_bytes(table(spark, sf_dir, "documents"))
    return done.select("doc_id", F.col("n_units").alias("n_bytes"), "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


ORACLE = """
WITH t AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h, octet_length(encode(coalesce(text, ''))) AS n FROM documents),
starts AS (SELECT doc_id, unnest(range(0, greatest(n - 49, 0))) AS p FROM t),
grams AS (SELECT s.doc_id, s.p, md5(substr(t.h, 2 * s.p + 1, 100)) AS k FROM starts s JOIN t USING (doc_id)),
least AS (SELECT k, min(doc_id) AS d FROM grams GROUP BY k HAVING min(doc_id) < max(doc_id)),
hit AS (SELECT g.doc_id, g.p FROM grams g JOIN least l ON g.k = l.k WHERE l.d < g.doc_id),
run AS (SELECT doc_id, p, CASE WHEN p <= lag(p) OVER (PARTITION BY doc_id ORDER BY p) + 50 THEN 0 ELSE 1 END AS new FROM hit),
num AS (SELECT doc_id, p, sum(new) OVER (PARTITION BY doc_id ORDER BY p) AS g FROM run),
span AS (SELECT doc_id, min(p) AS a, max(p) + 50 AS b FROM num GROUP BY doc_id, g),
edge AS (SELECT doc_id, a, b FROM span UNION ALL SELECT doc_id, n AS a, n AS b FROM t),
gap AS (SELECT doc_id, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a, b), 0) AS x, a AS y FROM edge),
kept AS (SELECT g.doc_id, string_agg(substr(t.h, 2 * g.x + 1, 2 * (g.y - g.x)), '' ORDER BY g.x, g.y) AS h FROM gap g JOIN t USING (doc_id) GROUP BY g.doc_id)
SELECT t.doc_id, t.n::BIGINT AS n_bytes, coalesce(s.gone, 0)::BIGINT AS n_removed, coalesce(s.c, 0)::BIGINT AS n_spans, sha256(unhex(k.h)) AS kept_sha256
FROM t JOIN kept k USING (doc_id) LEFT JOIN (SELECT doc_id, sum(b - a) AS gone, count(*) AS c FROM span GROUP BY doc_id) s USING (doc_id)
"""
