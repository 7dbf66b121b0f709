"""Substring dedup by words, with a count-min prefilter.

Partitions' sketches of windows are added up by cell ranges and overestimate each
window's count, so none that repeats is lost (see anchored). Only windows estimated
at two or more are then grouped exactly, by two independent fingerprints of 64 bits
of their words, each owner taking a range of the windows' own hashes: a common phrase
whose surroundings differ has many different windows, and those go to many owners.

Contracts: null and empty texts have no words; texts of fewer words than a window
keep everything; equal rows repeat each other; a null id is an id of its own row;
an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from pathload.llm.anchored import INTERVAL, Repeats, anchors_of, cover, without_repeats
from pathload.llm.common import U64, doc_slices, run_hashes, table, word_hashes, word_spans


class WordRepeats(Repeats):
    """Windows of `window` words that occur anywhere else too."""

    record = np.dtype([("a", "<u8"), ("b", "<u8"), ("row", "<u4"), ("at", "<u4")])
    spacing = 64

    def __init__(self, window: int = 35):
        self.window = window
        self.gram = min(8, window)

    def _slice(self, data: np.ndarray, off: np.ndarray):
        """Word hashes, the gram hashes, each window's anchor, and which windows stay inside a text."""
        start, end, words = word_spans(data, off)
        h = word_hashes(data, start, end)
        grams = run_hashes(h, self.gram)
        anchor = anchors_of(grams, self.window - self.gram + 1)
        doc = np.repeat(np.arange(len(off) - 1), np.diff(words))[: len(anchor)]
        inside = np.arange(len(anchor)) + self.window <= words[1:][doc]
        return start, end, words, h, grams, anchor, doc, inside

    def anchors(self, data, off):
        found = [np.zeros(0, U64)]
        for a, b in doc_slices(off):
            *_, grams, anchor, _, inside = self._slice(data[off[a] : off[b]], off[a : b + 1] - off[a])
            at = anchor[inside]
            found.append(grams[at[np.append(True, at[1:] != at[:-1])]] if len(at) else np.zeros(0, U64))
        return np.concatenate(found)

    def windows(self, data, off, keys, suspects, crowded):
        parts = [np.zeros(0, self.record)]
        for a, b in doc_slices(off) if len(suspects) else ():
            part, own = data[off[a] : off[b]], off[a : b + 1] - off[a]
            start, end, words, h, grams, anchor, doc, inside = self._slice(part, own)
            key = grams[anchor]
            at = np.minimum(np.searchsorted(suspects, key), len(suspects) - 1)
            use = np.flatnonzero(inside & (suspects[at] == key))
            if not len(use):
                continue
            out = np.empty(len(use), self.record)
            out["a"] = run_hashes(h, self.window)[use]
            out["b"] = run_hashes(word_hashes(part, start, end, 1), self.window, 1)[use]
            out["row"], out["at"] = doc[use] + a, use - words[doc[use]]
            parts.append(out)
        r = np.concatenate(parts)
        r = r[np.lexsort((r["b"], r["a"]))]
        first = self._first(r)
        at = np.flatnonzero(first)
        many = np.repeat(np.diff(np.append(at, len(r))) > 1, np.diff(np.append(at, len(r))))
        settled = cover(r["row"][many], r["at"][many], self.window)
        return r["a"][at], r[at], settled

    @staticmethod
    def _first(r: np.ndarray) -> np.ndarray:
        if not len(r):
            return np.zeros(0, bool)
        return np.append(True, (r["a"][1:] != r["a"][:-1]) | (r["b"][1:] != r["b"][:-1]))

    def decide(self, records, source):
        order = np.lexsort((records["b"], records["a"]))
        r, source = records[order], source[order]
        size = np.diff(np.append(np.flatnonzero(self._first(r)), len(r)))
        many = np.repeat(size > 1, size)
        return _by_source(source[many], r["row"][many], r["at"][many], self.window)

    def drop(self, text, marks):
        words = text.split()
        n = len(words)
        spans = list(zip(marks["start"].tolist(), marks["end"].tolist(), strict=True))
        for a, b in reversed(spans):
            del words[a:b]
        return b" ".join(words), n, n - len(words), spans


def _by_source(source: np.ndarray, row: np.ndarray, at: np.ndarray, length) -> tuple[np.ndarray, np.ndarray]:
    """Intervals within each source's rows."""
    tos, marks = [np.zeros(0, np.int64)], [np.zeros(0, INTERVAL)]
    order = np.argsort(source, kind="stable")
    s = source[order]
    cut = np.flatnonzero(np.diff(s)) + 1
    for part in np.split(order, cut) if len(s) else ():
        m = cover(row[part], at[part], length if np.isscalar(length) else length[part])
        tos.append(np.full(len(m), source[part[0]], np.int64))
        marks.append(m)
    return np.concatenate(tos), np.concatenate(marks)


def drop_repeated_windows(docs: DataFrame, window: int = 35, key: str = "doc_id", text: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """Each text without the words that repeated windows cover: (key, carried, kept binary, n_units, n_removed, spans)."""
    return without_repeats(docs, WordRepeats(window), key, text, carry)


def op10_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = drop_repeated_windows(table(spark, sf_dir, "documents"))
    return done.select("doc_id", F.col("n_units").alias("n_words"), "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


ORACLE = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents),
starts AS (SELECT doc_id, unnest(range(1, greatest(len(words) - 33, 1))) AS i FROM w),
grams AS (SELECT s.doc_id, s.i, array_to_string(list_slice(w.words, s.i, s.i + 34), ' ') AS g FROM starts s JOIN w USING (doc_id)),
many AS (SELECT md5(g) AS k FROM grams GROUP BY 1 HAVING count(*) > 1),
hit AS (SELECT doc_id, i FROM grams WHERE md5(g) IN (SELECT k FROM many)),
gone AS (SELECT DISTINCT doc_id, i + o AS j FROM hit, (SELECT unnest(range(0, 35)) AS o)),
each AS (SELECT doc_id, unnest(words) AS word, unnest(range(1, len(words) + 1)) AS j FROM w),
kept AS (SELECT e.doc_id, e.word, e.j FROM each e ANTI JOIN gone g ON e.doc_id = g.doc_id AND e.j = g.j),
text AS (SELECT doc_id, count(*) AS n, string_agg(word, ' ' ORDER BY j) AS t FROM kept GROUP BY doc_id)
SELECT w.doc_id, len(w.words)::BIGINT AS n_words, (len(w.words) - coalesce(t.n, 0))::BIGINT AS n_removed, sha256(coalesce(t.t, '')) AS kept_sha256
FROM w LEFT JOIN text t USING (doc_id)
"""
