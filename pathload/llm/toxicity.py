"""Toxicity by a weighted lexicon.

Learning: from labelled rows, words and word beginnings (4 to 7 letters, after
folding) are counted by class in Spark; those that are much likelier in toxic
rows become the lexicon, each with its smoothed log odds. Scoring: a text is
lower-cased, homoglyphs and digit or sign substitutions are folded, and one
Aho-Corasick pass finds lexicon entries at word borders. Matches inside exception
phrases don't count. The sum of weights over the logarithm of the text's length
goes through a logistic curve fitted on the same rows.

Contracts: a null or empty text has no matches and gets the curve's lowest value;
rows are scored by themselves, so ties, repeated rows and other columns change
nothing; without labelled rows of both classes the lexicon is empty and every
score is 0. Labels that are null are not learned from.
"""

from __future__ import annotations

import functools
import json
import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from pathload.llm.common import free_name, staged, table

#: Most labelled rows learned from (those of smallest id hash), most lexicon entries, least rows and log odds of an entry.
SAMPLE_ROWS, ENTRIES, LEAST_ROWS, LEAST_ODDS = 20_000, 4096, 5, 2.0
THRESHOLD = 0.7

# Look-alike letters and substitutions.
_LOOKS = {"а": "a", "е": "e", "о": "o", "р": "p", "с": "c", "х": "x", "у": "y", "і": "i", "ѕ": "s", "ј": "j", "ԁ": "d", "ɡ": "g", "ⅼ": "l", "ո": "n", "ν": "v", "ο": "o", "α": "a", "ι": "i", "κ": "k", "ρ": "p", "τ": "t", "υ": "u", "χ": "x", "０": "o", "１": "i", "​": "", "‌": "", "‍": "", "­": "", "﻿": ""}
_DIGITS = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g"}
_WIDE = {chr(0xFF21 + i): chr(0x61 + i) for i in range(26)} | {chr(0xFF41 + i): chr(0x61 + i) for i in range(26)}
_SIGNS = {"@": "a", "$": "s", "!": "i", "|": "l", "+": "t", "€": "e"}
_FOLD = str.maketrans(_LOOKS | _DIGITS | _WIDE)
_SIGN_INSIDE = re.compile(r"(?<=[^\W_])[@$!|+€](?=[^\W_])")
_NOT_WORD = re.compile(r"[\W_]+")

# Phrases in which a lexicon word is no insult.
EXCEPTIONS = ("trash can", "trash bin", "trash talk radio", "clown fish", "circus clown", "idiot proof", "sore loser rule", "pond scum", "stupid simple", "moron test")


def fold(text: str) -> str:
    """Lower case, look-alikes and digits folded, words parted by single spaces, a space at either end."""
    low = text.lower()
    if "@" in low or "$" in low or "!" in low or "|" in low or "+" in low or "€" in low:
        low = _SIGN_INSIDE.sub(lambda m: _SIGNS[m[0]], low)
    return f" {_NOT_WORD.sub(' ', low.translate(_FOLD)).strip()} "


def terms(folded: str) -> set[str]:
    """Words (` word `) and word beginnings (` wor`) of a folded text."""
    words = set(folded.split())
    out = {f" {w} " for w in words}
    for w in words:
        out.update(f" {w[:k]}" for k in range(4, min(7, len(w)) + 1))
    return out


def labelled(docs: DataFrame, labels: DataFrame, label: str = "toxic", rows: int = SAMPLE_ROWS) -> DataFrame:
    """(text, label) of at most `rows` labelled rows outside the held-out third."""
    use = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out("doc_id"))
    use = use.groupBy("doc_id").agg(F.max(label).alias("label")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    return staged(docs.select("doc_id", "text").join(F.broadcast(use), "doc_id").select("text", "label"))  # `rows` bounds what is broadcast


def held_out(key: str):
    return F.crc32(F.col(key).cast("string").cast("binary")) % 3 == 1


def learn(sample: DataFrame, entries: int = ENTRIES, least_rows: int = LEAST_ROWS, least_odds: float = LEAST_ODDS) -> dict:
    """The lexicon and the curve: {"weights": {term: weight}, "slope": , "shift": }."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[int, Counter] = {0: Counter(), 1: Counter()}
        rows = Counter()
        flush = lambda: pa.RecordBatch.from_arrays(
            [pa.array(t := list({**seen[0], **seen[1]}), pa.string()), pa.array([seen[1][x] for x in t], pa.int64()), pa.array([seen[0][x] for x in t], pa.int64())], ["term", "toxic", "clean"]
        )
        for b in batches:
            for text, y in zip(b.column(0), b.column(1), strict=True):
                y = int(bool(y.as_py()))
                seen[y].update(terms(fold(text.as_py() or "")))
                rows[y] += 1
                if len(seen[0]) + len(seen[1]) > 400_000:
                    yield flush()
                    seen[0].clear(), seen[1].clear()
        yield flush()
        yield pa.RecordBatch.from_arrays([pa.array([""]), pa.array([rows[1]], pa.int64()), pa.array([rows[0]], pa.int64())], ["term", "toxic", "clean"])

    counted = sample.mapInArrow(count, "term string, toxic bigint, clean bigint").groupBy("term").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))
    total = counted.where("term = ''").collect()
    pos, neg = (total[0]["toxic"], total[0]["clean"]) if total else (0, 0)
    if not pos or not neg:
        return {"weights": {}, "slope": 0.0, "shift": -50.0}
    odds = F.log((F.col("toxic") + 0.5) / (pos + 1.0)) - F.log((F.col("clean") + 0.5) / (neg + 1.0))
    best = counted.where(f"term <> '' and toxic >= {int(least_rows)}").withColumn("odds", odds).where(F.col("odds") >= least_odds).orderBy(F.desc(F.col("odds") * F.log1p("toxic")), "term").limit(entries).collect()
    found = {r["term"]: r["odds"] for r in best}
    weights: dict[str, float] = {}
    for term in sorted(found, key=lambda t: (len(t), t)):  # a longer entry counts for what it adds to its own beginnings
        had = max((weights[term[:k]] for k in range(5, len(term)) if term[:k] in weights), default=0.0)
        if found[term] > had + 0.25:
            weights[term] = found[term] - had
    model = {"weights": weights, "slope": 0.0, "shift": 0.0}
    scored, raw = _raw(sample.select("text", "label"), model)
    scored = scored.select(raw, "label").collect()  # two numbers a row of the bounded sample
    x = np.array([r[raw] for r in scored])
    y = np.array([float(bool(r["label"])) for r in scored])
    return model | dict(zip(("slope", "shift"), _curve(x, y), strict=True))


def _curve(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Logistic slope and shift by Newton's method with a small ridge."""
    a, c = 0.0, math.log((y.sum() + 1) / (len(y) - y.sum() + 1))
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a * x + c, -35, 35)))
        w = np.maximum(p * (1 - p), 1e-6)
        g = np.array([((y - p) * x).sum() - 1e-2 * a, (y - p).sum()])
        h = np.array([[(w * x * x).sum() + 1e-2, (w * x).sum()], [(w * x).sum(), w.sum()]])
        step = np.linalg.solve(h, g)
        a, c = a + step[0], c + step[1]
        if abs(step).max() < 1e-8:
            break
    return max(float(a), 0.0), float(c)


@functools.lru_cache(maxsize=4)
def _automaton(weights: str):
    import ahocorasick

    found = ahocorasick.Automaton()
    for term, w in json.loads(weights).items():
        found.add_word(term, (len(term), w))
    phrases = ahocorasick.Automaton()
    for p in EXCEPTIONS:
        phrases.add_word(f" {p} ", len(p) + 2)
    if len(found):
        found.make_automaton()
    phrases.make_automaton()
    return found, phrases


def raw_score(text: str, weights: str) -> float:
    """Sum of matched weights (each entry once, half for each repeat up to four), over the logarithm of the number of words."""
    found, phrases = _automaton(weights)
    if not text or not len(found):
        return 0.0
    folded = fold(text)
    matches = list(found.iter(folded))
    if not matches:
        return 0.0
    safe = [(end - n + 1, end) for end, n in phrases.iter(folded)]
    times: Counter = Counter()
    total = 0.0
    for end, (n, w) in matches:
        start = end - n + 1
        if any(a <= start and end <= b for a, b in safe):
            continue
        key = folded[start : end + 1]
        times[key] += 1
        total += w if times[key] == 1 else w / 2 if times[key] <= 4 else 0.0
    return total / math.log(10 + folded.count(" "))


def _raw(docs: DataFrame, model: dict, text: str = "text") -> tuple[DataFrame, str]:
    """All columns of the frame and one more, the text's sum; that column's name."""
    weights = json.dumps(model["weights"], sort_keys=True)
    at = docs.columns.index(text)
    name = free_name("raw", docs.columns)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw = [raw_score(t.as_py() or "", weights) for t in b.column(at)]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(raw, pa.float64())], [*b.schema.names, name])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return docs.mapInArrow(score, f"{kinds}, `{name}` double"), name


def _score(model: dict, raw: str):
    return 1 / (1 + F.exp(-(F.col(raw) * model["slope"] + model["shift"])))


def score_toxicity(docs: DataFrame, model: dict, key: str = "doc_id", text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """(key, score, predicted) of each whole text."""
    scored, raw = _raw(docs.select(key, text), model, text)
    return scored.select(key, _score(model, raw).alias("score")).withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def without_toxic(docs: DataFrame, model: dict, text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """The rows whose texts score below the threshold, with all their columns."""
    scored, raw = _raw(docs, model, text)
    return scored.where(_score(model, raw) < threshold).select(*(f"`{c}`" for c in docs.columns))


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = learn(labelled(docs, table(spark, sf_dir, "labels")))
    return score_toxicity(docs, model).select("doc_id", held_out("doc_id").alias("held_out"), "score", "predicted")
