"""Words that simple fingerprints confuse, columns of any name, counts and sums over results, crowded anchors."""

import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathload.llm import common, jaccard, packing, runlength, toxicity, windows
from tests.llm.test_operators import DOCS, corpus, frame, plain_bytes


def twins(steps=9):
    """Two words of 2**steps letters on which every polynomial fingerprint modulo 2**64 agrees."""
    word = "a"
    swap = str.maketrans("ab", "ba")
    for _ in range(steps):
        word += word.translate(swap)
    return word, word.translate(swap)


def test_word_numbers_follow_bytes():
    rng = random.Random(3)
    words = [*twins(), *twins(), *twins(12), *("".join(rng.choice("ab") for _ in range(rng.randint(1, 30))) for _ in range(500))]
    data = np.frombuffer(" ".join(words).encode(), np.uint8)
    start, end, _ = common.word_spans(data, np.array([0, len(data)]))
    number, place = common.word_numbers(data, start, end)
    assert len(place) == len(set(words)) and all(words[place[k]] == w for k, w in zip(number.tolist(), words))
    assert [len(set(common.word_hashes(data, start, end, i).tolist())) for i in (0, 1)] == [len(set(words))] * 2


def test_word_numbers_survive_equal_fingerprints(monkeypatch):
    monkeypatch.setattr(common, "word_hashes", lambda data, start, end, which=0: np.zeros(len(start), np.uint64))
    words = "b a b cc a d cc b".split()
    data = np.frombuffer(" ".join(words).encode(), np.uint8)
    start, end, _ = common.word_spans(data, np.array([0, len(data)]))
    number, place = common.word_numbers(data, start, end)
    assert len(place) == 4 and [words[place[k]] for k in number] == words


@pytest.mark.parametrize("length", [1, 3, 4, 5, 35])
def test_runs_by_doubling(length):
    x = np.random.default_rng(1).integers(0, 2, 400)
    runs = [tuple(x[i : i + length]) for i in range(len(x) - length + 1)]
    for got in (common.run_numbers(x, length), common.run_hashes(common.mix64(x), length)):
        assert len(got) == len(runs) and len(set(zip(got.tolist(), runs))) == len(set(runs)) == len(set(got.tolist()))


def test_twins_in_joins_and_windows(spark):
    a, b = twins()
    rows = [(1, f"x {a} y z w"), (2, f"x {b} y z w"), (3, f"x {a} y z w v")]
    got = {r["doc_id"]: r["component_id"] for r in jaccard.jaccard_components(frame(spark, rows), 4, 60).collect()}
    assert got == {1: 1, 2: 2, 3: 1}
    shared = " ".join(f"s{i}" for i in range(34))
    done = windows.drop_repeated_windows(frame(spark, [(1, f"{shared} {a}"), (2, f"{shared} {b}")])).collect()
    assert [r["n_removed"] for r in done] == [0, 0]


def test_twins_in_packing_and_sums_over_it(spark):
    a, b = twins()
    docs = frame(spark, [(1, a), (2, b), (3, None), (4, "one two " * 3000)])
    whole = packing.word_ids(packing.default_path("word_bpe_49k.json"))
    pieces = packing.token_pieces(docs)
    got = {r["doc_id"]: r["ids_crc32"] for r in pieces.where("doc_id < 3").collect()}
    assert got == {i: zlib.crc32(np.append(whole._library([w])[0], np.uint32(1)).tobytes()) for i, w in ((1, a), (2, b))}
    placed = packing.pack(pieces)
    n = pieces.count()
    assert placed.count() == n and placed.agg(F.sum("length")).first()[0] == pieces.agg(F.sum("length")).first()[0]
    assert placed.select("doc_id").join(docs, "doc_id").count() == n
    odd = packing.pack(pieces.withColumn("part", F.lit(7)).withColumn("size", F.lit("x")))
    assert odd.where("part = 7 and size = 'x' and sequence_id >= 0").count() == n


def test_crowded_anchors_are_split(spark, monkeypatch):
    rng = random.Random(9)
    phrase = "this phrase is in very many places. "
    rows = [(i, "".join(rng.choice("abc") for _ in range(40)) + phrase + "".join(rng.choice("abc") for _ in range(40))) for i in range(300)]
    rows += [(1000 + i, rows[i][1][10:100]) for i in range(0, 300, 3)]
    kind = runlength.ByteRepeats()
    data, off = common.text_buffer(frame(spark, rows).select("text").toArrow().column(0))
    ids = frame(spark, rows).select("doc_id").toArrow().column(0).combine_chunks()
    anchors = np.unique(kind.anchors(data, off))
    seen, often = np.unique(kind.anchors(data, off), return_counts=True)
    most = []
    for crowded in (anchors[:0], seen[often > 20]):
        key, records, _ = kind.windows(data, off, ids, anchors, crowded)
        _, n = np.unique(key, return_counts=True)
        most.append(n.max())
    assert most[1] < most[0] / 4
    from pathload.llm import anchored

    monkeypatch.setattr(anchored, "CROWDED", 20)
    got = {r["doc_id"]: bytes(r["kept"]) for r in runlength.drop_repeated_bytes(frame(spark, rows)).collect()}
    assert got == plain_bytes(rows)


def test_common_phrase_goes_to_many_owners(spark):
    """A phrase in many documents whose surroundings differ: windows travel under their own hashes."""
    rng = random.Random(4)
    phrase = " ".join(f"p{i}" for i in range(20))
    rows = [(i, " ".join(f"w{rng.random()}" for _ in range(30)) + f" {phrase} " + " ".join(f"w{rng.random()}" for _ in range(30))) for i in range(2000)]
    kind = windows.WordRepeats()
    data, off = common.text_buffer(frame(spark, rows).select("text").toArrow().column(0))
    anchors = np.unique(kind.anchors(data, off))
    key, _, _ = kind.windows(data, off, None, anchors, anchors[:0])
    from pathload.llm.anchored import owner_of

    n = np.bincount(owner_of(key, 64), minlength=64)
    assert n.max() < 2 * n.mean()


def test_carried_columns_of_any_name(spark):
    rows = corpus(20, 5)
    docs = frame(spark, rows)
    odd = docs.select("*", *(F.lit(i).alias(c) for i, c in enumerate(("kept", "part", "Spans", "n_units", "source_", "bucket", "block", "marks"))))
    done = runlength.drop_repeated_bytes(odd, carry=("kept", "part", "Spans", "n_units", "bucket", "block", "marks"))
    assert {r["doc_id"]: bytes(r["kept_"]) for r in done.collect()} == plain_bytes(rows)
    assert done.where("kept = 0 and part = 1 and Spans = 2").count() == len(rows)
    done = windows.drop_repeated_windows(odd, carry=("kept", "part"))
    assert done.where("kept = 0 and part = 1 and length(kept_) >= 0").count() == len(rows)
    labels = spark.createDataFrame([(i, 1, i % 2) for i in range(20)], "doc_id bigint, quality int, toxic int")
    model = toxicity.learn(toxicity.labelled(docs, labels))
    clash = docs.select("*", F.lit(1).alias("raw__"), F.lit(2).alias("score"))
    assert toxicity.without_toxic(clash, model).where("raw__ = 1 and score = 2").count() == toxicity.without_toxic(docs, model).count()


def test_empty_text_scores_the_curve(spark):
    labels = spark.createDataFrame([(i, 1, int(i % 4 == 0)) for i in range(200)], "doc_id bigint, quality int, toxic int")
    docs = spark.createDataFrame([(i, "you idiot" if i % 4 == 0 else "you friend", "en", "s", 1) for i in range(200)] + [(900, "", "en", "s", 0), (901, None, "en", "s", 0), (901, None, "en", "s", 0)], DOCS)
    model = toxicity.learn(toxicity.labelled(docs, labels))
    got = toxicity.score_toxicity(docs, model).where("doc_id >= 900").collect()
    assert len(got) == 3 and all(abs(r["score"] - 1 / (1 + np.exp(-model["shift"]))) < 1e-12 and r["predicted"] == 0 for r in got)
    long = "you friend " * 200_000
    assert toxicity.raw_score(long + " idiot", '{" idiot ": 5.0}') > 0
