"""Every stage of the pipeline against a plain version, over one small folder of tables; nulls, repeated rows, odd columns and empty tables."""

import math
import random
import re
import zlib

import corpus_pipeline
import duckdb
import numpy as np
import pytest

from pathload.llm import packing, secrets, toxicity
from tests.llm.test_operators import corpus

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, kept int, part string, score double"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    rng = random.Random(2)
    rows = corpus(70, 6)
    rows += [(100 + i, f"you {'idiot' if i % 3 == 0 else 'friend'} number {rng.random()} said so") for i in range(90)]
    rows += [(300, 'cfg: api_key = "k93jfKdl20sKD83jd0" end'), (301, "AKIA" + "Q" * 16 + " and " + "ab12" * 8), rows[3], rows[3], (302, "Zürich " * 30 + "ß"), (303, "x" + "Zürich " * 30)]
    at = str(tmp_path_factory.mktemp("sf"))
    docs = spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t), 1, "p", 0.5) for i, t in rows], SCHEMA)
    docs.repartition(3).write.parquet(f"{at}/documents.parquet")
    labels = [(100 + i, 1, int(i % 3 == 0)) for i in range(90)] + [(5, 0, None), (None, 0, 1)]
    spark.createDataFrame(labels, "doc_id bigint, quality int, toxic int").write.parquet(f"{at}/labels.parquet")
    return at


@pytest.fixture(scope="module")
def stages(spark, folder):
    """Rows before and after each stage."""
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    out = {}
    for name, stage in corpus_pipeline.STAGES:
        after = corpus_pipeline.staged(stage(spark, docs, folder))
        out[name] = [r.asDict() for r in docs.collect()], [r.asDict() for r in after.collect()], docs.columns, after.columns
        docs = after
    return out


def key(r):
    return tuple(sorted((k, str(v)) for k, v in r.items()))


def test_columns_stay(stages):
    for name, (_, _, before, after) in stages.items():
        assert before == after or name == "packing"


def test_toxic_documents_go(spark, folder, stages):
    before, after, *_ = stages["toxicity"]
    model = toxicity.learn(toxicity.labelled(spark.read.parquet(f"{folder}/documents.parquet"), spark.read.parquet(f"{folder}/labels.parquet")))
    import json

    weights = json.dumps(model["weights"], sort_keys=True)
    score = lambda t: 1 / (1 + math.exp(-(toxicity.raw_score(t or "", weights) * model["slope"] + model["shift"])))
    assert sorted(map(key, after)) == sorted(key(r) for r in before if score(r["text"]) < 0.7)
    gone = {r["doc_id"] for r in before} - {r["doc_id"] for r in after}
    assert gone == {100 + i for i in range(0, 90, 3)}


def test_one_of_each_group_stays(stages):
    before, after, *_ = stages["jaccard_join"]

    def shingles(text):
        w = re.findall(r"[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    own = {r["doc_id"]: shingles(r["text"]) for r in before if r["doc_id"] is not None}
    root = {i: i for i in own}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(own)
    for a in ids:
        for b in ids:
            if a < b and own[a] and own[b] and 100 * len(own[a] & own[b]) >= 80 * len(own[a] | own[b]):
                p, q = sorted((find(a), find(b)))
                root[q] = p
    want = {key(r) for r in before if r["doc_id"] is not None and find(r["doc_id"]) == r["doc_id"]}  # repeated rows count as one
    assert sorted(key(r) for r in after if r["doc_id"] is not None) == sorted(want)
    assert [key(r) for r in after if r["doc_id"] is None] == [key(r) for r in before if r["doc_id"] is None]


def test_repeated_strings_go(stages):
    before, after, *_ = stages["suffix_dedup"]
    big = 1 << 62
    first = {}
    for r in before:
        b = (r["text"] or "").encode()
        for p in range(len(b) - 49):
            first[b[p : p + 50]] = min(first.get(b[p : p + 50], big), big if r["doc_id"] is None else r["doc_id"])
    want = {}
    for r in before:
        b = (r["text"] or "").encode()
        gone = np.zeros(len(b) + 1, bool)
        for p in range(len(b) - 49):
            if first[b[p : p + 50]] < (big if r["doc_id"] is None else r["doc_id"]):
                gone[p : p + 50] = True
        out, at = [], 0
        edges = np.flatnonzero(np.diff(np.concatenate([[0], gone.astype(int)])))
        for x, y in zip(edges[::2].tolist(), edges[1::2].tolist()):
            while x < y and b[x] & 0xC0 == 0x80:
                x += 1
            while x < y < len(b) and b[y] & 0xC0 == 0x80:
                y -= 1
            out.append(b[at:x])
            at = max(x, y)
        want[r["doc_id"]] = b"".join([*out, b[at:]]).decode()
    assert {r["doc_id"]: r["text"] or "" for r in after} == want
    assert all(r["n_chars"] == len(r["text"]) for r in after if r["text"] is not None)


def test_secrets_are_masked(stages):
    before, after, *_ = stages["secret_scan"]
    want = {r["doc_id"]: None if r["text"] is None else secrets.redact(r["text"], secrets.find_spans(r["text"])) for r in before}
    assert {r["doc_id"]: r["text"] for r in after} == want
    assert any("[ASSIGN]" in (t or "") for t in want.values()) and any("[ACCESS]" in (t or "") for t in want.values())


def test_what_is_left_is_packed(stages):
    before, after, *_ = stages["packing"]
    words = packing.word_ids(packing.default_path("word_bpe_49k.json"))
    ids = {r["doc_id"]: [*x.tolist(), 1] for r, x in zip(before, words._library([r["text"] or "" for r in before]))}
    assert {r["doc_id"] for r in after} == set(ids)
    for r in after:
        part = np.array(ids[r["doc_id"]][r["start"] : r["start"] + r["length"]], np.uint32)
        assert len(part) == r["length"] and zlib.crc32(part.tobytes()) == r["ids_crc32"]
    for i, x in ids.items():
        assert sorted(r["start"] for r in after if r["doc_id"] == i) == list(range(0, len(x), 4096))
    places = {}
    for r in after:
        places.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert all([o for o, _ in sorted(p)] == list(np.cumsum([0] + [n for _, n in sorted(p)])[:-1]) and sum(n for _, n in p) <= 4096 for p in places.values())


def test_run_and_empty_tables(spark, folder, stages, tmp_path):
    assert sorted((r["doc_id"] or -1, r["piece"], r["ids_crc32"]) for r in corpus_pipeline.run(spark, folder).collect()) == sorted((r["doc_id"] or -1, r["piece"], r["ids_crc32"]) for r in stages["packing"][1])
    for name in ("documents", "labels"):
        spark.read.parquet(f"{folder}/{name}.parquet").where("false").write.parquet(str(tmp_path / f"{name}.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_base_secrets_against_sql(spark):
    """The base columns of the scan by another engine's patterns, on given documents."""
    at = "/root/testdata/sf0.01"
    got = {r["doc_id"]: (r["n_assign"], r["n_access"], r["n_hex"]) for r in secrets.op2_secrets(spark, at).collect()}
    db = duckdb.connect()
    name = """(?i)(password|passwd|secret|token|api_?key)["']?\\x20*[:=]\\x20*["']?([A-Za-z0-9+/_.=-]+)"""
    rows = db.execute(
        "SELECT doc_id, len(list_filter(regexp_extract_all(coalesce(text, ''), $1, 2), lambda x: len(x) >= 6)), len(list_filter(regexp_extract_all(coalesce(text, ''), 'AKIA[A-Z0-9]+'), lambda x: len(x) >= 20)), "
        f"len(list_filter(regexp_extract_all(coalesce(text, ''), '[0-9a-f]+'), lambda x: len(x) >= 24)) FROM '{at}/documents.parquet'",
        [name],
    ).fetchall()
    assert got == {r[0]: tuple(r[1:]) for r in rows}
    assert sum(n for n, _, _ in got.values()) and sum(n for _, _, n in got.values())
