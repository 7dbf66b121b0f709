"""Training-data operators against plain versions, with nulls, empty texts, ties and repeated rows."""

import base64
import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest

from pathload.llm import anchored, bpe, common, forest, jaccard, kdtree, packing, runlength, secrets, toxicity, warc, windows

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def corpus(n=60, seed=1):
    rng = random.Random(seed)
    words = ["".join(rng.choice("abcdeé") for _ in range(rng.randint(1, 7))) for _ in range(400)]
    passage = " ".join(rng.choice(words) for _ in range(60))
    out = []
    for i in range(n):
        t = " ".join(rng.choice(words) for _ in range(rng.randint(0, 200)))
        if i % 3 == 0:
            t += "\n" + passage + " \t" + rng.choice(words)
        if i % 7 == 0 and out:
            t = out[rng.randrange(len(out))][1]
        if i % 11 == 0 and out and out[-1][1]:
            w = out[-1][1].split()
            if len(w) > 40:
                w[5] = "changed"
            t = " ".join(w)
        out.append((i, t))
    return [*out, (n, None), (n + 1, ""), (n + 2, "one two"), (n + 3, "ONE two"), (n + 4, "x " * 9000), (None, passage)]


def frame(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], DOCS)


def plain_bytes(rows, length=50):
    first = {}
    big = 1 << 62
    for i, t in rows:
        b = (t or "").encode()
        for p in range(len(b) - length + 1):
            w = b[p : p + length]
            first[w] = min(first.get(w, big), big if i is None else i)
    out = {}
    for i, t in rows:
        b = (t or "").encode()
        gone = np.zeros(len(b), bool)
        for p in range(len(b) - length + 1):
            if first[b[p : p + length]] < (big if i is None else i):
                gone[p : p + length] = True
        out[i] = bytes(x for x, g in zip(b, gone) if not g)
    return out


def test_bytes(spark):
    rows = corpus()
    got = {r["doc_id"]: bytes(r["kept"]) for r in runlength.drop_repeated_bytes(frame(spark, rows)).collect()}
    assert got == plain_bytes(rows)


def test_bytes_whole_characters(spark):
    rows = [(1, "é" * 60), (2, "a" + "é" * 60 + "b"), (3, "xé" * 40)]
    for r in runlength.drop_repeated_bytes(frame(spark, rows), whole_characters=True).collect():
        bytes(r["kept"]).decode()


def test_index_locates_and_counts():
    rng = random.Random(2)
    strings = sorted({bytes(rng.choice(b"ab") for _ in range(rng.randint(50, 84))) for _ in range(30)})
    block = np.zeros((len(strings), 84), np.uint8)
    for i, s in enumerate(strings):
        block[i, : len(s)] = np.frombuffer(s, np.uint8)
    index = runlength.RunLengthIndex(block, np.array([len(s) for s in strings]))
    place = sorted(((s[o:] + b"", i, o) for i, s in enumerate(strings) for o in range(len(s) + 1)), key=lambda x: (bytes(c + 1 for c in x[0]), x[1]))
    string, offset = index.locate(np.arange(index.rows))
    assert [(a, b) for _, a, b in place] == list(zip(string.tolist(), offset.tolist()))
    ids = np.arange(len(strings))[::-1].copy()
    least = index.least_ids(ids)
    for i, s in enumerate(strings):
        for o in range(len(s) - 49):
            assert least[i, o] == min(ids[j] for j, t in enumerate(strings) if s[o : o + 50] in t)


def test_words(spark):
    rows = corpus(seed=3)
    texts = [re.findall(r"[^\x20\x09-\x0d]+", t or "") for _, t in rows]
    seen = {}
    for w in texts:
        for p in range(len(w) - 34):
            k = tuple(w[p : p + 35])
            seen[k] = seen.get(k, 0) + 1
    want = {}
    for (i, _), w in zip(rows, texts):
        gone = [False] * len(w)
        for p in range(len(w) - 34):
            if seen[tuple(w[p : p + 35])] > 1:
                gone[p : p + 35] = [True] * 35
        want[i] = " ".join(x for x, g in zip(w, gone) if not g)
    got = {r["doc_id"]: bytes(r["kept"]).decode() for r in windows.drop_repeated_windows(frame(spark, rows)).collect()}
    assert got == want


@pytest.mark.parametrize("k,t", [(4, 85), (5, 80)])
def test_jaccard(spark, k, t):
    rows = [r for r in corpus(80, 4)] + [(200 + i, " ".join(["same"] * 3 + [str(j) for j in range(100)] + [f"v{i}"])) for i in range(12)]

    def shingles(text):
        w = re.findall(r"[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        return {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()

    own = [(i, shingles(x)) for i, x in rows if i is not None]
    root = {i: i for i, _ in own}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, (i, x) in enumerate(own):
        for j, y in own[:a]:
            if x and y and 100 * len(x & y) >= t * len(x | y):
                p, q = sorted((find(i), find(j)))
                root[q] = p
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard.jaccard_components(frame(spark, rows), k, t).collect()}
    assert {i: v for i, v in got.items() if i is not None} == {i: (len(x), find(i)) for i, x in own}
    assert got[None][1] is None


def test_squeezed_blocks():
    kind = runlength.ByteRepeats().record
    r = np.zeros(300, kind)
    r["doc"], r["text"] = np.arange(300), 97
    rng = np.random.default_rng(1)
    for records in (r, r[:1], np.frombuffer(rng.bytes(7 * kind.itemsize), kind)):
        blocks = common.squeezed(common.packed(np.zeros(len(records), np.int64), records).column(1), kind)
        back, count = common.opened(pa.chunked_array([blocks, pa.nulls(1, pa.binary())]), kind)
        assert back.tobytes() == records.tobytes() and count.tolist() == [len(records), 0]


def test_merged_sketch_never_low():
    """Cells of several partitions, added up, never estimate below the true count."""
    rng = np.random.default_rng(1)
    h = rng.integers(0, 2**63, 5000).astype(np.uint64)
    parts = [np.concatenate([h[:3000], h[:5]]), np.concatenate([h[2900:4000], np.repeat(h[7], 3000)]), h[3990:]]
    sent = []
    for x in parts:
        cell, n = anchored.partition_sketch(x, 3)
        sent.append((cell, (cell % (2 * anchored.WIDTH) << 8 | np.minimum(n, 255)).astype(np.uint32)))
    two, crowd = {}, {}
    for owner in range(3):
        mine = [(c[c // (2 * anchored.WIDTH) == owner], r[c // (2 * anchored.WIDTH) == owner]) for c, r in sent]
        flags = anchored.merged_sketch(np.concatenate([r for _, r in mine]))
        for c, t, w in zip(np.concatenate([c for c, _ in mine]).tolist(), *(f.tolist() for f in flags)):
            assert two.setdefault(c, t) == t and crowd.setdefault(c, w) == w  # all partitions hear the same
    often = {int(x): sum(int((p == x).sum()) for p in parts) for x in h}
    suspected = 0
    for x, *cells in zip(h.tolist(), *(c.tolist() for c in anchored.sketch_cells(h, 3))):
        estimate = all(two[c] for c in cells)
        assert estimate or often[x] < 2
        suspected += estimate
    assert suspected <= 130


def test_empty_tables(spark):
    docs = frame(spark, []).where("doc_id > 0")
    assert runlength.drop_repeated_bytes(docs).count() == 0
    assert windows.drop_repeated_windows(docs).count() == 0
    assert jaccard.jaccard_components(docs).count() == 0
    assert packing.pack(packing.token_pieces(docs)).count() == 0
    assert bpe.encode_bpe(docs).count() == 0
    assert secrets.scan_secrets(docs).count() == 0
    v = spark.createDataFrame([], "vec_id bigint, embedding array<float>, label int")
    assert forest.near_duplicates(v).count() == 0
    assert kdtree.exact_top_k(kdtree.integer_vectors(v), kdtree.integer_vectors(v)).count() == 0
    pages = spark.createDataFrame([], "page_id bigint, url string, html string")
    assert warc.read_records(warc.normalise(warc.write_archives(warc.choose_records(pages)))).count() == 0
    model = toxicity.learn(toxicity.labelled(docs, spark.createDataFrame([], "doc_id bigint, quality int, toxic int")))
    assert toxicity.score_toxicity(docs, model).count() == 0


TEXTS = ["", "Hello world's end", "a" * 3000, "é日本 ²½ \x85 <|endoftext|> x", "tab\tnew\n\nline  ", "I'll DON'T 123 45", "ǅ İstanbul Σς", "\x1c\x1f ñ"]


def test_bpe_round_trip(spark):
    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(bpe.default_path())
    own = bpe.vocabulary(bpe.default_path())
    rng = random.Random(5)
    for t in TEXTS + ["".join(rng.choice("abc the'sdl \té日1²_-!") for _ in range(50)) for _ in range(300)]:
        ids = whole.encode(t, add_special_tokens=False).ids
        assert own.encode(t) == np.array(ids, np.uint32).tobytes()
        assert own.decode(own.encode(t)).decode() == whole.decode(ids, skip_special_tokens=False)
    rows = bpe.decode_bpe(bpe.encode_bpe(frame(spark, list(enumerate([*TEXTS, None]))))).collect()
    assert {r["doc_id"]: r["text"] for r in rows} == dict(enumerate([*TEXTS, ""]))


def test_word_ids_and_packing(spark):
    w = packing.word_ids(packing.default_path("word_bpe_49k.json"))
    for a, b in zip(w.ids(TEXTS), w._library(TEXTS)):
        assert a.tolist() == b.tolist()
    rows = [*enumerate([*TEXTS, None]), (50, "word " * 9000), (50, "word " * 9000)]
    got = packing.pack(packing.token_pieces(frame(spark, rows))).collect()
    ids = {i: [*x.tolist(), 1] for (i, _), x in zip(rows, w._library([t or "" for _, t in rows]))}
    for r in got:
        part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert len(part) == r["length"] and zlib.crc32(np.array(part, np.uint32).tobytes()) == r["ids_crc32"]
    by = {}
    for r in got:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for places in by.values():
        at = 0
        for o, n in sorted(places):
            assert o == at
            at += n
        assert at <= 4096


def test_best_two_fit_is_tight():
    rng = random.Random(6)
    counts = {}
    for _ in range(5000):
        n = min(4096, int(rng.expovariate(1 / 600)) + 1)
        counts[n] = counts.get(n, 0) + 1
    plan = packing.best_two_fit(counts)
    bins = int(plan[-1, 4] + plan[-1, 2])
    total = sum(n * c for n, c in counts.items())
    assert bins <= -(-total // 4096) * 1.01 + 1
    placed = {}
    for size, _, b, copies, _, _ in plan.tolist():
        placed[size] = placed.get(size, 0) + b * copies
    assert placed == counts


def test_secrets():
    s = lambda t: secrets.joined(secrets.find_spans(t))
    assert s('token = "abcdef"') == "assign:0:15"
    assert s("password=abc") == ""
    assert s("AKIA" + "B" * 16) == "access:0:20"
    assert s("x" + "a" * 24) == "hex:1:25"
    assert s('K = "abcD1234efGH5678"\nauth_token = K') == "literal:5:21"
    assert s("paſſword=abcdef12") == "" and s("") == ""
    assert secrets.redact('a token = "abcdef" b', secrets.find_spans('a token = "abcdef" b')) == 'a [ASSIGN]" b'


def test_warc(spark, tmp_path):
    rows = [(1, "http://a/1", "x"), (2, "http://a/2", "x"), (3, None, None), (4, "u", ""), (5, "u", "<é>" * 500)]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    whole = warc.write_archives(warc.choose_records(pages))
    normal = warc.normalise(whole)
    got = {r["page_id"]: r for r in warc.read_records(normal).collect()}
    for i, _, h in rows:
        raw = (h or "").encode()
        assert got[i]["payload_bytes"] == len(raw)
        assert got[i]["payload_digest"] == base64.b32encode(hashlib.sha1(raw).digest()).decode()
    assert (got[1]["record_type"], got[1]["refers_to"]) == ("revisit", 2) and got[2]["refers_to"] is None
    assert got[3]["refers_to"] == 4 and bytes(got[5]["payload"]).decode() == "<é>" * 500
    warc.export_files(normal, str(tmp_path))
    again = warc.read_records(warc.normalise(warc.import_files(spark, str(tmp_path))))
    assert again.count() == 5
    assert warc.sidecar(normal).count() == 5


def test_toxicity(spark):
    docs = spark.createDataFrame([(i, ("you idiot " if i % 4 == 0 else "you friend ") + f"word{i} again", "en", "s", 1) for i in range(400)] + [(999, None, "en", "s", 0)], DOCS)
    labels = spark.createDataFrame([(i, 1, int(i % 4 == 0)) for i in range(400)] + [(5, 1, None)], "doc_id bigint, quality int, toxic int")
    model = toxicity.learn(toxicity.labelled(docs, labels))
    got = {r["doc_id"]: r["predicted"] for r in toxicity.score_toxicity(docs, model).collect()}
    assert all(got[i] == int(i % 4 == 0) for i in range(400)) and got[999] == 0
    weights = '{" idiot ": 5.0}'
    assert toxicity.raw_score("1D10T!", weights) > 0 and toxicity.raw_score("an idiot proof lid", weights) == 0


def test_forest(spark):
    rng = np.random.default_rng(7)
    base = rng.standard_normal((40, 16))
    x = np.concatenate([base + 0.05 * rng.standard_normal((40, 16)) for _ in range(6)]).astype(np.float32)
    rows = [(i, x[i].tolist(), int(i % 2)) for i in range(len(x))] + [(900, None, 1), (901, [0.0] * 16, 1), (902, [float("nan")] * 16, 1), (903, x[0].tolist(), 0), (904, x[0].tolist(), None), (905, [1.0, 2.0], 1), (906, [2.0, 4.0], 1)]
    v = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>, label int")
    got = {r["vec_id"]: r for r in forest.near_duplicates(v, leaf=32, block=40).collect()}
    ok = [(i, np.array(e, np.float64), y) for i, e, y in rows if e is not None and y is not None and np.isfinite(e).all() and any(e)]
    links = {i: 0 for i, _, _ in rows}
    for a, (i, e, y) in enumerate(ok):
        for j, f, z in ok[:a]:
            if y == z and len(e) == len(f) and e @ f / np.linalg.norm(e) / np.linalg.norm(f) >= 0.98:
                links[i] += 1
                links[j] += 1
    found = sum(r["n_links"] for r in got.values())
    assert found >= 0.9 * sum(links.values()) and all(got[i]["n_links"] <= n for i, n in links.items())
    assert got[905]["component_id"] == got[906]["component_id"] == 905


def planted(n, dim, least, seed=11):
    """n random unit vectors; every fourth is followed by one at a cosine just over `least` to it."""
    rng = np.random.default_rng(seed)
    x = rng.standard_normal((n, dim))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    at = np.arange(0, n - 1, 4)
    side = rng.standard_normal((len(at), dim))
    side -= (side * x[at]).sum(axis=1, keepdims=True) * x[at]
    side /= np.linalg.norm(side, axis=1, keepdims=True)
    cosine = rng.uniform(least + 1e-4, 1, (len(at), 1))
    x[at + 1] = cosine * x[at] + np.sqrt(1 - cosine**2) * side
    return x, at


def test_forest_recall_below_the_root(spark):
    """Production parameters on enough vectors for five levels: planted pairs against brute force."""
    x, at = planted(24_000, 64, 0.98)
    table = pa.table({"vec_id": pa.array(np.arange(len(x))), "embedding": pa.array(list(x), pa.list_(pa.float64())), "label": pa.array(np.zeros(len(x), np.int32))})
    assert forest.Forest(x[:: 2], len(x)).depth == 5
    got = forest.near_duplicates(spark.createDataFrame(table)).where("n_links > 0").toArrow().to_pylist()
    links = 0
    for a in range(0, len(x), 2000):
        links += int((x[a : a + 2000] @ x.T >= 0.98).sum()) - len(x[a : a + 2000])
    found = sum(r["n_links"] for r in got)
    assert links >= 2 * len(at) and 0.99 * links <= found <= links
    assert sum(r["component_id"] != r["vec_id"] for r in got) >= 0.99 * len(at)


def test_kdtree(spark):
    rng = np.random.default_rng(8)
    x = rng.integers(-20, 20, (700, 6)) / 16
    x[600:] = x[3]  # many equal vectors: ties, and a region that needs several shards
    other = rng.integers(-20, 20, (60, 3)) / 16
    rows = [(i, x[i].tolist()) for i in range(700)] + [(800, None), (850, [float("inf")] * 6), (None, [1.0] * 6)] + [(1000 + i, other[i].tolist()) for i in range(60)] + [(2000, [])]
    v = kdtree.integer_vectors(spark.createDataFrame(rows, "vec_id bigint, embedding array<float>"))
    for shard, block in ((60, 3), (10_000, 10_000)):
        got = {}
        for r in kdtree.exact_top_k(v, v.where("vec_id % 50 = 0"), shard=shard, block=block).collect():
            got.setdefault(r["query_id"], []).append((r["rank"], -r["score"], r["vec_id"]))
        assert set(got) == {*range(0, 700, 50), 1000, 1050}
        for first, y in ((0, x), (1000, other)):
            q = np.floor(256 * y.astype(np.float32).astype(np.float64)).astype(int)
            for i in range(0, len(y), 50):
                want = sorted((-int(q[i] @ q[j]), first + j) for j in range(len(y)) if j != i)[:5]
                assert [r[1:] for r in sorted(got[first + i])] == want


def test_kdtree_prunes():
    """Far clusters: most boxes' bounds stay below the kth score, so queries never travel there."""
    rng = np.random.default_rng(3)
    corners = np.array([[1000 * (1 if c >> i & 1 else -1) for i in range(3)] + [0] * 5 for c in range(8)])
    x = np.concatenate([corners[c] + rng.integers(-5, 5, (200, 8)) for c in range(8)])
    regions = kdtree.Regions(x.astype(float), len(x), 200)
    where = regions.of(x.astype(float))
    assert regions.count == 8 and np.bincount(where).max() <= 400
    low, high = (np.array([f(x[where == r], axis=0) for r in range(8)]).astype(float) for f in (np.min, np.max))
    q = x[::50].astype(float)
    kth = np.sort(q @ x.T, axis=1)[:, -6]
    reached = kdtree.bounds(q, low, high) >= kth[:, None]
    assert reached.any(axis=1).all() and reached.sum(axis=1).mean() < 3


WARC_ROWS = [(None, "u", "x"), (1, "u", "x"), (2, "u", "x"), (2, "u", "other"), (3, "u", "x"), (3, "u", "x"), (4, None, None), (None, None, None)]


def test_warc_nulls_and_repeated_ids(spark):
    pages = spark.createDataFrame(WARC_ROWS, "page_id bigint, url string, html string")
    records = warc.read_records(warc.normalise(warc.write_archives(warc.choose_records(pages), archive_bytes=2)))
    got = sorted(((r["page_id"], bytes(r["payload"]).decode(), r["record_type"], r["refers_to"]) for r in records.collect()), key=str)
    want = [(None, "x", "response", None), (1, "", "revisit", 3), (2, "", "revisit", 3), (2, "other", "response", None), (3, "x", "response", None), (3, "x", "response", None), (4, "", "response", None), (None, "", "response", None)]
    assert got == sorted(want, key=str)


def test_warc_archives_are_bounded(spark):
    pages = spark.createDataFrame([(i, "u", "y" * 999 + str(i)) for i in range(300)], "page_id bigint, url string, html string")
    sizes = [len(zlib.decompress(bytes(r["content"]), 31)) for r in warc.write_archives(warc.choose_records(pages), 10_000).collect()]
    assert len(sizes) >= 30 and max(sizes) < 20_000


def test_cut_streams_raise():
    records = [warc.record_bytes(i, "u", b"z" * 500, "D", None, None) for i in range(20)]
    stream = zlib.compressobj(6, zlib.DEFLATED, 31)
    parts = [stream.compress(b"".join(records[:10])) + stream.flush(zlib.Z_FULL_FLUSH), stream.compress(b"".join(records[10:])) + stream.flush()]
    assert len(warc.normalise_stream(b"".join(parts))[1]) == 20
    for cut in (parts[0], b"".join(parts)[:-3], parts[0][:-20]):
        with pytest.raises(ValueError):
            warc.normalise_stream(cut)
    big = zlib.compressobj(9, zlib.DEFLATED, 31)
    bomb = big.compress(b"".join(records) * 400) + big.flush()
    assert len(warc.normalise_stream(bomb, 1 << 12)[1]) == 8000
    assert warc.normalise_stream(b"") == (b"", [])
