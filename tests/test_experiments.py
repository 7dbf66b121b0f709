"""Sessions over the store, restarts, modes, scopes, samples and stateful blocks."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathload.operators import experiments as ex, graph as g
from pathload.operators.state import StateStore
from pathload.operators.update import Session, Update
from pathload.plans.blocks import sampled_betweenness, static_betweenness
from pathload.plans.kernel import Block, Net
from pathload.streaming.stateful import run_stateful_blocks
from pathload.streaming.updates import UpdateSink

PAIRS = [(0, 1), (1, 2), (2, 3), (3, 4), (4, 0), (1, 5), (5, 6), (7, 8)]
SCHEMA = "seq bigint, op string, u string, v string"


def graph(spark, pairs=PAIRS, directed=False):
    return g.Graph.from_edges(spark.createDataFrame([(f"v{a}", f"v{b}") for a, b in pairs], "src string, dst string"), directed=directed)


def same(session, other):
    for part, keys in (("vertex", ["id"]), ("edge", ["src", "dst"])):
        a, b = ({tuple(r[k] for k in keys): r[-1] for r in getattr(x, part).collect()} for x in (session.loads, other))
        assert a.keys() == b.keys() and all(abs(a[k] - b[k]) < 1e-9 for k in a)


def test_skipped_sources_are_not_read_or_written(spark):
    s = Session.start(graph(spark), 3)
    after = s.apply([Update("add", "v2", "v4", 1)])
    du = {r["s"]: (r["d"][2], r["d"][4]) for r in s.state.collect()}
    hit = {x for x, (a, b) in du.items() if a != b}
    assert after.read_rows == len(hit) < len(du)
    written = {r["s"] for r in after.store.rows(after.lineage[-1:], "s").select("s").collect()}
    assert written <= hit
    plan = s.touched_sources([("add", 2, 4, 1)])._jdf.queryExecution().executedPlan().toString()
    assert "sigma" not in plan and "delta" not in plan
    same(after, static_betweenness(after.graph, "block"))
    same(s, static_betweenness(s.graph, "block"))  # the session before still stands


def test_lineages_and_compaction(spark, monkeypatch):
    from pathload.operators import update

    monkeypatch.setattr(update, "COMPACT_AFTER", 2)
    now = Session.start(graph(spark), 2, "cases")
    other = now.apply([Update("remove", "v0", "v1", 9)])
    for i, (op, a, b) in enumerate([("add", "v0", "v7"), ("remove", "v2", "v3"), ("add", "v6", "v8"), ("remove", "v0", "v1")]):
        now = now.apply([Update(op, a, b, i)])
    assert len(now.lineage) <= 2
    same(now, static_betweenness(now.graph, "block"))
    same(now.rebase(), static_betweenness(now.graph, "block"))
    same(other, static_betweenness(other.graph, "block"))


def test_removed_vertices_stay_away_and_may_come_back(spark):
    s = Session.start(graph(spark), 2).remove_vertex("v1", 1)
    ids = {r["id"] for r in s.loads.vertex.collect()}
    assert "v1" not in ids and len(ids) == 8
    later = s.apply([Update("add", "v0", "v2", 9), Update("add", "v0", "v1", 10)])
    assert [why for _, why in later.rejected] == ["unknown vertex"] and "v1" not in {r["id"] for r in later.rebase().loads.vertex.collect()}
    same(later, static_betweenness(later.graph, "block"))
    back = later.add_vertex("v1", ["v3", "v8"], 20).add_vertex("a", ["v1"], 30)
    same(back, static_betweenness(back.graph, "block"))
    gone = back.remove_vertex("a", 40)
    assert "a" not in {r["id"] for r in gone.graph.vertices.collect()}


def test_sink_goes_on_after_a_restart(spark, tmp_path):
    path = str(tmp_path / "store")
    start = Session.start(graph(spark), 2, path=path)
    batch = lambda rows: spark.createDataFrame(rows, SCHEMA)
    one, two = [(1, "add", "v0", "v7"), (2, "add", "znew", "v3")], [(3, "remove", "v2", "v3"), (4, "add", "v8", "v4")]
    first = UpdateSink(start)
    first(batch(one), 0)
    again = UpdateSink(start)  # a new driver: nothing but the store is left
    assert again.last == 0 and again.session.lineage == first.session.lineage
    again(batch(one), 0)
    again(batch(two), 1)
    same(again.session, static_betweenness(again.session.graph, "block"))
    assert {r["id"] for r in again.session.loads.vertex.collect()} >= {"znew", "v8"}
    store = StateStore(spark, path)
    unsealed = store.write(store.rows([0], "s").drop("version"))  # a batch that died before its manifest
    assert unsealed not in store.versions() and UpdateSink(start).last == 1
    third = UpdateSink(start)
    third(batch([(5, "remove", "v0", "v7")]), 2)
    same(third.session, static_betweenness(third.session.graph, "block"))


@pytest.mark.parametrize("directed", [False, True])
def test_kept_lists_equal_scans(directed):
    rng = random.Random(4)
    for _ in range(6):
        n = rng.randint(4, 10)
        pairs = sorted({tuple(rng.sample(range(n), 2)) if directed else tuple(sorted(rng.sample(range(n), 2))) for _ in range(2 * n)})
        blocks = [Block(Net(n, [a for a, _ in pairs], [b for _, b in pairs], directed), np.arange(n), predecessors=p) for p in (True, False)]
        for _ in range(12):
            a, b = rng.sample(range(n), 2)
            op = "remove" if blocks[0].net.find(a, b) >= 0 else "add"
            for x in blocks:
                x.apply(op, a, b, "cases")
            for x, y in zip(blocks[0].loads(), blocks[1].loads()):
                assert np.allclose(x, y)
            assert sorted(zip(*(x.tolist() for x in blocks[0].lists))) == sorted(zip(*(x.tolist() for x in blocks[1]._path_arcs())))
        assert blocks[0].state_bytes() > blocks[1].state_bytes()


def test_modes_agree_on_work(spark):
    gr = graph(spark)
    work = [Update("add", "v0", "v7", 1), Update("remove", "v2", "v3", 2)]
    rows = {m: {r["seq"]: (r["affected"], r["touched"]) for r in ex.cumulative(ex.measured_blocks(gr, work, 2, m)).collect()} for m in ("MP", "MO")}
    session, stored = ex.stored_run(gr, work, 2)
    assert rows["MP"] == rows["MO"] == {r["seq"]: (r["affected"], r["touched"]) for r in stored}
    mix = {(r["seq"], r["case"]): r["n"] for r in session.log.collect()}
    assert all(sum(n for (s, c), n in mix.items() if s == seq and c not in ("touched", "skip")) == rows["MO"][seq][0] for seq in (1, 2))
    assert all(sum(n for (s, c), n in mix.items() if s == seq and c != "touched") == 9 for seq in (1, 2))
    assert ex.scaling_runs(gr, work, (1, 2)).count() == 2 == ex.scaling_runs(gr, work, (1, 2), True).count()


def test_case_mix_against_one_block(spark):
    gr = graph(spark)
    work = [Update("add", "v0", "v7", 1), Update("remove", "v2", "v3", 2), Update("remove", "v7", "v8", 3)]
    csr = g.to_csr(gr)
    place = {v: i for i, v in enumerate(csr.ids.tolist())}
    block = Block(Net(len(place), csr.src, csr.dst), np.arange(len(place)))
    want = {}
    for x in work:
        for case, n in block.apply(x.op, place[x.u], place[x.v])["cases"].items():
            want[x.seq, case] = n
    log = Session.start(gr, 3).apply(work).log.where("case <> 'touched'")
    assert {(r["seq"], r["case"]): r["n"] for r in log.collect()} == want


def test_biconnected_against_cuts():
    rng = random.Random(8)
    for _ in range(30):
        n = rng.randint(3, 9)
        pairs = sorted({tuple(sorted(rng.sample(range(n), 2))) for _ in range(rng.randint(2, 14))})
        csr = g.Csr(np.arange(n).astype(object), np.array([a for a, _ in pairs]), np.array([b for _, b in pairs]), False)
        component, size = ex.biconnected(csr)

        def linked(x, y, cut):
            seen, todo = {x}, [x]
            while todo:
                a = todo.pop()
                for p in pairs:
                    if a in p and (b := p[1 - p.index(a)]) not in seen and b != cut:
                        seen.add(b)
                        todo.append(b)
            return y in seen

        for k, (a, b) in enumerate(pairs):
            scope = {a, b} | {x for x in range(n) if x not in (a, b) and all(linked(x, b if c == a else a, c) for c in range(n) if c != x)}
            assert size[component[k]] == len(scope)


def test_sampled_error_shrinks(spark):
    pairs = [(a, b) for a, b in itertools.combinations(range(14), 2) if (a * 7 + b * 3) % 4 == 0] + [(i, i + 1) for i in range(13)]
    gr = graph(spark, pairs)
    exact = {r["id"]: r["vbc"] for r in static_betweenness(gr, "block").vertex.collect()}
    whole = sampled_betweenness(gr, 100).collect()
    assert all(abs(r["vbc"] - exact[r["id"]]) < 1e-9 and r["error"] == 0 for r in whole)
    some = sampled_betweenness(gr, 7).collect()
    assert np.mean([abs(r["vbc"] - exact[r["id"]]) <= 3 * r["error"] + 1e-9 for r in some]) > 0.8


def test_kinds_and_restricted_operations(spark):
    gr = graph(spark)
    both = static_betweenness(gr, "block")
    for plan in ("block", "level"):
        v, e = static_betweenness(gr, plan, kind="vertex"), static_betweenness(gr, plan, kind="edge")
        assert v.edge.count() == 0 == e.vertex.count()
        assert {r["id"]: round(r["vbc"], 9) for r in v.vertex.collect()} == {r["id"]: round(r["vbc"], 9) for r in both.vertex.collect()}
        assert {(r["src"], r["dst"]): round(r["ebc"], 9) for r in e.edge.collect()} == {(r["src"], r["dst"]): round(r["ebc"], 9) for r in both.edge.collect()}
    only = Session.start(gr, 2, ops=("add",)).apply([Update("remove", "v0", "v1", 1), Update("add", "v0", "v2", 2)])
    assert [why for _, why in only.rejected] == ["unknown operation"]
    same(only, static_betweenness(only.graph, "block"))


def test_stateful_blocks_over_two_runs(spark, tmp_path):
    gr = graph(spark)
    put = lambda rows: spark.createDataFrame(rows, SCHEMA).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    run = lambda: run_stateful_blocks(spark.readStream.schema(SCHEMA).parquet(str(tmp_path / "in")), gr, 2, checkpoint=str(tmp_path / "c"), out=str(tmp_path / "o"))
    put([(2, "remove", "v2", "v3"), (1, "add", "v0", "v7")])
    run()
    put([(3, "add", "v2", "v8"), (4, "add", "v0", "v1"), (5, "remove", "v1", "v5")])
    loads = run()
    now = [p for p in PAIRS if p not in ((2, 3), (1, 5))] + [(0, 7), (2, 8)]
    again = static_betweenness(g.Graph(graph(spark, now).edges, False, gr.vertices), "block")

    class Done:
        pass

    done = Done()
    done.loads = loads
    same(done, again)
