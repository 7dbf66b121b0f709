"""The engine against recomputation, closed forms and worked values."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathload.operators import community, graph as g, metrics, online, triage
from pathload.operators.components import component_roots
from pathload.operators.state import StateStore
from pathload.operators.update import Session, Update
from pathload.plans import level
from pathload.plans.blocks import long_state, static_betweenness
from pathload.plans.kernel import Block, Net
from pathload.sources.generator import social
from pathload.streaming.updates import run_update_stream


def net(pairs, n, directed=False):
    return Net(n, [a for a, _ in pairs], [b for _, b in pairs], directed)


def loads(pairs, n, directed=False, **kw):
    v, e = Block(net(pairs, n, directed), np.arange(n), **kw).loads()
    return v.tolist(), e.tolist()


def test_worked_values():
    path = [(0, 1), (1, 2), (2, 3)]
    assert loads(path, 4) == ([0, 4, 4, 0], [6, 8, 6])
    assert loads([*path, (0, 3)], 4) == ([1] * 4, [4] * 4)
    assert loads(path, 4, predecessors=True) == loads(path, 4)
    star = [(0, i) for i in range(1, 6)]
    assert loads(star, 6)[0][0] == 20
    full = [(i, j) for i in range(5) for j in range(i + 1, 5)]
    assert loads(full, 5) == ([0] * 5, [2] * 10)


@pytest.mark.parametrize("pairs,n,op,edge,want", [
    ([(0, 1), (1, 2), (2, 3)], 4, "add", (0, 3), ["rise", "flat_add", "flat_add", "rise"]),
    ([(0, 1), (1, 2), (2, 3), (0, 3)], 4, "remove", (0, 3), ["drop", "flat_remove", "flat_remove", "drop"]),
    ([(0, 1), (1, 2), (0, 2)], 3, "remove", (0, 1), ["drop_one", "drop_one", "skip"]),
    ([(0, 1), (1, 2), (2, 3), (3, 4), (0, 4)], 5, "remove", (0, 1), None),
    ([(0, 1), (2, 3)], 4, "add", (1, 2), ["attach"] * 4),
])
def test_cases(pairs, n, op, edge, want):
    block = Block(net(pairs, n), np.arange(n))
    got = block.apply(op, *edge)["case"].tolist()
    assert got == want if want else got[3] == "skip"


@pytest.mark.parametrize("directed", [False, True])
@pytest.mark.parametrize("strategy", ["uniform", "cases"])
def test_streams_equal_recomputation(directed, strategy):
    rng = random.Random(11)
    for _ in range(8):
        n = rng.randint(4, 12)
        pairs = sorted({tuple(sorted(rng.sample(range(n), 2))) if not directed else tuple(rng.sample(range(n), 2)) for _ in range(2 * n)})
        block = Block(net(pairs, n, directed), np.arange(n))
        v, e = block.loads()
        for _ in range(20):
            alive = [(int(block.net.src[i]), int(block.net.dst[i])) for i in np.flatnonzero(block.net.alive)]
            op, (a, b) = ("remove", rng.choice(alive)) if alive and rng.random() < 0.5 else ("add", rng.sample(range(n), 2))
            if op == "add" and block.net.find(a, b) >= 0:
                continue
            got = block.apply(op, a, b, strategy)
            v = v + got["vertex"]
            e = np.append(e, np.zeros(len(got["edge"]) - len(e))) + got["edge"]
            live = np.flatnonzero(block.net.alive)
            again = Block(Net(n, block.net.src[live], block.net.dst[live], directed), np.arange(n))
            v2, e2 = again.loads()
            assert (again.d == block.d).all() and np.allclose(again.sigma, block.sigma) and np.allclose(again.delta, block.delta)
            assert np.allclose(v, v2) and np.allclose(e[live], e2)


def graph(spark, pairs, directed=False):
    return g.Graph.from_edges(spark.createDataFrame([(f"v{a}", f"v{b}") for a, b in pairs], "src string, dst string"), directed=directed)


def table(df, *keys):
    return {tuple(r[k] for k in keys): r[-1] for r in df.collect()}


def close(a, b):
    assert a.keys() == b.keys()
    assert all(abs(a[k] - b[k]) < 1e-9 for k in a)


PAIRS = [(0, 1), (1, 2), (2, 3), (3, 4), (4, 0), (1, 5), (5, 6), (7, 8)]


def test_plans_agree(spark):
    gr = graph(spark, PAIRS)
    a = static_betweenness(gr, "block", n_blocks=3)
    for other in (static_betweenness(gr, "level"), static_betweenness(gr, "block", predecessors=True, n_blocks=1)):
        close(table(a.vertex, "id"), table(other.vertex, "id"))
        close(table(a.edge, "src", "dst"), table(other.edge, "src", "dst"))


def test_session_batches(spark):
    gr = graph(spark, PAIRS)
    s = Session.start(gr, 3)
    work = [Update("add", "v0", "v7", 1), Update("remove", "v2", "v3", 2), Update("add", "v2", "v2", 3), Update("add", "v0", "v1", 4), Update("remove", "v0", "v8", 5)]
    after = s.apply(work)
    assert sorted(r for _, r in after.rejected) == ["edge exists", "loop", "no such edge"]
    again = static_betweenness(after.graph, "block")
    close(table(after.loads.vertex, "id"), table(again.vertex, "id"))
    close(table(after.loads.edge, "src", "dst"), table(again.edge, "src", "dst"))
    close(table(after.rebase().loads.vertex, "id"), table(again.vertex, "id"))
    one = s.apply(work[:1]).apply(work[1:2])
    close(table(one.loads.edge, "src", "dst"), table(after.loads.edge, "src", "dst"))
    new = after.add_vertex("w", ["v3", "v8"], 6)
    close(table(new.loads.vertex, "id"), table(static_betweenness(new.graph, "block").vertex, "id"))
    gone = new.remove_vertex("w", 8)
    close(table(gone.loads.vertex, "id"), table(after.loads.vertex, "id"))
    assert metrics.work(after.log).count() == 2


def test_stream_and_state(spark, tmp_path):
    gr = graph(spark, PAIRS)
    s = Session.start(gr, 2)
    rows = [(2, "remove", "v2", "v3"), (1, "add", "v0", "v7"), (3, "add", "v6", "znew")]
    f = spark.createDataFrame(rows, "seq bigint, op string, u string, v string").withColumn("ts", F.timestamp_seconds(F.col("seq")))
    f.select("seq", "ts", "op", "u", "v").write.parquet(str(tmp_path / "in"))
    done = run_update_stream(spark.readStream.schema(f.select("seq", "ts", "op", "u", "v").schema).parquet(str(tmp_path / "in")), s)
    close(table(done.loads.vertex, "id"), table(static_betweenness(done.graph, "block").vertex, "id"))
    store = StateStore(spark, str(tmp_path / "state"))
    assert store.versions() == [] and store.commit(s.state, 0) == 0 and store.commit(s.state, 0) == 0
    store.commit(s.state.where("s = 1").withColumn("delta", F.transform("delta", lambda x: x + 1)), 1)
    assert store.versions() == [0, 1] and store.read(("d",)).count() == s.state.count()
    plan = store.read(("d",), 0)._jdf.queryExecution().executedPlan().toString()
    assert "sigma" not in plan
    assert store.read(version=1).where("s = 1").first()["delta"][1] == store.read(version=0).where("s = 1").first()["delta"][1] + 1


def test_triage_and_invariants(spark):
    gr = graph(spark, PAIRS)
    base = static_betweenness(gr, "block", keep_state=True)
    ids = sorted(r[0] for r in gr.vertices.collect())
    state = long_state(base.state, ids)
    a = triage.classify(state, gr.vertices, "v0", "v6", "add")
    b = triage.classify_symmetric(state, gr.vertices, "v0", "v6", "add")
    assert table(a.select("s", "case"), "s") == table(b.select("s", "case"), "s")
    total = state.where("d > 0").agg(F.sum(F.col("d") - 1), F.sum("d")).first()
    assert abs(sum(table(base.vertex, "id").values()) - total[0]) < 1e-9
    assert abs(sum(table(base.edge, "src", "dst").values()) - total[1]) < 1e-9
    flow = level.flows(state, gr).groupBy("s", "w").agg(F.sum("flow").alias("f")).join(state.select("s", F.col("t").alias("w"), "delta"), ["s", "w"])
    assert flow.where(F.abs(F.col("f") - 1 - F.col("delta")) > 1e-9).count() == 0


def test_communities_agree(spark):
    gr = graph(spark, [(0, 1), (1, 2), (0, 2), (2, 3), (3, 4), (4, 5), (3, 5)])
    a = community.divisive(gr, max_steps=3)
    b = community.divisive(gr, max_steps=3, engine="recompute")
    assert [tuple(r) for r in a.steps.collect()] == [tuple(r) for r in b.steps.collect()]
    assert a.steps.first()["src"] == "v2" and a.steps.first()["n_components"] == 2
    assert community.modularity(gr, a.members).count() == 3


def test_empty_and_isolated(spark):
    empty = g.Graph(spark.createDataFrame([], "src string, dst string"), False, spark.createDataFrame([("a",)], "id string"))
    assert [tuple(r) for r in static_betweenness(empty, "block").vertex.collect()] == [("a", 0.0)]
    assert static_betweenness(empty, "level").edge.count() == 0
    assert component_roots(spark.createDataFrame([], "a bigint, b bigint")).count() == 0


def test_dense_index_and_generator(spark):
    gr = social(spark, 300, 4)
    assert gr.edges.count() > 600 and sorted(map(tuple, gr.edges.collect())) == sorted(map(tuple, social(spark, 300, 4).edges.collect()))
    index = g.dense_index(gr).orderBy("pos").collect()
    assert [r["pos"] for r in index] == list(range(len(index))) and [r["id"] for r in index] == sorted(r["id"] for r in index)
    assert g.stats(gr).first()["clustering"] > 0.02


def test_online_formulas(spark):
    f = spark.createDataFrame([(1, 2.0, 1.0), (2, 0.5, 1.0), (3, 0.5, 1.0), (4, 9.0, 1.0)], "seq bigint, t_i double, t_u double")
    p = spark.range(1).select(online.required_parallelism(F.lit(0.1), F.lit(100), F.lit(2.0), F.lit(1.0)).alias("a"), online.required_parallelism(F.lit(0.1), F.lit(100), F.lit(1.0), F.lit(1.0)).alias("b")).first()
    assert p["a"] == 11 and p["b"] is None
    assert [round(r["delay"], 6) for r in online.lateness(f).orderBy("seq").collect()] == [0, 0.5, 0.5, 0]
    assert [round(r["delay"], 6) for r in online.lateness(f, "queued").orderBy("seq").collect()] == [0, 0.5, 1.0, 0]
    assert metrics.state_bytes(1_000_000, 0) == 11e12
