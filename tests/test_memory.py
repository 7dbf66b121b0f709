"""Memory and results of round 2's findings: work arrays stay small on dense graphs; cases without path state."""

import tracemalloc

import duckdb
import numpy as np
import pytest

from pathload.plans import kernel
from pathload.plans.kernel import Block, Net
from pathload.queries import register_all

TINY = "/root/testdata/sf0.001"


def by_sql(name):
    con = duckdb.connect()
    for t in ("nation", "supplier", "events"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{TINY}/{t}.parquet'")
    return sorted(con.execute(register_all()[1][name]).fetchall(), key=str)


def test_static_run_of_a_dense_graph_is_unfolded_in_parts():
    n = 300
    src, dst = np.triu_indices(n, 1)
    tracemalloc.start()
    vertex, edge = Block(Net(n, src, dst), np.arange(n)).loads()
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert (vertex == 0).all() and (edge == 2).all()
    assert peak < 120e6  # 27 million arcs of one level took over 1 GB


@pytest.mark.parametrize("directed", [False, True])
def test_whole_levels_and_parts_agree(directed, monkeypatch):
    rng = np.random.default_rng(3)
    for n, m in ((40, 60), (40, 300), (30, 8), (20, 0)):
        e = rng.integers(0, n, (m, 2))
        e = np.unique(np.sort(e[e[:, 0] != e[:, 1]], axis=1), axis=0)
        e = e if not directed else np.where(rng.random((len(e), 1)) < 0.5, e, e[:, ::-1])
        seen = []
        for share, arcs in ((0, 1 << 20), (1 << 30, 1 << 20), (1 << 30, 7), (0, 7)):
            monkeypatch.setattr(kernel, "WHOLE_SHARE", share)
            monkeypatch.setattr(kernel, "PASS_ARCS", arcs)
            block = Block(Net(n, e[:, 0], e[:, 1], directed), np.arange(n))
            seen.append((block.d, block.sigma, block.delta, *block.loads()))
        for other in seen[1:]:
            assert (other[0] == seen[0][0]).all() and all(np.allclose(x, y, rtol=1e-12) for x, y in zip(other, seen[0], strict=True))


def test_lists_of_a_changed_net_are_those_of_a_new_one():
    for directed in (False, True):
        a = Net(6, [0, 1, 2], [3, 2, 5], directed)
        b = a.copy()
        b.add(4, 0)
        b.remove(1, 2)
        b.add(2, 1)
        again = Net(6, b.src, b.dst, directed)
        again.alive = b.alive
        again._index()
        for x, y in ((b.out, again.out), (b.into, again.into)):
            assert all((p == q).all() for p, q in zip(x, y, strict=True))
        assert a.find(1, 2) == 1 and len(a.out[1]) == (3 if directed else 6)


def test_case_counts_without_a_skip(spark):
    got = register_all()[0]["op_map_case_counts"](spark, TINY)
    assert sorted(map(tuple, got.collect()), key=str) == by_sql("op_map_case_counts")
    assert dict(got.dtypes)["n_cases"] == "bigint"


@pytest.mark.parametrize("name", ["op_cube_cases", "triage_cases_remove_user_pairs", "anchors_of_removal"])
def test_cases_write_no_path_state(spark, name, monkeypatch):
    from pathload import queries

    monkeypatch.setattr(queries, "packed_run", None)
    got = register_all()[0][name](spark, TINY)
    assert sorted(map(tuple, got.collect()), key=str) == by_sql(name)


def test_anchors_without_such_an_edge(spark, monkeypatch):
    from pathload import queries

    monkeypatch.setattr(queries, "chosen", lambda *a: [])
    got = register_all()[0]["anchors_of_removal"](spark, TINY)
    assert got.columns == ["id"] and not got.collect()


def test_measured_blocks_take_few_sources_at_once(spark, monkeypatch):
    from pathload.operators import experiments
    from pathload.operators.graph import Graph
    from pathload.operators.update import Update

    graph = Graph.from_edges(spark.createDataFrame([(f"v{i}", f"v{(i * i + 1) % 30}") for i in range(30)], "src string, dst string"))
    work = [Update("add", "v3", "v8", 1), Update("remove", "v3", "v8", 2)]
    counts = lambda: [tuple(r) for r in experiments.measured_blocks(graph, work, 2, "MP").select("seq", "block", "affected", "touched", "arcs", "state_bytes").orderBy("seq", "block").collect()]
    whole = counts()
    monkeypatch.setattr(experiments, "sources_at_once", lambda n, m: 4)
    assert counts() == whole


def test_long_sides_are_not_broadcast(spark, monkeypatch):
    from pathload import coverage_queries

    rows = lambda: sorted(map(tuple, coverage_queries.lanes(spark, TINY, "broadcast").collect()))
    plan = lambda: coverage_queries.lanes(spark, TINY, "broadcast")._jdf.queryExecution().optimizedPlan().toString()
    few = rows()
    assert plan().count("strategy=broadcast") == 3
    monkeypatch.setattr(coverage_queries, "BROADCAST_ROWS", 1_000)
    assert plan().count("strategy=broadcast") == 2 and plan().count("strategy=merge") == 1 and rows() == few


def test_triangles_by_bits_and_by_joins_agree(spark, monkeypatch):
    from pathload.operators import graph as g
    from pathload.sources.tables import graph_of

    graph = graph_of(spark, TINY, "coactive")
    joined = []
    real = g.triangles
    monkeypatch.setattr(g, "triangles", lambda x: joined.append(1) or real(x))
    monkeypatch.setattr(g, "BIT_BYTES", 100)  # several ranges of columns
    bits = sorted(map(tuple, g.clustering(graph).collect()))
    assert not joined
    monkeypatch.setattr(g, "BIT_WORK", 0)
    assert sorted(map(tuple, g.clustering(graph).collect())) == bits and joined
