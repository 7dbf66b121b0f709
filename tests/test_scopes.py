"""Batches without path state: results of sessions, whatever the scopes are like."""

import numpy as np
import pytest

from pathload import queries
from pathload.operators.graph import Graph
from pathload.plans import scopes
from pathload.plans.kernel import Block, Net
from pathload.queries import register_all

TINY = "/root/testdata/sf0.001"
NAMES = ["inc_mixed_one_block", "inc_directed_batch_ebc", "inc_mixed_batch_ebc", "inc_sparse_attach_cases", "inc_remove_vertex", "inc_add_vertex_ebc", "inc_chain_detach"]


@pytest.mark.parametrize("name", NAMES)
def test_large_state_is_not_kept(spark, name, monkeypatch):
    query = register_all()[0][name]
    kept = sorted(map(tuple, query(spark, TINY).collect()))
    monkeypatch.setattr(queries, "STATE_BYTES", 0)
    monkeypatch.setattr(queries, "Session", None)  # no row a source is written
    got = query(spark, TINY)
    assert [t for _, t in got.dtypes] == ["string"] * (len(got.columns) - 1) + ["double"]
    got = sorted(map(tuple, got.collect()))
    assert [x[:-1] for x in got] == [x[:-1] for x in kept] and np.allclose([x[-1] for x in got], [x[-1] for x in kept], atol=2e-6)


@pytest.mark.parametrize("directed", [False, True])
@pytest.mark.parametrize("shared", [1, 6, 512])
def test_scopes_dense_and_sparse_equal_one_block(spark, directed, shared, monkeypatch):
    rng = np.random.default_rng(4)
    pairs = [(int(a) + o, int(b) + o) for o, n, m in ((0, 12, 60), (20, 12, 8), (40, 30, 70), (80, 3, 2)) for a, b in rng.integers(0, n, (m, 2)) if a != b]
    graph = Graph.from_edges(spark.createDataFrame([(f"v{a:03}", f"v{b:03}") for a, b in pairs], "src string, dst string"), directed=directed, vertices=spark.createDataFrame([("alone",)], "id string"))
    monkeypatch.setattr(scopes, "SHARED", shared)
    monkeypatch.setattr(scopes, "TILE", 8)
    monkeypatch.setattr(scopes, "DENSE", 8)
    monkeypatch.setattr(scopes, "TASK_CELLS", 40)
    ends = scopes.ends_of(graph)
    ends = scopes.edited(ends, [("add", "v000", "v025"), ("add", "v000", "v025"), ("remove", "v000", "v025"), ("add", "v081", "v021"), ("add", "new", "v041"), ("remove", "v001", "v999")], ("new",))
    vertex, edge = Block(Net(len(ends.ids), ends.src, ends.dst, directed), np.arange(len(ends.ids))).loads()
    got = {r["id"]: r["vbc"] for r in scopes.loads_of(spark, ends, "vertex").vertex.collect()}
    assert sorted(got) == ends.ids and "alone" in got and np.allclose([got[x] for x in ends.ids], vertex)
    got = {(r["src"], r["dst"]): r["ebc"] for r in scopes.loads_of(spark, ends, "edge").edge.collect()}
    assert np.allclose([got[ends.ids[a], ends.ids[b]] for a, b in zip(ends.src, ends.dst)], edge) and len(got) == len(edge)


def test_updates_are_checked_in_turn(spark):
    ends = scopes.Ends(["a", "b", "c"], np.array([0, 1], np.int32), np.array([1, 2], np.int32), False)
    now = scopes.edited(ends, [("remove", "b", "a"), ("remove", "a", "b"), ("add", "c", "a"), ("add", "a", "a"), ("add", "a", "x")])
    assert list(zip(now.src.tolist(), now.dst.tolist())) == [(0, 2), (1, 2)]
    now = scopes.edited(ends, [], (), "b")
    assert now.ids == ["a", "c"] and not len(now.src)
    empty = scopes.Ends([], np.zeros(0, np.int32), np.zeros(0, np.int32), False)
    assert scopes.loads_of(spark, empty, "vertex").vertex.collect() == [] and scopes.loads_of(spark, empty, "edge").edge.collect() == []
