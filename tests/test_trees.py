"""Scopes of trees are counted, and one source is searched without a Spark round a level."""

from pathlib import Path

import numpy as np
import pytest

from pathload import queries
from pathload.operators.graph import Graph
from pathload.plans import scopes
from pathload.plans.kernel import Block, Net
from pathload.queries import register_all

TINY = "/root/testdata/sf0.001"


@pytest.mark.parametrize("n, trees, near", [(1, 1, 1), (2, 1, 1), (2, 2, 1), (40, 1, 1), (60, 1, 5), (90, 4, 90), (200, 60, 200)])
def test_counted_trees_equal_searched_ones(n, trees, near):
    rng = np.random.default_rng(n)
    at = rng.permutation(n)
    ends = np.sort(np.array([(at[i], at[rng.integers(max(0, i - near), i)]) for i in range(trees, n)], np.int32).reshape(-1, 2), axis=1)
    vertex, edge = Block(Net(n, *ends.T), np.arange(n)).loads()
    assert np.allclose(scopes.tree_loads(n, *ends.T, "vertex"), vertex) and np.allclose(scopes.tree_loads(n, *ends.T, "edge"), edge)


def test_trees_beside_other_scopes(spark, monkeypatch):
    monkeypatch.setattr(scopes, "SHARED", 6)
    rng = np.random.default_rng(7)
    pairs = [(int(a), int(b)) for a, b in rng.integers(0, 30, (70, 2)) if a != b]  # not a tree
    pairs += [(40 + i, 40 + (i - 1) // 2) for i in range(1, 25)] + [(70 + i, 71 + i) for i in range(20)] + [(100, 101), (103, 104), (104, 105), (103, 105)]
    graph = Graph.from_edges(spark.createDataFrame([(f"v{a:03}", f"v{b:03}") for a, b in pairs], "src string, dst string"), vertices=spark.createDataFrame([("alone",)], "id string"))
    ends = scopes.ends_of(graph)
    vertex, edge = Block(Net(len(ends.ids), ends.src, ends.dst), np.arange(len(ends.ids))).loads()
    got = {r["id"]: r["vbc"] for r in scopes.loads_of(spark, ends, "vertex").vertex.collect()}
    assert sorted(got) == ends.ids and np.allclose([got[x] for x in ends.ids], vertex)
    got = {(r["src"], r["dst"]): r["ebc"] for r in scopes.loads_of(spark, ends, "edge").edge.collect()}
    assert len(got) == len(edge) and np.allclose([got[ends.ids[a], ends.ids[b]] for a, b in zip(ends.src, ends.dst)], edge)


@pytest.mark.parametrize("directed", [False, True])
def test_distances_of_one_source(spark, directed):
    pairs = [(i, i + 1) for i in range(50)] + [(3, 20), (60, 5), (70, 71)]
    graph = Graph.from_edges(spark.createDataFrame([(f"v{a:02}", f"v{b:02}") for a, b in pairs], "src string, dst string"), directed=directed)
    ends = scopes.ends_of(graph)
    for source in (0, 5, 51):
        d = Block(Net(len(ends.ids), ends.src, ends.dst, directed), np.array([source]), dependencies=False).d[0]
        got = {(r["s"], r["t"]): r["d"] for r in scopes.distances_from(graph, ends.ids[source]).collect()}
        assert got == {(ends.ids[source], ends.ids[i]): k for i, k in enumerate(d.tolist()) if k >= 0}


def test_a_long_conversation_takes_no_round_a_turn(spark, tmp_path, monkeypatch):
    """The source that updates are picked by lies in conversation 0, which has 300 turns."""
    for p in Path(TINY).glob("*.parquet"):
        if p.stem != "conversations":
            (tmp_path / p.name).symlink_to(p)
    kinds = {f.name: f.dataType.simpleString() for f in spark.read.parquet(f"{TINY}/conversations.parquet").schema}
    rows = spark.range(701).selectExpr("id AS c", "explode(sequence(0, IF(id = 0, 299, 4))) AS t")
    values = {"conv_id": "c", "turn": "t"}
    rows.selectExpr(*(f"CAST({values.get(x, repr('x'))} AS {kind}) AS {x}" for x, kind in kinds.items())).write.parquet(f"{tmp_path}/conversations.parquet")
    picked = []
    chosen = queries.chosen
    monkeypatch.setattr(queries, "chosen", lambda *a: picked.extend(chosen(*a)) or picked)
    monkeypatch.setattr(queries, "level", None)  # its search joins once a level
    got = {r["id"]: r["vbc"] for r in register_all()[0]["inc_sparse_attach"](spark, str(tmp_path)).collect()}
    pairs = [(f"t{c}_{t}", f"t{c}_{t + 1}") for c in range(701) for t in range(4 if c else 299)] + [(x.u, x.v) for x in picked]
    ids = sorted({x for pair in pairs for x in pair})
    at = {x: i for i, x in enumerate(ids)}
    assert len(picked) == 1 and sorted(got) == ids and len(ids) == 3800
    net, want = Net(len(ids), *np.array([(at[u], at[v]) for u, v in pairs]).T), np.zeros(len(ids))
    for lo in range(0, len(ids), 500):
        want += Block(net, np.arange(lo, min(len(ids), lo + 500))).loads("vertex")[0]
    assert np.allclose([got[x] for x in ids], want, atol=2e-6)
    assert sum(x.split("_")[0] == "t0" for p in picked for x in (p.u, p.v)) == 1  # the edge joins it to another
