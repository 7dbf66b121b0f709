"""Scopes of few hubs and many rims: loads of one block, also where edges lie inside a side."""

import numpy as np
import pytest

from pathload import queries
from pathload.plans import scopes, sides
from pathload.plans.kernel import Block, Net
from pathload.queries import register_all

TINY = "/root/testdata/sf0.001"


def graph(seed):
    """Two or so groups of hubs and rims, some edges inside a side or between groups, some vertices without edges."""
    rng = np.random.default_rng(seed)
    n, a, b = 0, [], []
    for _ in range(int(rng.integers(1, 4))):
        p, q = int(rng.integers(5, 60)), int(rng.integers(2, 10))
        m = int(rng.integers(p, 4 * p))
        a += (n + rng.integers(0, p, m)).tolist()
        b += (n + p + rng.integers(0, q, m)).tolist()
        n += p + q
    x = int(rng.integers(0, 5))
    a, b = np.array(a + rng.integers(0, n, x).tolist()), np.array(b + rng.integers(0, n, x).tolist())
    key = np.unique(np.minimum(a, b) * n + np.maximum(a, b))
    key = key[key // n != key % n]
    return n, key // n, key % n


@pytest.mark.parametrize("seed", range(12))
def test_two_sides_equal_one_block(seed, monkeypatch):
    monkeypatch.setattr(sides, "RIMS", (4, 16, 1024)[seed % 3])
    n, a, b = graph(seed)
    hub = sides.hubs(n, a, b)
    assert (hub[a] | hub[b]).all()
    cross = hub[a] != hub[b]
    flows = sides.Flows(sides.Sides.of(hub, scopes.labels(n, a[cross], b[cross]), a, b))
    for lo, hi in flows.sides.jobs(7):
        flows.add(lo, hi)
    assert np.allclose(flows.loads(), Block(Net(n, a, b), np.arange(n)).loads("vertex")[0], rtol=1e-10)


@pytest.mark.parametrize("seed", range(12))
def test_parts_behind_bridges_count_as_ends(seed, monkeypatch):
    monkeypatch.setattr(scopes, "SHARED", 3)
    monkeypatch.setattr(scopes, "TWO_SIDED", 1 << 20)
    rng = np.random.default_rng(seed)
    a, b, first = [], [], [0]
    for _ in range(3):  # groups in a chain, one edge apart; now and then both at one vertex
        p, q = int(rng.integers(30, 50)), int(rng.integers(2, 5))
        a += [first[-1] + x for x in range(p) for _ in range(2)]
        b += [first[-1] + p + int(x) for _ in range(p) for x in rng.choice(q, 2, replace=False)]
        first.append(first[-1] + p + q)
    a += [0, first[1] + seed % 2]
    b += [first[1], first[2] + 3]
    n = first[-1]
    key = np.unique(np.minimum(a, b) * n + np.maximum(a, b))
    a, b = key // n, key % n
    label, stay, weight, behind = scopes.parted(n, scopes.labels(n, a, b), a, b)
    assert (~stay).sum() == 2
    got = behind
    for r in np.unique(label):
        own = np.flatnonzero(label == r)
        at = np.cumsum(label == r) - 1
        use = stay & (label[a] == r)
        x, y = at[a[use]], at[b[use]]
        hub = sides.hubs(len(own), x, y)
        flows = sides.Flows(sides.Sides.of(hub, np.zeros(len(own), int), x, y, weight[own]))
        for lo, hi in flows.sides.jobs(7):
            flows.add(lo, hi)
        got[own] += flows.loads()
    assert np.allclose(got, Block(Net(n, a, b), np.arange(n)).loads("vertex")[0], rtol=1e-10)


def test_supply_is_not_searched_by_lists(spark, monkeypatch):
    query = register_all()[0]["inc_mixed_supply"]
    kept = {r["id"]: r["vbc"] for r in query(spark, TINY).collect()}
    monkeypatch.setattr(queries, "STATE_BYTES", 0)
    monkeypatch.setattr(scopes, "SHARED", 8)
    for name in ("Block", "Net", "Dense"):  # neither lists nor a matrix of all pairs
        monkeypatch.setattr(scopes, name, None if name != "Dense" else type("Dense", (), {}))
    got = {r["id"]: r["vbc"] for r in query(spark, TINY).collect()}
    assert set(got) == set(kept) and np.allclose([got[x] for x in kept], list(kept.values()), rtol=1e-9, atol=2e-6)


@pytest.mark.parametrize("picked", [0, 200, 1 << 40])
@pytest.mark.parametrize("seed", range(8))
def test_edge_loads_of_two_sides_equal_one_block(seed, picked, monkeypatch):
    monkeypatch.setattr(sides, "RIMS", (4, 16, 1024)[seed % 3])
    monkeypatch.setattr(sides, "PICKED", picked)  # all by lists, as counted, all by products
    monkeypatch.setattr(sides, "PICKS", 7)
    n, a, b = graph(seed)
    hub = sides.hubs(n, a, b)
    cross = hub[a] != hub[b]
    flows = sides.Flows(sides.Sides.of(hub, scopes.labels(n, a[cross], b[cross]), a, b, edges=True))
    for lo, hi in flows.sides.jobs(7):
        flows.add(lo, hi)
    vertex, edge = Block(Net(n, a, b), np.arange(n)).loads()
    assert np.allclose(flows.loads(), vertex, rtol=1e-10) and np.allclose(flows.edge_loads(), edge, rtol=1e-10)


@pytest.mark.parametrize("name", ["inv_sum_vbc", "inv_sum_ebc", "static_vbc_blocks", "static_ebc_only", "op_dense_rank_load", "op_cume_dist_load", "op_percent_rank_load", "op_ntile_load"])
def test_large_static_runs_are_not_searched_by_lists(spark, name, monkeypatch):
    from pathload.plans import blocks

    query = register_all()[0][name]
    kept = sorted(map(tuple, query(spark, TINY).collect()))
    monkeypatch.setattr(blocks, "SCOPES_FROM", 0)
    monkeypatch.setattr(blocks, "run_blocks", None)
    monkeypatch.setattr(scopes, "SHARED", 8)
    monkeypatch.setattr(scopes, "TWO_SIDED", 1 << 20)
    got = sorted(map(tuple, query(spark, TINY).collect()))
    assert [x[:-1] for x in got] == [x[:-1] for x in kept] and np.allclose([x[-1] for x in got], [x[-1] for x in kept], rtol=1e-9, atol=2e-6)
