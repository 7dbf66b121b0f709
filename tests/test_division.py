"""Whole divisions: until no edge is left, against a plain one."""

import test_whole

from pathload.operators import community
from pathload.queries import register_all
from pathload.operators.graph import Graph


def parts_of(ids, pairs):
    root = {x: x for x in ids}
    for _ in ids:
        for a, b in pairs:
            root[a] = root[b] = min(root[a], root[b])
    return root


def plain_division(pairs):
    ids = sorted({x for p in pairs for x in p})
    now, steps = sorted(pairs), []
    members = [(0, x, c) for x, c in parts_of(ids, now).items()]
    parts = len(set(parts_of(ids, now).values()))
    while now:
        loads = {e: round(x + 1e-9, 6) for e, x in test_whole.brute_loads(now)[1].items()}
        top = min(loads, key=lambda e: (-loads[e], e))
        now.remove(top)
        root = parts_of(ids, now)
        if len(set(root.values())) > parts:
            members += [(len(steps) + 1, x, c) for x, c in root.items()]
        parts = len(set(root.values()))
        steps.append((len(steps) + 1, *top, loads[top], parts))
    return steps, members


def plain_modularity(pairs, members):
    out = {}
    for step in {m[0] for m in members}:
        c = {x: y for s, x, y in members if s == step}
        share = {}
        for p in pairs:
            for x in p:
                share[c[x]] = share.get(c[x], 0) + 1 / (2 * len(pairs))
        out[step] = sum(c[a] == c[b] for a, b in pairs) / len(pairs) - sum(x * x for x in share.values())
    return out


def test_whole_division(spark):
    pairs = [("a", "b"), ("a", "c"), ("b", "c"), ("c", "d"), ("d", "e"), ("d", "f"), ("e", "f")]
    gr = Graph.from_edges(spark.createDataFrame(pairs, "src string, dst string"))
    steps, members = plain_division(pairs)
    for engine in ("incremental", "recompute"):
        out = community.divisive(gr, engine=engine)
        assert [tuple(r) for r in out.steps.orderBy("step").collect()] == steps
        assert sorted(map(tuple, out.members.collect())) == sorted(members)
    got = {r[0]: r[1] for r in community.modularity(gr, out.members).collect()}
    want = plain_modularity(pairs, members)
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-9 for k in want)
    tree = {tuple(r) for r in community.hierarchy(out.members).collect()}
    at = {(s, x): c for s, x, c in members}
    order = sorted({s for s, _ in at})
    assert tree == {(s, at[s, x], at[before, x]) for before, s in zip(order, order[1:]) for x in "abcdef"}


def test_registered_division_has_no_step_limit(spark, monkeypatch):
    asked = []

    def noted(graph, max_steps=None, min_components=None, engine="incremental"):
        asked.append(max_steps)
        raise StopIteration

    monkeypatch.setattr(community, "divisive", noted)
    for name in ("steps", "steps_recompute", "components", "modularity", "hierarchy"):
        try:
            register_all()[0][f"community_{name}"](spark, test_whole.TINY)
        except StopIteration:
            pass
    assert asked == [None] * 5
