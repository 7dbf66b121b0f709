"""Graphs and logs of all rows: against brute force on the smallest tables."""

from collections import defaultdict, deque

import pyarrow.parquet as pq

from pathload.queries import mixed_updates, register_all
from pathload.sources.tables import graph_of

TINY = "/root/testdata/sf0.001"


def rows(name):
    return pq.read_table(f"{TINY}/{name}.parquet").to_pylist()


def brute_loads(pairs, edges=True):
    """Loads by counting, for each pair, its shortest paths through each vertex and edge."""
    near = defaultdict(set)
    for a, b in pairs:
        near[a].add(b)
        near[b].add(a)
    far, ways = {}, {}
    for s in near:
        d, w, todo = {s: 0}, {s: 1}, deque([s])
        while todo:
            x = todo.popleft()
            for y in near[x]:
                if y not in d:
                    d[y], w[y] = d[x] + 1, 0
                    todo.append(y)
                if d[y] == d[x] + 1:
                    w[y] += w[x]
        far[s], ways[s] = d, w
    vertex, edge = dict.fromkeys(near, 0.0), {tuple(sorted(p)): 0.0 for p in pairs}
    for s in near:
        for t in far[s]:
            for x in far[s]:
                if x not in (s, t) and x in far[t] and far[s][x] + far[t][x] == far[s][t]:
                    vertex[x] += ways[s][x] * ways[t][x] / ways[s][t]
            for a, b in edge if edges else ():
                for u, v in ((a, b), (b, a)):
                    if u in far[s] and v in far[t] and far[s][u] + 1 + far[t][v] == far[s][t]:
                        edge[a, b] += ways[s][u] * ways[t][v] / ways[s][t]
    return vertex, edge


def same(got, want):
    assert got.keys() == want.keys()
    assert all(abs(got[k] - want[k]) < 1e-5 for k in want)


def test_supply_of_all_rows(spark):
    customer = {r["o_orderkey"]: r["o_custkey"] for r in rows("orders")}
    pairs = {(f"c{customer[r['l_orderkey']]}", f"s{r['l_suppkey']}") for r in rows("lineitem")}
    queries, _ = register_all()
    vertex, _ = brute_loads(pairs, False)
    same({r["id"]: r["vbc"] for r in queries["static_vbc_supply"](spark, TINY).collect()}, vertex)
    now = set(pairs)
    for x in mixed_updates(spark, graph_of(spark, TINY, "supply"), 2):
        (now.add if x.op == "add" else now.discard)(tuple(sorted((x.u, x.v))))
    after, _ = brute_loads(now, False)
    same({r["id"]: r["vbc"] for r in queries["inc_mixed_supply"](spark, TINY).collect()}, after)


def test_users_of_all_rows(spark):
    events = rows("events")
    hours = defaultdict(set)
    for r in events:
        if r["event_type"] == "purchase":
            hours[r["ts"].replace(minute=0, second=0, microsecond=0)].add(r["user_id"])
    pairs = {tuple(sorted((f"u{a}", f"u{b}"))) for who in hours.values() for a in who for b in who if a < b}
    queries, _ = register_all()
    vertex, edge = brute_loads(pairs)
    same({r["id"]: r["vbc"] for r in queries["static_vbc_auto"](spark, TINY).collect()}, vertex)
    same({(r["src"], r["dst"]): r["ebc"] for r in queries["static_ebc_blocks_coactive"](spark, TINY).collect()}, edge)
    errors = [r["user_id"] for r in sorted((r for r in events if r["event_type"] == "error"), key=lambda r: (r["ts"], r["event_id"]))]
    pairs = {tuple(sorted((f"u{a}", f"u{b}"))) for a, b in zip(errors, errors[1:]) if a != b}
    same({r["id"]: r["vbc"] for r in queries["static_vbc_users"](spark, TINY).collect()}, brute_loads(pairs, False)[0])


def test_logs_of_all_rows(spark):
    n = sum(r["event_type"] == "purchase" for r in rows("events"))
    queries, _ = register_all()
    assert queries["online_lateness"](spark, TINY).count() == n - 1


def test_no_query_reads_a_part():
    """Derived graphs keep no condition that picks rows by value, quantity or id."""
    from pathload.sources.tables import GRAPHS

    for sql, _ in GRAPHS.values():
        assert not any(x in sql for x in ("value >", "l_quantity >", "custkey <", "LIMIT"))
