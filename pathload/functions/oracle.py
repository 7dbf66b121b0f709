"""SQL text that computes loads by definition, for comparison on another engine.

Counts of walks grow by a recursive query; the first length at which a pair appears
is its distance and the count there its number of shortest paths. Loads follow from
the definition over pairs, so nothing here accumulates dependencies.
"""

from __future__ import annotations

from pathload.sources.tables import GRAPHS, WALKS

ROUND = "round({0} + 1e-9, 6)"


def graph_ctes(name: str, g: str = "g") -> list[str]:
    """g(src, dst), arcs(u, v) and v(id)."""
    sql, directed = GRAPHS[name]
    return [f"{g} AS ({sql})", *arc_ctes(directed, g)]


def arc_ctes(directed: bool, g: str = "g", arcs: str = "arcs", v: str = "v") -> list[str]:
    back = "" if directed else f" UNION ALL SELECT dst, src FROM {g}"
    return [f"{arcs} AS (SELECT src AS u, dst AS v FROM {g}{back})", f"{v} AS (SELECT src AS id FROM {g} UNION SELECT dst FROM {g})"]


def path_ctes(depth: int, arcs: str = "arcs", v: str = "v", p: str = "p") -> list[str]:
    """p(s, t, d, sigma) of reachable pairs."""
    return [
        f"walk_{p}(s, t, k, c) AS (SELECT id, id, 0, 1.0::DOUBLE FROM {v} UNION ALL SELECT w.s, a.v, w.k + 1, sum(w.c) FROM walk_{p} w JOIN {arcs} a ON a.u = w.t WHERE w.k < {depth} GROUP BY w.s, a.v, w.k + 1)",
        f"{p} AS MATERIALIZED (SELECT s, t, min(k) AS d, arg_min(c, k) AS sigma FROM walk_{p} GROUP BY s, t)",
    ]


def vbc_ctes(p: str = "p", v: str = "v", out: str = "vbc") -> list[str]:
    return [
        f"on_{out} AS (SELECT a.t AS id, sum(a.sigma * b.sigma / c.sigma) AS x FROM {p} a JOIN {p} b ON b.s = a.t JOIN {p} c ON c.s = a.s AND c.t = b.t WHERE a.d + b.d = c.d AND a.s <> a.t AND b.s <> b.t GROUP BY a.t)",
        f"{out} AS (SELECT v.id, coalesce(x, 0.0) AS vbc FROM {v} v LEFT JOIN on_{out} o ON o.id = v.id)",
    ]


def ebc_ctes(directed: bool, p: str = "p", g: str = "g", arcs: str = "arcs", out: str = "ebc") -> list[str]:
    ends = "e.u AS src, e.v AS dst" if directed else "least(e.u, e.v) AS src, greatest(e.u, e.v) AS dst"
    return [
        f"on_{out} AS (SELECT {ends}, sum(a.sigma * b.sigma / c.sigma) AS x FROM {arcs} e JOIN {p} a ON a.t = e.u JOIN {p} b ON b.s = e.v JOIN {p} c ON c.s = a.s AND c.t = b.t WHERE a.d + 1 + b.d = c.d GROUP BY 1, 2)",
        f"{out} AS (SELECT g.src, g.dst, coalesce(x, 0.0) AS ebc FROM {g} g LEFT JOIN on_{out} o ON o.src = g.src AND o.dst = g.dst)",
    ]


def sql(ctes: list[str], select: str) -> str:
    return f"WITH RECURSIVE {', '.join(ctes)} {select}"


def vbc(name: str, extra: list[str] | None = None, select: str = "SELECT id, round(vbc + 1e-9, 6) AS vbc FROM vbc") -> str:
    return sql(graph_ctes(name) + path_ctes(WALKS[name]) + vbc_ctes() + (extra or []), select)


def ebc(name: str, extra: list[str] | None = None, select: str = "SELECT src, dst, round(ebc + 1e-9, 6) AS ebc FROM ebc") -> str:
    return sql(graph_ctes(name) + path_ctes(WALKS[name]) + ebc_ctes(GRAPHS[name][1]) + (extra or []), select)


def paths(name: str, select: str, extra: list[str] | None = None) -> str:
    return sql(graph_ctes(name) + path_ctes(WALKS[name]) + (extra or []), select)
