"""The level plan: all sources at once as relations, for graphs that no task can hold.

A round joins the frontier (s, v, sigma) with the arcs, sums the counts of equal
(s, v) and drops what was visited. Accumulation runs the levels backwards. Every
round is written to the shared folder, so plans stay short and lost executors cost
one round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from pathload.operators.components import cut_lineage
from pathload.operators.graph import Graph


def shortest_path_state(graph: Graph, sources: DataFrame | None = None, max_depth: int | None = None) -> DataFrame:
    """(s, t, d, sigma) of all reachable pairs. sources: (id), every vertex by default."""
    start = graph.vertices if sources is None else sources.select("id")
    arcs = cut_lineage(graph.arcs)
    frontier = cut_lineage(start.select(F.col("id").alias("s"), F.col("id").alias("t"), F.lit(0).alias("d"), F.lit(1.0).alias("sigma")))
    levels, seen, depth = [frontier], frontier.select("s", "t"), 0
    while max_depth is None or depth < max_depth:
        depth += 1
        step = frontier.join(arcs, F.col("t") == F.col("u")).groupBy("s", "v").agg(F.sum("sigma").alias("sigma"))
        step = step.select("s", F.col("v").alias("t"), F.lit(depth).alias("d"), "sigma").join(seen, ["s", "t"], "left_anti")
        frontier = cut_lineage(step)
        if frontier.isEmpty():
            break
        levels.append(frontier)
        seen = seen.unionByName(frontier.select("s", "t"))
        if depth % 8 == 0:
            seen = cut_lineage(seen)
    out = levels[0]
    for part in levels[1:]:
        out = out.unionByName(part)
    return out


def flows(state: DataFrame, graph: Graph) -> DataFrame:
    """(s, v, w, flow): what each arc of the path graphs carries. state: (s, t, d, sigma, delta)."""
    up = state.select("s", F.col("t").alias("v"), F.col("d").alias("dv"), F.col("sigma").alias("sv"))
    low = state.select("s", F.col("t").alias("w"), F.col("d").alias("dw"), F.col("sigma").alias("sw"), "delta")
    arcs = graph.arcs.toDF("v", "w")
    return up.join(arcs, "v").join(low, ["s", "w"]).where(F.col("dw") == F.col("dv") + 1).select("s", "v", "w", (F.col("sv") / F.col("sw") * (1 + F.col("delta"))).alias("flow"))


def dependency_state(state: DataFrame, graph: Graph) -> DataFrame:
    """(s, t, d, sigma, delta): dependencies from the deepest level up."""
    state = cut_lineage(state)
    arcs = cut_lineage(graph.arcs)
    depth = state.agg(F.max("d")).first()[0] or 0
    done = [cut_lineage(state.where(F.col("d") == depth).withColumn("delta", F.lit(0.0)))]
    for level in range(depth, 0, -1):
        low = done[-1].select("s", F.col("t").alias("w"), F.col("sigma").alias("sw"), "delta")
        here = state.where(F.col("d") == level - 1)
        up = here.select("s", F.col("t").alias("v"), F.col("sigma").alias("sv"))
        flow = low.join(arcs.toDF("v", "w"), "w").join(up, ["s", "v"])
        part = flow.groupBy("s", F.col("v").alias("t")).agg(F.sum(F.col("sv") / F.col("sw") * (1 + F.col("delta"))).alias("delta"))
        done.append(cut_lineage(here.join(part, ["s", "t"], "left").select("s", "t", "d", "sigma", F.coalesce("delta", F.lit(0.0)).alias("delta"))))
    out = done[0]
    for part in done[1:]:
        out = out.unionByName(part)
    return out


def vertex_load(state: DataFrame, vertices: DataFrame) -> DataFrame:
    """(id, vbc) from dependencies; vertices that nothing depends on have 0."""
    total = state.where("s <> t").groupBy(F.col("t").alias("id")).agg(F.sum("delta").alias("vbc"))
    return vertices.select("id").join(total, "id", "left").select("id", F.coalesce("vbc", F.lit(0.0)).alias("vbc"))


def edge_load(state: DataFrame, graph: Graph) -> DataFrame:
    """(src, dst, ebc) from flows; both directions of an undirected edge add up."""
    flow = flows(state, graph)
    ends = [F.col("v"), F.col("w")] if graph.directed else [F.least("v", "w"), F.greatest("v", "w")]
    total = flow.groupBy(ends[0].alias("src"), ends[1].alias("dst")).agg(F.sum("flow").alias("ebc"))
    return graph.edges.join(total, ["src", "dst"], "left").select("src", "dst", F.coalesce("ebc", F.lit(0.0)).alias("ebc"))
