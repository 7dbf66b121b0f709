"""Divisive communities: the edge of most load goes, loads are renewed, again and again."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, functions as F

from pathload.operators.components import cut_lineage
from pathload.operators.graph import Graph, components, without_edge
from pathload.operators.update import Session, Update
from pathload.plans.blocks import static_betweenness


@dataclass
class Division:
    """steps: (step, src, dst, ebc, n_components); members: (step, id, component) at the start and after each split."""

    steps: DataFrame
    members: DataFrame


def heaviest(edges: DataFrame) -> tuple[str, str, float] | None:
    """The edge of most load; loads are rounded so that noise can't choose, ties go to the least ids."""
    top = edges.select("src", "dst", F.round(F.col("ebc") + 1e-9, 6).alias("ebc")).orderBy(F.desc("ebc"), "src", "dst").first()
    return None if top is None else (top["src"], top["dst"], float(top["ebc"]))


def divisive(graph: Graph, max_steps: int | None = None, min_components: int | None = None, engine: str = "incremental") -> Division:
    """Removes edges until none, max_steps or min_components is reached. engine: 'incremental', or 'recompute' as the baseline."""
    spark = graph.spark
    session = Session.start(graph) if engine == "incremental" else None
    if session is None:
        graph = Graph(cut_lineage(graph.edges), graph.directed, cut_lineage(graph.vertices))
    now = session.graph if session else graph
    members = [cut_lineage(components(now).select(F.lit(0).alias("step"), "id", "component"))]
    parts = members[0].select("component").distinct().count()
    steps = []
    while max_steps is None or len(steps) < max_steps:
        top = session.heaviest() if session else heaviest(static_betweenness(now, kind="edge").edge)
        if top is None or (min_components is not None and parts >= min_components):
            break
        step = len(steps) + 1
        if session:
            session = session.apply([Update("remove", top[0], top[1], step)])
            now = session.graph
            split = (step, "detach") in session.counts
        else:
            now = without_edge(now, top[0], top[1])
            now = Graph(cut_lineage(now.edges), now.directed, graph.vertices)
            split = True
        if split:
            own = cut_lineage(components(now).select(F.lit(step).alias("step"), "id", "component"))
            count = own.select("component").distinct().count()
            if count > parts:
                members.append(own)
            parts = count
        steps.append((step, *top, parts))
    out = members[0]
    for m in members[1:]:
        out = out.unionByName(m)
    return Division(spark.createDataFrame(steps, "step int, src string, dst string, ebc double, n_components int"), out)


def hierarchy(members: DataFrame) -> DataFrame:
    """(step, component, parent): each component of a split and the one it lay in before."""
    order = members.select("step").distinct()
    earlier = order.alias("x").join(order.alias("y"), F.col("y.step") < F.col("x.step")).groupBy(F.col("x.step").alias("step")).agg(F.max("y.step").alias("before"))
    old = members.select(F.col("step").alias("before"), "id", F.col("component").alias("parent"))
    return members.join(earlier, "step").join(old, ["before", "id"]).select("step", "component", "parent").distinct()


def modularity(graph: Graph, members: DataFrame) -> DataFrame:
    """(step, modularity) of each split, on the original graph."""
    m = graph.edges.count()
    a, b = members.toDF("step", "src", "ca"), members.toDF("step", "dst", "cb")
    inside = graph.edges.join(a, "src").join(b, ["step", "dst"]).groupBy("step").agg(F.sum((F.col("ca") == F.col("cb")).cast("int")).alias("inside"))
    ends = graph.edges.select(F.explode(F.array("src", "dst")).alias("id")).groupBy("id").count()
    share = members.join(ends, "id").groupBy("step", "component").agg(F.sum("count").alias("k")).groupBy("step").agg(F.sum(F.pow(F.col("k") / (2.0 * m), 2)).alias("expected"))
    return inside.join(share, "step").select("step", (F.col("inside") / m - F.col("expected")).alias("modularity"))
