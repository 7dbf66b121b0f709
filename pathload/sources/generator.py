"""Seeded social graphs: attachment to earlier vertices, with a share of links closed to triangles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from pathload.operators.graph import Graph


def _draw(low: int, *salt):
    """A number in [0, 1) from hashed columns."""
    return F.pmod(F.xxhash64(*salt, F.lit(low)), F.lit(1 << 30)) / float(1 << 30)


def social(spark: SparkSession, n: int, per_vertex: int = 6, closure: float = 0.3, seed: int = 1) -> Graph:
    """About n * per_vertex edges. Every vertex draws earlier ones, older ones more often; a draw with probability
    `closure` goes to one that the first drawn vertex drew itself, which closes a triangle. All draws are hashes of
    (vertex, draw, seed), so the graph is one map over a range and one join, at any size."""
    draws = spark.range(1, n).select("id", F.explode(F.sequence(F.lit(0), F.lit(per_vertex - 1))).alias("k"))
    earlier = lambda v, k: F.floor(F.pow(_draw(seed, v, k), 1.5) * v).cast("bigint")
    first = earlier(F.col("id"), F.lit(0))
    friend = earlier(first, 1 + F.floor(_draw(seed + 2, "id", "k") * (per_vertex - 1)).cast("int"))
    close = (F.col("k") > 0) & (_draw(seed + 1, "id", "k") < closure) & (first > 0)
    to = F.when(close, friend).otherwise(earlier(F.col("id"), F.col("k")))
    name = lambda c: F.format_string("v%09d", c)
    return Graph.from_edges(draws.select(name(F.col("id")).alias("src"), name(to).alias("dst")))


def as_updates(edges: DataFrame) -> DataFrame:
    """Edges (src, dst, ts) as additions in order of time."""
    from pyspark.sql import Window

    return edges.select(F.row_number().over(Window.orderBy("ts", "src", "dst")).cast("bigint").alias("seq"), "ts", F.lit("add").alias("op"), F.col("src").alias("u"), F.col("dst").alias("v"))
