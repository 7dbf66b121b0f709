"""Connected components of a graph given as edges, without collecting any of it.

Edges are rewritten by alternating star steps: every vertex hands its larger
neighbours to its least neighbour, then its smaller ones. Edge sets shrink to stars
around component minima in a number of rounds logarithmic in the diameter. Each round
is two aggregations and two equi-joins whose right side has one row a vertex, so
a hub's edges can be split by adaptive skew handling.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, functions as F


def shared_folder(spark: SparkSession) -> str:
    """A fresh folder below spark.checkpoint.dir; a temporary one only where that setting is unset (local mode)."""
    base = spark.conf.get("spark.checkpoint.dir", None) or f"{tempfile.gettempdir()}/pathload-shared"
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


def cut_lineage(df: DataFrame) -> DataFrame:
    """The frame written to the shared folder and read back."""
    path = shared_folder(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def forget(spark: SparkSession, path: str) -> None:
    """Deletes a folder that nothing will read again."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def cut_and_forget(df: DataFrame, before: str | None) -> tuple[DataFrame, str]:
    """The frame written and read back, and its folder; what the step before wrote goes when this step's is there."""
    path = shared_folder(df.sparkSession)
    df.write.parquet(path)
    if before is not None:
        forget(df.sparkSession, before)
    return df.sparkSession.read.schema(df.schema).parquet(path), path


def _stars(edges: DataFrame, larger: bool) -> DataFrame:
    """One star step over edges (a > b)."""
    if larger:
        arcs = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).union(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
    else:
        arcs = edges.select(F.col("a").alias("u"), F.col("b").alias("v"))
    least = arcs.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    moved = arcs.join(least, "u").where(F.col("v") > F.col("u") if larger else F.lit(True)).select(F.col("v").alias("a"), F.col("m").alias("b"))
    if not larger:
        moved = moved.union(least.select(F.col("u").alias("a"), F.col("m").alias("b")))
    return moved.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def component_roots(links: DataFrame, left: str = "a", right: str = "b", rounds: int = 60) -> DataFrame:
    """(id, root) for each vertex of the links: root is the least vertex of its component."""
    edges = links.where(F.col(left).isNotNull() & F.col(right).isNotNull()).select(F.greatest(left, right).alias("a"), F.least(left, right).alias("b")).distinct()
    every = edges.select(F.explode(F.array("a", "b")).alias("id")).distinct()
    edges, path = cut_and_forget(edges.where("a <> b"), None)
    seen = None
    for _ in range(rounds):
        edges, path = cut_and_forget(_stars(_stars(edges, True), False), path)
        sign = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if sign == seen:
            break
        seen = sign
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return every.join(edges.select(F.col("a").alias("id"), F.col("b").alias("root")), "id", "left").select("id", F.coalesce("root", "id").alias("root"))
