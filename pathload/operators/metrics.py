"""Cost and accuracy measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

#: Bytes of a (source, vertex) cell: distance, count, dependency. The compact widths, and those that this engine stores.
COMPACT, STORED, POINTER = (1, 2, 8), (2, 8, 8), 8


def state_bytes(n: int, m: int, predecessors: bool = False, p: int = 1, widths: tuple[int, int, int] = COMPACT) -> float:
    """Bytes of path state a machine holds: n cells a source, and with predecessor lists up to 2m entries more."""
    return (n * n * sum(widths) + (n * 2 * m * POINTER if predecessors else 0)) / p


def speedup(log: DataFrame, full: str = "t_full", update: str = "t_update") -> DataFrame:
    return log.withColumn("speedup", F.col(full) / F.col(update))


def cdf(frame: DataFrame, value: str) -> DataFrame:
    """(value, share): cumulative share of rows at most as large."""
    return frame.select(F.col(value), F.cume_dist().over(Window.orderBy(value)).alias("share")).distinct()


def summary(frame: DataFrame, value: str, *by: str) -> DataFrame:
    return frame.groupBy(*by).agg(F.min(value).alias("least"), F.percentile(value, F.lit(0.5)).alias("median"), F.max(value).alias("most"), F.avg(value).alias("mean"))


def work(log: DataFrame) -> DataFrame:
    """(seq, affected, skipped, touched) from a session's log."""
    n = lambda c: F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0))
    return log.groupBy("seq").agg(n(~F.col("case").isin("skip", "touched")).alias("affected"), n(F.col("case") == "skip").alias("skipped"), n(F.col("case") == "touched").alias("touched"))


def case_mix(log: DataFrame) -> DataFrame:
    return log.where("case <> 'touched'").groupBy("case").agg(F.sum("n").alias("n"))


def max_error(a: DataFrame, b: DataFrame, keys: list[str], value: str) -> DataFrame:
    """One row: largest absolute and relative difference of two results."""
    both = a.select(*keys, F.col(value).alias("x")).join(b.select(*keys, F.col(value).alias("y")), keys, "full_outer")
    gap = F.abs(F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0)))
    return both.agg(F.max(gap).alias("absolute"), F.max(gap / F.greatest(F.abs("x"), F.abs("y"), F.lit(1.0))).alias("relative"))


def scaling(runs: DataFrame) -> DataFrame:
    """(workers, updates, seconds) -> with the speedup over the fewest workers at equal updates (strong) and updates per worker (weak)."""
    first = Window.partitionBy("updates").orderBy("workers")
    return runs.withColumn("strong", F.first("seconds").over(first) / F.col("seconds")).withColumn("per_worker", F.col("updates") / F.col("workers"))


def edge_transitions(old: DataFrame, new: DataFrame, arcs: DataFrame) -> DataFrame:
    """(before, after, moved, n): how ends of edges u < v relate to each source before and after, and how many of them moved.

    old, new: (s, t, d). Relations: sibling, parent (u above v), child, apart (an end is unreachable).
    """
    e = arcs.where("u < v")

    def ends(state: DataFrame, tag: str) -> DataFrame:
        d = state.select("s", "t", "d")
        return d.toDF("s", "u", f"du{tag}"), d.toDF("s", "v", f"dv{tag}")

    sources = old.select("s").distinct()
    base = e.select("u", "v").crossJoin(sources)  # a row for each edge and source, as the measure counts them
    for state, tag in ((old, "0"), (new, "1")):
        du, dv = ends(state, tag)
        base = base.join(du, ["s", "u"], "left").join(dv, ["s", "v"], "left")

    def relation(tag: str):
        a, b = F.col(f"du{tag}"), F.col(f"dv{tag}")
        return F.when(a.isNull() | b.isNull(), "apart").when(a == b, "sibling").when(a < b, "parent").otherwise("child")

    moved = sum(((~F.col(f"d{x}0").eqNullSafe(F.col(f"d{x}1"))).cast("int") for x in "v"), (~F.col("du0").eqNullSafe(F.col("du1"))).cast("int"))
    return base.select(relation("0").alias("before"), relation("1").alias("after"), moved.alias("moved")).groupBy("before", "after", "moved").agg(F.count(F.lit(1)).alias("n"))
