"""When updates can be applied as they arrive, and by how many machines."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F


def update_time(t_s: Column, n: Column, p: Column, t_m: Column) -> Column:
    """Seconds of an update: a source's time, for the sources of one of p machines, and the merge."""
    return t_s * n / p + t_m


def is_online(t_u: Column, t_i: Column) -> Column:
    return t_u < t_i


def required_parallelism(t_s: Column, n: Column, t_i: Column, t_m: Column) -> Column:
    """The least number of machines that keeps an update strictly within the inter-arrival time; null where the merge alone takes it."""
    return F.when(t_i > t_m, F.floor(t_s * n / (t_i - t_m)) + 1).cast("bigint")


def interarrival(updates: DataFrame, ts: str = "ts", order: tuple[str, ...] = ("ts",)) -> DataFrame:
    """Adds t_i, the seconds since the update before."""
    seconds = F.timestamp_diff("MICROSECOND", F.lag(ts).over(Window.orderBy(*order)), F.col(ts)) / 1e6
    return updates.withColumn("t_i", seconds)


def lateness(log: DataFrame, mode: str = "independent", order: str = "seq") -> DataFrame:
    """Adds delay: seconds by which an update is done after the next one came.

    log: (seq, t_i, t_u), t_i until the next update. independent: each update starts
    when it comes. queued: it starts when the one before is done (Lindley's recursion, as a running maximum).
    """
    if mode == "independent":
        return log.withColumn("delay", F.greatest(F.col("t_u") - F.col("t_i"), F.lit(0.0)))
    w = Window.orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    walk = log.withColumn("x", F.sum(F.col("t_u") - F.col("t_i")).over(w))
    low = F.least(F.lit(0.0), F.min("x").over(w))
    return walk.withColumn("delay", F.col("x") - low).drop("x")


def missed(late: DataFrame) -> DataFrame:
    """One row: share of updates that are late, and their mean delay."""
    return late.agg(F.avg((F.col("delay") > 0).cast("double")).alias("missed"), F.coalesce(F.avg(F.when(F.col("delay") > 0, F.col("delay"))), F.lit(0.0)).alias("delay"))


def monitor(log: DataFrame, k: int, *values: str, order: str = "seq") -> DataFrame:
    """Running means of the last k rows."""
    w = Window.orderBy(order).rowsBetween(-(k - 1), 0)
    return log.select(order, *(F.avg(v).over(w).alias(f"mean_{v}") for v in values))
