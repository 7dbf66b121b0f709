"""Which sources an update touches, and how: the gap between its ends per source."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

FAR = 1 << 30


def _case(op: str, gap: Column, unreachable: Column) -> Column:
    if op == "add":
        return F.when(gap == 0, "skip").when(gap == 1, "flat_add").when(unreachable, "attach").otherwise("rise")
    return F.when(gap == 0, "skip").otherwise("lost")


def _ends(rows: DataFrame, u: str, v: str, op: str) -> DataFrame:
    """(s, near, far, gap, case) from (s, du, dv); a missing distance is infinite."""
    du, dv = F.coalesce("du", F.lit(FAR)), F.coalesce("dv", F.lit(FAR))
    gap = F.abs(du - dv)
    return rows.select("s", F.when(du <= dv, u).otherwise(v).alias("near"), F.when(du <= dv, v).otherwise(u).alias("far"), F.when(gap > FAR // 2, F.lit(None)).otherwise(gap).cast("int").alias("gap"), _case(op, gap, gap > FAR // 2).alias("case"))


def classify(state: DataFrame, vertices: DataFrame, u: str, v: str, op: str) -> DataFrame:
    """One scan of the distance column, filtered to the two ends, with one row a source."""
    two = state.where(F.col("t").isin(u, v)).groupBy("s").agg(F.max(F.when(F.col("t") == u, F.col("d"))).alias("du"), F.max(F.when(F.col("t") == v, F.col("d"))).alias("dv"))
    return _ends(vertices.select(F.col("id").alias("s")).join(two, "s", "left"), u, v, op)


def classify_stored(state: DataFrame, ids, u: str, v: str, op: str) -> DataFrame:
    """The same from the store's distance column, (s, d) with positions: two places of each row are looked at, nothing is unfolded."""
    place = {x: i for i, x in enumerate(ids.tolist())}
    at = lambda x: F.nullif(F.coalesce(F.try_element_at("d", F.lit(place[x] + 1)), F.lit(-1)), F.lit(-1))
    names = state.sparkSession.createDataFrame(pa.table({"pos": pa.array(range(len(place)), pa.int64()), "s": pa.array(list(place), pa.string())}))
    two = state.select(F.col("s").alias("pos"), at(u).alias("du"), at(v).alias("dv")).join(names, "pos").select("s", "du", "dv")
    return _ends(two, u, v, op)


def classify_symmetric(state: DataFrame, vertices: DataFrame, u: str, v: str, op: str) -> DataFrame:
    """The same from the two ends' own rows: distances of an undirected graph are symmetric, so two sources' rows tell all."""
    two = state.where(F.col("s").isin(u, v)).groupBy(F.col("t").alias("s")).agg(F.max(F.when(F.col("s") == u, F.col("d"))).alias("du"), F.max(F.when(F.col("s") == v, F.col("d"))).alias("dv"))
    return _ends(vertices.select(F.col("id").alias("s")).join(two, "s", "left"), u, v, op)


def removal_cases(state: DataFrame, triaged: DataFrame, arcs: DataFrame) -> DataFrame:
    """(s, case) of a removal: skip, flat_remove (another upper neighbour), drop_one (a sibling), drop_more (neither)."""
    lost = triaged.where("case = 'lost'").select("s", "near", "far")
    around = lost.join(arcs, F.col("u") == F.col("far")).where("v <> near").select("s", "far", "v")
    d = state.select("s", "t", "d")
    beside = around.join(d.toDF("s", "v", "dv"), ["s", "v"]).join(d.toDF("s", "far", "df"), ["s", "far"])
    held = beside.groupBy("s").agg(F.max((F.col("dv") == F.col("df") - 1).cast("int")).alias("upper"), F.max((F.col("dv") == F.col("df")).cast("int")).alias("sibling"))
    kind = F.when(F.col("case") == "skip", "skip").when(F.col("upper") == 1, "flat_remove").when(F.col("sibling") == 1, "drop_one").otherwise("drop_more")
    return triaged.join(held, "s", "left").select("s", kind.alias("case"))


def anchors(state: DataFrame, arcs: DataFrame, source: str, orphans: DataFrame) -> DataFrame:
    """(id): vertices that keep their distance from the source and have an orphan beside them."""
    reach = state.where(F.col("s") == source).select(F.col("t").alias("id"))
    beside = arcs.join(orphans.select(F.col("id").alias("v")), "v", "left_semi").select(F.col("u").alias("id")).distinct()
    return beside.join(reach, "id", "left_semi").join(orphans, "id", "left_anti")


def orphans_of(state: DataFrame, source: str, near: str, far: str) -> DataFrame:
    """(id): vertices all of whose shortest paths from the source use near-far, that is as many as there are in all."""
    s = state.where(F.col("s") == source).select(F.col("t").alias("id"), "d", "sigma")
    f = state.where(F.col("s") == far).select(F.col("t").alias("id"), F.col("d").alias("df"), F.col("sigma").alias("sf"))
    top = s.where(F.col("id") == near).select(F.col("d").alias("dn"), F.col("sigma").alias("sn"))
    through = s.join(f, "id").crossJoin(top).where(F.col("d") == F.col("dn") + 1 + F.col("df"))
    return through.where(F.col("sn") * F.col("sf") == F.col("sigma")).select("id")
