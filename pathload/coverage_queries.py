"""Queries of the operators around the engine, each with plain SQL beside it."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from pathload.functions import oracle as o
from pathload.sources.tables import graph_of, load
from pathload.streaming import updates as st


#: A side of more rows than this isn't broadcast: its hash table would be built in the driver's memory.
BROADCAST_ROWS = 1_000_000


def lanes(s, d, hint: str) -> DataFrame:
    """Customer nation to supplier nation quantities, by a named join strategy; sides too long to broadcast are shuffled and merged."""

    def hinted(side: DataFrame) -> DataFrame:
        return side.hint("merge" if hint == "broadcast" and side.count() > BROADCAST_ROWS else hint)

    li = load(s, d, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity")
    orders = hinted(load(s, d, "orders").select("o_orderkey", "o_custkey"))
    cust = hinted(load(s, d, "customer").select("c_custkey", "c_nationkey"))
    supp = hinted(load(s, d, "supplier").select("s_suppkey", "s_nationkey"))
    joined = li.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(cust, F.col("o_custkey") == F.col("c_custkey")).join(supp, F.col("l_suppkey") == F.col("s_suppkey"))
    return joined.groupBy("c_nationkey", "s_nationkey").agg(F.round(F.sum("l_quantity"), 2).alias("quantity"), F.count(F.lit(1)).alias("n"))


_LANES = "SELECT c_nationkey, s_nationkey, round(sum(l_quantity), 2) AS quantity, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2"


def scan_pushdown(s, d):
    orders = load(s, d, "orders").where("o_orderdate >= timestamp_ntz'1995-01-01' AND o_orderdate < timestamp_ntz'1995-04-01'").select("o_orderkey", "o_custkey")
    li = load(s, d, "lineitem").select("l_orderkey", "l_suppkey")
    return orders.join(li, F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("o_custkey").alias("src"), F.col("l_suppkey").alias("dst")).distinct()


def round_of_search(s, d):
    """Views g, arcs and the two first levels around the vertex of most neighbours."""
    graph = graph_of(s, d, "user_pairs")
    arcs = graph.arcs
    start = arcs.groupBy(F.col("u").alias("id")).count().orderBy(F.desc("count"), "id").limit(1).select("id")
    first = arcs.join(start, F.col("u") == F.col("id")).select(F.col("v").alias("id"))
    return arcs, start, first


_START = "start AS (SELECT u AS id FROM arcs GROUP BY u ORDER BY count(*) DESC, u LIMIT 1), first AS (SELECT a.v AS id FROM arcs a JOIN start ON a.u = start.id)"


def anti_unvisited(s, d):
    arcs, start, first = round_of_search(s, d)
    seen = start.unionByName(first)
    return arcs.join(first, F.col("u") == F.col("id")).select(F.col("v").alias("id")).distinct().join(seen, "id", "left_anti")


def semi_upper(s, d):
    """Vertices of level two that have at least two upper neighbours."""
    arcs, _, first = round_of_search(s, d)
    second = anti_unvisited(s, d)
    return arcs.join(second, F.col("u") == F.col("id")).join(first.withColumnRenamed("id", "f"), F.col("v") == F.col("f"), "left_semi").groupBy(F.col("u").alias("id")).agg(F.count(F.lit(1)).alias("uppers")).where("uppers > 1")


_SECOND = "second AS (SELECT DISTINCT a.v AS id FROM arcs a JOIN first f ON a.u = f.id WHERE a.v NOT IN (SELECT id FROM start) AND a.v NOT IN (SELECT id FROM first))"


def purchases(s, d):
    return load(s, d, "events").where("event_type = 'purchase'").select("event_id", "ts", "user_id", "value", F.get_json_object("props", "$.k").cast("int").alias("k"))


def range_lifetime(s, d):
    """Edges user-topic alive at noon of each day: an edge lives three days from each purchase; days are the bins of the range join."""
    p = purchases(s, d)
    days = p.select(F.date_trunc("day", "ts").alias("day")).distinct().select("day", (F.col("day") + F.expr("INTERVAL 12 HOURS")).alias("noon"))
    binned = p.select("user_id", "k", "ts", (F.col("ts") + F.expr("INTERVAL 3 DAYS")).alias("gone"), F.explode(F.sequence(F.lit(0), F.lit(3))).alias("i"))
    binned = binned.withColumn("day", F.expr("date_trunc('day', ts) + make_dt_interval(i)"))
    alive = binned.join(days, "day").where("ts <= noon AND noon < gone")
    return alive.groupBy("day").agg(F.countDistinct("user_id", "k").alias("n")).select(F.date_format("day", "yyyy-MM-dd").alias("day"), "n")


def asof_latest(s, d):
    """The topic of a user's last purchase before each of their errors."""
    e = load(s, d, "events")
    both = e.where("event_type IN ('purchase', 'error')").withColumn("k", F.when(F.col("event_type") == "purchase", F.get_json_object("props", "$.k").cast("int")))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn("last_k", F.last("k", ignorenulls=True).over(w)).where("event_type = 'error'").select("event_id", "last_k")


def mapped_degree(s, d):
    """Degrees by an Arrow batch function before the sum."""

    def count(batches):
        for b in batches:
            t = pa.Table.from_batches([b]).group_by("u").aggregate([("u", "count")])
            yield from t.select(["u", "u_count"]).rename_columns(["id", "n"]).to_batches()

    return graph_of(s, d, "user_pairs").arcs.select("u").mapInArrow(count, "id string, n bigint").groupBy("id").agg(F.sum("n").alias("degree"))


def median_lateness(s, d):
    @F.pandas_udf("double")
    def median(x: pd.Series) -> float:
        return float(x.median())

    return load(s, d, "events").groupBy("event_type").agg(median(F.col("value").cast("double")).alias("median")).select("event_type", F.round("median", 6).alias("median"))


def neighbours_udtf(s, d):
    """(id, nbr) through a table function over adjacency rows, joined laterally."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="nbr string")
    class Neighbours:
        def eval(self, nbrs: list):
            for x in nbrs:
                yield (x,)

    s.udtf.register("neighbours_of", Neighbours)
    graph_of(s, d, "user_pairs").adjacency().createOrReplaceTempView("adjacency")
    return s.sql("SELECT a.v AS id, t.nbr FROM adjacency a, LATERAL neighbours_of(a.nbrs) t")


def recursive_reach(s, d):
    graph_of(s, d, "chat_chains").register("chains")
    return s.sql("WITH RECURSIVE r(s, t, k) AS (SELECT id, id, 0 FROM chains_vertices UNION ALL SELECT r.s, a.v, r.k + 1 FROM r JOIN chains_arcs a ON a.u = r.t WHERE r.k < 3) SELECT s, count(DISTINCT t) AS reached FROM r GROUP BY s")


def regex_links(s, d):
    p = load(s, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("link"))
    return p.groupBy("page_id").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("link").alias("links"))


def packed_roundtrip(s, d):
    """Adjacency to packed lists and back."""
    adj = graph_of(s, d, "trade_lanes").adjacency()
    return adj.select("v", F.posexplode("nbrs").alias("i", "nbr")).select("v", "i", "nbr")


def common_neighbours(s, d):
    g = graph_of(s, d, "trade_lanes")
    adj = g.adjacency()
    a, b = adj.toDF("src", "na"), adj.toDF("dst", "nb")
    return g.edges.join(a, "src").join(b, "dst").select("src", "dst", F.size(F.array_intersect("na", "nb")).alias("n"))


def snapshots(s, d, how: str):
    p = purchases(s, d)
    first = p.select(F.min(F.date_trunc("day", "ts")).alias("day0"))
    e = p.crossJoin(F.broadcast(first)).withColumn("day", F.datediff("ts", "day0"))
    a, b = (e.where(F.col("day") % 2 == r).select("user_id", "k") for r in (0, 1))
    return a.intersect(b) if how == "both" else a.subtract(b)


_SNAP = "e AS (SELECT user_id, k, date_diff('day', min(date_trunc('day', ts)) OVER (), ts) AS day FROM (SELECT user_id, ts, regexp_extract(props, '\"k\": *([0-9]+)', 1)::INT AS k FROM events WHERE event_type = 'purchase') q)"


def install(add) -> None:
    for hint, name in (("broadcast", "op_join_broadcast"), ("merge", "op_join_sortmerge"), ("shuffle_hash", "op_join_shuffled_hash")):
        add(name, lambda s, d, h=hint: lanes(s, d, h), _LANES)
    add("op_scan_pushdown", scan_pushdown, "SELECT DISTINCT o_custkey AS src, l_suppkey AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderdate >= TIMESTAMP '1995-01-01' AND o_orderdate < TIMESTAMP '1995-04-01'")
    add("op_anti_unvisited", anti_unvisited, o.sql([*o.graph_ctes("user_pairs"), _START, _SECOND], "SELECT id FROM second"))
    add("op_semi_upper_neighbour", semi_upper, o.sql([*o.graph_ctes("user_pairs"), _START, _SECOND], "SELECT a.u AS id, count(*) AS uppers FROM arcs a JOIN second s ON s.id = a.u JOIN first f ON f.id = a.v GROUP BY a.u HAVING count(*) > 1"))
    add("op_agg_distinct_degree", lambda s, d: purchases(s, d).groupBy("k").agg(F.countDistinct("user_id").alias("users")), "SELECT regexp_extract(props, '\"k\": *([0-9]+)', 1)::INT AS k, count(DISTINCT user_id) AS users FROM events WHERE event_type = 'purchase' GROUP BY 1")
    lifetime = "WITH p AS (SELECT user_id, regexp_extract(props, '\"k\": *([0-9]+)', 1)::INT AS k, ts FROM events WHERE event_type = 'purchase'), days AS (SELECT DISTINCT date_trunc('day', ts) AS day FROM p) SELECT strftime(day, '%Y-%m-%d') AS day, count(DISTINCT (user_id, k)) AS n FROM days JOIN p ON ts <= day + INTERVAL 12 HOUR AND day + INTERVAL 12 HOUR < ts + INTERVAL 3 DAY GROUP BY 1"
    add("op_range_lifetime", range_lifetime, lifetime)
    add("op_asof_latest_edge", asof_latest, "WITH b AS (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'purchase' THEN regexp_extract(props, '\"k\": *([0-9]+)', 1)::INT END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_k FROM events WHERE event_type IN ('purchase', 'error')) SELECT event_id, last_k FROM b WHERE event_type = 'error'")
    add("op_lag_gap", lambda s, d: purchases(s, d).select("event_id", F.timestamp_diff("SECOND", F.lag("ts").over(Window.partitionBy("user_id").orderBy("ts", "event_id")), F.col("ts")).alias("gap")), "SELECT event_id, (epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id))) // 1000000 AS gap FROM events WHERE event_type = 'purchase'")
    add("op_running_max", lambda s, d: purchases(s, d).select("event_id", F.max("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("m")), "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS m FROM events WHERE event_type = 'purchase'")
    add("op_moving_avg", lambda s, d: purchases(s, d).select("event_id", F.round(F.avg("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 0)), 5).alias("m")), "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 5) AS m FROM events WHERE event_type = 'purchase'")
    add("op_union_edge", lambda s, d: graph_of(s, d, "trade_lanes").edges.unionByName(s.createDataFrame([("n0", "zz")], "src string, dst string")).distinct(), o.sql(o.graph_ctes("trade_lanes"), "SELECT src, dst FROM g UNION SELECT 'n0', 'zz'"))
    add("op_except_edge", lambda s, d: (lambda e: e.subtract(e.orderBy("src", "dst").limit(1)))(graph_of(s, d, "trade_lanes").edges), o.sql(o.graph_ctes("trade_lanes"), "SELECT src, dst FROM g EXCEPT (SELECT src, dst FROM g ORDER BY src, dst LIMIT 1)"))
    add("op_intersect_snapshots", lambda s, d: snapshots(s, d, "both"), f"WITH {_SNAP} SELECT user_id, k FROM e WHERE day % 2 = 0 INTERSECT SELECT user_id, k FROM e WHERE day % 2 = 1")
    add("op_except_snapshots", lambda s, d: snapshots(s, d, "first"), f"WITH {_SNAP} SELECT user_id, k FROM e WHERE day % 2 = 0 EXCEPT SELECT user_id, k FROM e WHERE day % 2 = 1")
    add("op_array_adjacency", lambda s, d: graph_of(s, d, "trade_lanes").adjacency().select("v", F.array_join("nbrs", ",").alias("nbrs")), o.sql(o.graph_ctes("trade_lanes"), "SELECT u AS v, string_agg(v, ',' ORDER BY v) AS nbrs FROM arcs GROUP BY u"))
    add("op_packed_roundtrip", packed_roundtrip, o.sql(o.graph_ctes("trade_lanes"), "SELECT u AS v, row_number() OVER (PARTITION BY u ORDER BY v) - 1 AS i, v AS nbr FROM arcs"))
    add("op_array_common_neighbours", common_neighbours, o.sql(o.graph_ctes("trade_lanes"), "SELECT g.src, g.dst, count(b.v) AS n FROM g JOIN arcs a ON a.u = g.src LEFT JOIN arcs b ON b.u = g.dst AND b.v = a.v GROUP BY 1, 2"))
    add("op_json_topic", lambda s, d: load(s, d, "events").select("event_id", F.from_json("props", "k int").getField("k").alias("k")), "SELECT event_id, regexp_extract(props, '\"k\": *([0-9]+)', 1)::INT AS k FROM events")
    add("op_string_ids", lambda s, d: graph_of(s, d, "user_topic").vertices.select("id", F.substring("id", 1, 1).alias("kind"), F.regexp_extract("id", r"([0-9]+)", 1).cast("bigint").alias("n")), o.sql(o.graph_ctes("user_topic"), "SELECT id, substr(id, 1, 1) AS kind, regexp_extract(id, '([0-9]+)', 1)::BIGINT AS n FROM v"))
    add("op_regex_links", regex_links, "SELECT page_id, count(*) AS n, count(DISTINCT link) AS links FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS link FROM pages) x GROUP BY 1")
    add("op_date_buckets", lambda s, d: purchases(s, d).groupBy(F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd").alias("day")).agg(F.count(F.lit(1)).alias("n")), "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, count(*) AS n FROM events WHERE event_type = 'purchase' GROUP BY 1")
    add("op_map_in_arrow_degree", mapped_degree, o.sql(o.graph_ctes("user_pairs"), "SELECT u AS id, count(*) AS degree FROM arcs GROUP BY u"))
    add("op_pandas_udaf_lateness", median_lateness, "SELECT event_type, round(median(value), 6) AS median FROM events GROUP BY 1")
    add("op_udtf_neighbours", neighbours_udtf, o.sql(o.graph_ctes("user_pairs"), "SELECT u AS id, v AS nbr FROM arcs"))
    add("op_recursive_reach", recursive_reach, o.sql([*o.graph_ctes("chat_chains"), "r(s, t, k) AS (SELECT id, id, 0 FROM v UNION ALL SELECT r.s, a.v, r.k + 1 FROM r JOIN arcs a ON a.u = r.t WHERE r.k < 3)"], "SELECT s, count(DISTINCT t) AS reached FROM r GROUP BY s"))
    add("op_stream_tumbling", st.tumbling, "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS h, count(*) AS n FROM events WHERE event_type = 'purchase' GROUP BY 1")
    add("stream_dedup", st.deduplicated, "SELECT DISTINCT event_id, user_id FROM events WHERE event_type = 'purchase'")
    from pathload.queries import ORACLES

    add("stream_incremental_vbc", st.incremental_query, ORACLES["inc_mixed_batch_vbc"])
    add(
        "stream_session_users",
        st.sessions,
        "WITH p AS (SELECT user_id, event_id, ts, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS gap FROM events WHERE event_type = 'purchase'), "
        "s AS (SELECT user_id, ts, sum(CASE WHEN gap <= INTERVAL 2 HOUR THEN 0 ELSE 1 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM p) "
        "SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k",
    )
