"""Queries of the experiments, of streams and of the operators that the experiments need, with the SQL they must equal."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from pathload.functions import oracle as o
from pathload.operators import experiments as ex, graph as g, metrics, online
from pathload.operators.components import cut_lineage, shared_folder
from pathload.operators.update import Session, Update
from pathload.plans.blocks import sampled_betweenness, static_betweenness
from pathload.sources.tables import UPDATE_SCHEMA, WALKS, graph_of, load
from pathload.streaming import stateful, updates as st

# -- last edges in order of arrival ------------------------------------------------

_K = "regexp_extract(props, '\"k\": *([0-9]+)', 1)"
_ARRIVALS = f"arrived AS (SELECT concat('k', {_K}) AS src, concat('u', user_id) AS dst, min(ts) AS ts FROM events WHERE event_type = 'purchase' GROUP BY 1, 2)"


def arrivals(s: SparkSession, d: str) -> DataFrame:
    """(src, dst, ts): each user-topic edge and when it first came."""
    e = load(s, d, "events").where("event_type = 'purchase'")
    return e.select(F.concat(F.lit("k"), F.regexp_extract("props", r'"k": *([0-9]+)', 1)).alias("src"), F.concat(F.lit("u"), F.col("user_id")).alias("dst"), "ts").groupBy("src", "dst").agg(F.min("ts").alias("ts"))


def last_arrivals(s: SparkSession, d: str, k: int = 100) -> DataFrame:
    """(seq, ts, src, dst): the k edges that came last, in order; what a replay adds."""
    last = arrivals(s, d).orderBy(F.desc("ts"), "src", "dst").limit(k)
    return last.select(F.row_number().over(Window.orderBy("ts", "src", "dst")).cast("bigint").alias("seq"), "ts", "src", "dst")


def replayed(s: SparkSession, d: str) -> tuple[g.Graph, list[Update]]:
    """The graph before its last 100 edges, and these as updates."""
    last = cut_lineage(last_arrivals(s, d))
    whole = graph_of(s, d, "user_topic")
    before = g.Graph(cut_lineage(whole.edges.join(F.broadcast(last), ["src", "dst"], "left_anti")), False, cut_lineage(whole.vertices))
    return before, [Update("add", r["src"], r["dst"], r["seq"]) for r in last.orderBy("seq").collect()]


def replay_loads(s: SparkSession, d: str) -> DataFrame:
    """Loads after the replay, ten edges a batch: those of the whole graph."""
    graph, work = replayed(s, d)
    session = Session.start(graph, 4, "cases")
    for i in range(0, len(work), 10):
        session = session.apply(work[i : i + 10])
    return session.loads.vertex.select("id", F.round(F.col("vbc") + 1e-9, 6).alias("vbc"))


def removable(s: SparkSession, d: str, k: int = 100) -> DataFrame:
    """(src, dst, seq): the k edges that came last and do not part the graph, last first."""
    free = arrivals(s, d).join(ex.bridges(graph_of(s, d, "user_topic")), ["src", "dst"], "left_anti")
    return free.orderBy(F.desc("ts"), "src", "dst").limit(k).select("src", "dst", F.row_number().over(Window.orderBy(F.desc("ts"), "src", "dst")).cast("bigint").alias("seq"))


_FREE = "free AS (SELECT a.* FROM arrived a WHERE EXISTS (SELECT 1 FROM cut WHERE cut.src = a.src AND cut.dst = a.dst AND cut.r = a.dst)), late AS (SELECT src, dst, ts FROM free ORDER BY ts DESC, src, dst LIMIT 100)"


def removal_loads(s: SparkSession, d: str) -> DataFrame:
    """Loads after those removals, ten a batch."""
    graph = graph_of(s, d, "user_topic")
    graph = g.Graph(cut_lineage(graph.edges), False)
    work = [Update("remove", r["src"], r["dst"], r["seq"]) for r in removable(s, d).orderBy("seq").collect()]
    session = Session.start(graph, 4, "cases")
    for i in range(0, len(work), 10):
        session = session.apply(work[i : i + 10])
    return session.loads.vertex.select("id", F.round(F.col("vbc") + 1e-9, 6).alias("vbc"))


def online_measured(s: SparkSession, d: str) -> DataFrame:
    """(updates, missed, delay): the last 10 arrivals replayed one by one, with measured times against the real gaps."""
    graph, work = replayed(s, d)
    graph = g.Graph(graph.edges.unionByName(s.createDataFrame([(x.u, x.v) for x in work[:-10]], "src string, dst string")), False, graph.vertices)
    _, rows = ex.stored_run(graph, work[-10:], 4)
    log = ex.with_measured_times(last_arrivals(s, d).select("seq", "ts"), rows)
    return online.missed(online.lateness(log)).select(F.lit(len(rows)).alias("updates"), "missed", "delay")


# -- modes, summary, scaling, structure ----------------------------------------------


def one_by_one(s: SparkSession, graph: g.Graph, k: int = 10) -> list[Update]:
    from pathload.queries import mixed_updates

    return mixed_updates(s, graph, k)


def modes(s: SparkSession, d: str, name: str = "user_topic") -> DataFrame:
    """(mode, op, least, median, most, affected): speedups of an update by cumulative task time, with lists and without; counts don't depend on the mode."""
    from pathload.queries import held

    graph = held(s, d, name)
    work = one_by_one(s, graph)
    both = ex.cumulative(ex.measured_blocks(graph, work, 4, "MP").unionByName(ex.measured_blocks(graph, work, 4, "MO")))
    counts = both.groupBy("mode", "op").agg(F.sum("affected").alias("affected"))
    return metrics.summary(both, "speedup", "mode", "op").join(counts, ["mode", "op"]).drop("mean")


def affected(s: SparkSession, d: str, name: str = "user_topic") -> DataFrame:
    """(op, affected) of the first addition and the first removal: the work counts of either in-memory mode."""
    from pathload.queries import held

    graph = held(s, d, name)
    work = one_by_one(s, graph, 1)
    out = None
    for x in work:
        one = ex.cumulative(ex.measured_blocks(graph, [x], 3, "MO")).select("op", "affected")
        out = one if out is None else out.unionByName(one)
    return out


def structure(s: SparkSession, d: str) -> DataFrame:
    """(graph, clustering, affected, touched): how much of (source, vertex) an update touches, by graph; shares of n and of n squared."""
    from pathload.queries import held

    out = None
    for name in ("user_topic", "coactive", "user_pairs", "hierarchy", "chat_chains"):
        graph = held(s, d, name)
        n = graph.vertices.count()
        seen = ex.cumulative(ex.measured_blocks(graph, one_by_one(s, graph, 5), 2))
        part = seen.agg(F.round(F.avg("affected") / n, 6).alias("affected"), F.round(F.avg("touched") / (n * n), 6).alias("touched"))
        one = g.stats(graph).select(F.lit(name).alias("graph"), F.round("clustering", 6).alias("clustering")).crossJoin(part)  # one row each
        out = one if out is None else out.unionByName(one)
    return out


def scaled(s: SparkSession, d: str, per_worker: bool) -> DataFrame:
    from pathload.queries import held

    graph = held(s, d, "user_topic")
    runs = ex.scaling_runs(graph, one_by_one(s, graph, 4), (1, 2, 4), per_worker)
    return metrics.scaling(runs)


# -- other operators -------------------------------------------------------------------


def full_outer_flows(s: SparkSession, d: str) -> DataFrame:
    """(src, dst, old, new) of every edge before or after the first addition; 0 where it is not there."""
    from pathload.queries import _NON, chosen, held

    graph = held(s, d, "trade_lanes")
    session = Session.start(graph, 2)
    after = session.apply(chosen(s, graph, [_NON], "SELECT u, v FROM non ORDER BY h LIMIT 1", "add"))
    old, new = session.loads.edge.withColumnRenamed("ebc", "old"), after.loads.edge.withColumnRenamed("ebc", "new")
    return old.join(new, ["src", "dst"], "full_outer").select("src", "dst", *(F.round(F.coalesce(c, F.lit(0.0)) + 1e-9, 6).alias(c) for c in ("old", "new")))


def complement(s: SparkSession, d: str) -> DataFrame:
    """Pairs of nations without a lane; the number of nations is fixed."""
    graph = graph_of(s, d, "trade_lanes")
    a, b = graph.vertices.toDF("src"), graph.vertices.toDF("dst")
    return a.join(F.broadcast(b), F.col("src") < F.col("dst")).join(graph.edges, ["src", "dst"], "left_anti")


def purchases_in_hour(s: SparkSession, d: str) -> DataFrame:
    """(event_id, n): purchases of the same user in the hour up to each."""
    e = load(s, d, "events").where("event_type = 'purchase'")
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)
    return e.select("event_id", F.count(F.lit(1)).over(w).alias("n"))


def top_of_components(s: SparkSession, d: str, k: int = 3) -> DataFrame:
    from pathload.queries import held

    graph = held(s, d, "chat_chains")
    loads = static_betweenness(graph).edge.select("src", "dst", F.round(F.col("ebc") + 1e-9, 6).alias("ebc"))
    own = loads.join(g.components(graph), F.col("src") == F.col("id"))
    w = Window.partitionBy("component").orderBy(F.desc("ebc"), "src", "dst")
    return own.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).select("component", "src", "dst", "ebc", "r")


# -- streams ---------------------------------------------------------------------------


def sliding(s: SparkSession, d: str) -> DataFrame:
    """Purchases in windows of an hour that start each half hour."""
    e = st.event_stream(s, d).where("event_type = 'purchase'")
    return st.drained(e.groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("n")), "complete").select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("h"), "n")


def late(s: SparkSession, d: str) -> DataFrame:
    """Hours that the watermark closed, when the first 100 purchases come once more behind all others: those are dropped."""
    e = load(s, d, "events").where("event_type = 'purchase'").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    path = shared_folder(s)
    e.coalesce(1).write.parquet(f"{path}/one")
    e.orderBy("ts", "event_id").limit(100).coalesce(1).write.parquet(f"{path}/two")
    schema = "event_id bigint, ts timestamp"
    out, checkpoint = shared_folder(s), shared_folder(s)
    for part in ("one", "two"):  # a second run over the same state: the late rows come in a batch of their own
        s.read.schema(schema).parquet(f"{path}/{part}").coalesce(1).write.mode("append").parquet(f"{path}/in")
        counts = s.readStream.schema(schema).parquet(f"{path}/in").withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"))
        counts.writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return s.read.schema("w struct<start:timestamp,end:timestamp>, n bigint").parquet(out).select(F.date_format("w.start", "yyyy-MM-dd HH").alias("h"), "n")


def joined_streams(s: SparkSession, d: str) -> DataFrame:
    """(purchase, error): a user's errors within ten minutes after a purchase; both sides are streams."""
    e = st.event_stream(s, d).select("event_id", "ts", "user_id", "event_type")
    a = e.where("event_type = 'purchase'").withWatermark("ts", "1 hour").select(F.col("event_id").alias("purchase"), F.col("ts").alias("t1"), F.col("user_id").alias("u1"))
    b = e.where("event_type = 'error'").withWatermark("ts", "1 hour").select(F.col("event_id").alias("error"), F.col("ts").alias("t2"), F.col("user_id").alias("u2"))
    return st.drained(a.join(b, F.expr("u1 = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL 10 MINUTES")).select("purchase", "error"))


def edges_of_stream(s: SparkSession, d: str) -> DataFrame:
    """The user-topic edges of a stream of purchases, each once."""
    e = st.event_stream(s, d).where("event_type = 'purchase'")
    return st.drained(e.select(F.concat(F.lit("k"), F.get_json_object("props", "$.k")).alias("src"), F.concat(F.lit("u"), F.col("user_id")).alias("dst")).dropDuplicates(["src", "dst"]))


def window_graph(s: SparkSession, d: str) -> DataFrame:
    """(day, src, dst, n): the user-topic graph of each day's purchases."""
    e = st.event_stream(s, d).where("event_type = 'purchase'").select("ts", F.concat(F.lit("k"), F.get_json_object("props", "$.k")).alias("src"), F.concat(F.lit("u"), F.col("user_id")).alias("dst"))
    return st.drained(e.groupBy(F.window("ts", "1 day").alias("w"), "src", "dst").agg(F.count(F.lit(1)).alias("n")), "complete").select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "src", "dst", "n")


def stateful_loads(s: SparkSession, d: str, name: str = "trade_lanes") -> DataFrame:
    from pathload.queries import held, mixed_updates

    graph = held(s, d, name)
    rows = [(u.seq, u.op, u.u, u.v) for u in mixed_updates(s, graph)]
    path = shared_folder(s)
    s.createDataFrame(rows, "seq bigint, op string, u string, v string").withColumn("ts", F.timestamp_seconds(F.col("seq"))).select("seq", "ts", "op", "u", "v").repartition(2).write.parquet(path)
    loads = stateful.run_stateful_blocks(s.readStream.schema(UPDATE_SCHEMA).parquet(path), graph, 3)
    return loads.vertex.select("id", F.round(F.col("vbc") + 1e-9, 6).alias("vbc"))


_PURCHASE = "FROM events WHERE event_type = 'purchase'"
_SCOPE = (
    "apart(c, id, r) AS (SELECT x.id, y.id, y.id FROM v x JOIN v y ON x.id <> y.id UNION SELECT p.c, p.id, a.v FROM apart p JOIN arcs a ON a.u = p.r WHERE a.v <> p.c), "
    "hurt AS (SELECT DISTINCT g.src, g.dst, x.id FROM g JOIN v x ON x.id <> g.src AND x.id <> g.dst JOIN v c ON c.id <> x.id "
    "WHERE NOT EXISTS (SELECT 1 FROM apart p WHERE p.c = c.id AND p.id = x.id AND p.r = CASE WHEN c.id = g.src THEN g.dst ELSE g.src END))"
)


def install(add) -> None:
    from pathload.queries import _MIXED, _NON, _OWN, _ADD1, _DEL1, _GAPS, _BRIDGE, _COMP, final_ctes

    topic = o.graph_ctes("user_topic")
    add("wl_last_nonbridge_removals", removable, o.sql([*topic, _BRIDGE, _ARRIVALS, _FREE], "SELECT src, dst, row_number() OVER (ORDER BY ts DESC, src, dst) AS seq FROM late"))
    add("wl_removals_loads", removal_loads, o.sql([*topic, _BRIDGE, _ARRIVALS, _FREE, "gone AS (SELECT src AS u, dst AS v FROM late)", *final_ctes("user_topic", "gone", None)], "SELECT id, round(vbc + 1e-9, 6) AS vbc FROM vbc2"))
    add("wl_replay_loads", replay_loads, o.vbc("user_topic"))
    add("online_measured", online_measured)
    add("modes_speedup", modes)
    gone = _GAPS.replace("gaps AS", "lost AS").replace("one", "two")
    add(
        "modes_affected",
        affected,
        o.sql(
            [*topic, *o.path_ctes(WALKS["user_topic"]), _NON, _ADD1, _GAPS, _OWN, _DEL1.replace("one AS", "two AS"), gone],
            "SELECT 'add' AS op, count(*) AS affected FROM gaps WHERE du IS DISTINCT FROM dv UNION ALL SELECT 'remove', count(*) FROM lost WHERE du IS DISTINCT FROM dv",
        ),
    )
    add("structure_work", structure)
    add("scaling_strong", lambda s, d: scaled(s, d, False))
    add("scaling_weak", lambda s, d: scaled(s, d, True))
    add("rival_cycle_scope", lambda s, d: ex.cycle_scope(graph_of(s, d, "trade_lanes")), o.sql([*o.graph_ctes("trade_lanes"), _SCOPE], "SELECT g.src, g.dst, (SELECT count(*) FROM v) - count(h.id) AS scope FROM g LEFT JOIN hurt h ON h.src = g.src AND h.dst = g.dst GROUP BY 1, 2"))
    add("rival_cycle_scope_tree", lambda s, d: ex.cycle_scope(graph_of(s, d, "hierarchy")), o.sql(o.graph_ctes("hierarchy"), "SELECT src, dst, 2 AS scope FROM g"))
    add(
        "sample_vbc_part",
        lambda s, d: sampled_betweenness(graph_of(s, d, "trade_lanes"), 10).select("id", *(F.round(F.col(c) + 1e-9, 5).alias(c) for c in ("vbc", "error"))),
        o.paths(
            "trade_lanes",
            "SELECT v.id, round(coalesce(sum(x), 0) * 2.5 + 1e-9, 5) AS vbc, round(25 * sqrt(greatest((coalesce(sum(x * x), 0) - coalesce(sum(x), 0) * coalesce(sum(x), 0) / 10) / 9, 0) / 10 * (1 - 10 / 25.0)) + 1e-9, 5) AS error FROM v LEFT JOIN dep ON dep.id = v.id GROUP BY v.id",
            ["few AS (SELECT id FROM v ORDER BY md5(concat(id, ':', '0')), id LIMIT 10)", "dep AS (SELECT a.s, a.t AS id, sum(a.sigma * b.sigma / c.sigma) AS x FROM p a JOIN few ON few.id = a.s JOIN p b ON b.s = a.t JOIN p c ON c.s = a.s AND c.t = b.t WHERE a.d + b.d = c.d AND a.s <> a.t AND b.s <> b.t GROUP BY a.s, a.t)"],
        ),
    )
    add("op_full_outer_flows", full_outer_flows, o.sql([*o.graph_ctes("trade_lanes"), *o.path_ctes(WALKS["trade_lanes"]), *o.ebc_ctes(False), _NON, _ADD1, *final_ctes("trade_lanes", None, "one")], "SELECT coalesce(a.src, b.src) AS src, coalesce(a.dst, b.dst) AS dst, round(coalesce(a.ebc, 0.0) + 1e-9, 6) AS old, round(coalesce(b.ebc, 0.0) + 1e-9, 6) AS new FROM ebc a FULL OUTER JOIN ebc2 b ON a.src = b.src AND a.dst = b.dst"))
    add("op_theta_complement", complement, o.sql(o.graph_ctes("trade_lanes"), "SELECT a.id AS src, b.id AS dst FROM v a JOIN v b ON a.id < b.id LEFT JOIN g ON g.src = a.id AND g.dst = b.id WHERE g.src IS NULL"))
    add("op_range_frame", purchases_in_hour, f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n {_PURCHASE}")
    add("op_topk_per_component", top_of_components, o.ebc("chat_chains", [_COMP, "r AS (SELECT component, src, dst, round(ebc + 1e-9, 6) AS ebc FROM ebc JOIN comp ON comp.id = ebc.src)", "k AS (SELECT *, row_number() OVER (PARTITION BY component ORDER BY ebc DESC, src, dst) AS r FROM r)"], "SELECT component, src, dst, ebc, r FROM k WHERE r <= 3"))
    add("op_stream_sliding", sliding, f"SELECT strftime(h, '%Y-%m-%d %H:%M') AS h, count(*) AS n FROM (SELECT time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE * i AS h {_PURCHASE.replace('FROM events', 'FROM events, (SELECT unnest([0, 1]) AS i) q')}) x GROUP BY 1")
    add("op_stream_late", late, f"SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS h, count(*) AS n {_PURCHASE} AND date_trunc('hour', ts) + INTERVAL 1 HOUR <= (SELECT max(ts) {_PURCHASE}) - INTERVAL 1 HOUR GROUP BY 1")
    add("op_stream_join", joined_streams, "SELECT a.event_id AS purchase, b.event_id AS error FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE WHERE a.event_type = 'purchase' AND b.event_type = 'error'")
    add("stream_updates_to_edges", edges_of_stream, o.sql(topic, "SELECT src, dst FROM g"))
    add("stream_window_graph", window_graph, f"SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, concat('k', {_K}) AS src, concat('u', user_id) AS dst, count(*) AS n {_PURCHASE} GROUP BY 1, 2, 3")
    add("stream_stateful_vbc", stateful_loads, o.sql(o.graph_ctes("trade_lanes") + _MIXED + final_ctes("trade_lanes", "less", "more"), "SELECT id, round(vbc + 1e-9, 6) AS vbc FROM vbc2"))
