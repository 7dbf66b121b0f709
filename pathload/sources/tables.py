"""Tables, edge lists and update streams; graphs derived from the tables.

A derived graph is one SQL text over all rows of the tables that runs alike on Spark
and on the engine that the results are compared with.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from pathload.operators.graph import Graph

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
UPDATE_SCHEMA = "seq bigint, ts timestamp, op string, u string, v string"
EDGE_SCHEMA = "src string, dst string, ts timestamp"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def read_edges(spark: SparkSession, path: str, form: str = "csv", schema: str = EDGE_SCHEMA, **options) -> DataFrame:
    """An edge list of CSV, JSON or Parquet files with an explicit schema; text lines of two ids with form='text'."""
    if form == "text":
        ends = F.split(F.trim("value"), r"\s+")
        return spark.read.text(path).where(~F.col("value").startswith("#")).select(ends[0].alias("src"), ends[1].alias("dst"))
    return spark.read.format(form).schema(schema).options(**options).load(path)


def read_updates(spark: SparkSession, path: str, form: str = "json", stream: bool = False, **options) -> DataFrame:
    """Updates (seq, ts, op, u, v) as a batch or as a stream of files."""
    reader = spark.readStream if stream else spark.read
    return reader.format(form).schema(UPDATE_SCHEMA).options(**options).load(path)


_TOPIC = r"regexp_extract(props, '\"k\": *([0-9]+)', 1)"
_BUYS = "SELECT DISTINCT user_id AS who, date_trunc('hour', ts) AS h FROM events WHERE event_type = 'purchase'"
_ERRORS = "SELECT user_id AS b, lag(user_id) OVER (ORDER BY ts, event_id) AS a FROM events WHERE event_type = 'error'"

#: name -> (SQL of src and dst, directed)
GRAPHS: dict[str, tuple[str, bool]] = {
    "trade_lanes": (
        "SELECT DISTINCT least(concat('n', cn), concat('n', sn)) AS src, greatest(concat('n', cn), concat('n', sn)) AS dst FROM (SELECT cn, sn, row_number() OVER (PARTITION BY cn ORDER BY q DESC, sn) AS r FROM ("
        "SELECT c_nationkey AS cn, s_nationkey AS sn, sum(l_quantity) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY c_nationkey, s_nationkey) x) y WHERE r <= 2 AND cn <> sn",
        False,
    ),
    "user_topic": (f"SELECT DISTINCT concat('k', {_TOPIC}) AS src, concat('u', user_id) AS dst FROM events WHERE event_type = 'purchase'", False),
    "user_pairs": (f"SELECT DISTINCT least(concat('u', a), concat('u', b)) AS src, greatest(concat('u', a), concat('u', b)) AS dst FROM ({_ERRORS}) x WHERE a <> b", False),
    "user_pairs_directed": (f"SELECT DISTINCT concat('u', a) AS src, concat('u', b) AS dst FROM ({_ERRORS}) x WHERE a <> b", True),
    "coactive": (f"SELECT DISTINCT least(concat('u', x.who), concat('u', y.who)) AS src, greatest(concat('u', x.who), concat('u', y.who)) AS dst FROM ({_BUYS}) x JOIN ({_BUYS}) y ON x.h = y.h AND x.who < y.who", False),
    "coactive_directed": (f"SELECT DISTINCT concat('u', x.who) AS src, concat('u', y.who) AS dst FROM ({_BUYS}) x JOIN ({_BUYS}) y ON x.h = y.h AND x.who < y.who", True),
    "supply": ("SELECT DISTINCT concat('c', o_custkey) AS src, concat('s', l_suppkey) AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey", False),
    "chat_chains": (
        "SELECT DISTINCT least(concat('t', conv_id, '_', turn), concat('t', conv_id, '_', turn + 1)) AS src, greatest(concat('t', conv_id, '_', turn), concat('t', conv_id, '_', turn + 1)) AS dst FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations) x WHERE nxt = turn + 1",
        False,
    ),
    "hierarchy": (
        "SELECT DISTINCT concat('n', n_nationkey) AS src, concat('r', n_regionkey) AS dst FROM nation UNION SELECT DISTINCT concat('n', s_nationkey) AS src, concat('s', s_suppkey) AS dst FROM supplier",
        False,
    ),
    "order_part": ("SELECT DISTINCT concat('o', l_orderkey) AS src, concat('p', l_partkey) AS dst FROM lineitem", False),
    "part_supp": ("SELECT DISTINCT concat('p', l_partkey) AS src, concat('s', l_suppkey) AS dst FROM lineitem", False),
}
#: Largest finite distances at the scale of the oracle runs, as a bound for its walks; for loads of the graphs that are not here, SQL by definition is too slow.
WALKS = {"trade_lanes": 8, "user_topic": 6, "user_pairs": 5, "user_pairs_directed": 6, "coactive": 4, "coactive_directed": 8, "chat_chains": 12, "hierarchy": 6}


def graph_of(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """A derived graph by name."""
    sql, directed = GRAPHS[name]
    register(spark, sf_dir)
    return Graph.from_edges(spark.sql(sql), directed=directed)
