"""Update streams: files of updates into loads, and windows over event streams."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from pathload.operators.components import shared_folder
from pathload.operators.update import Session, updates_from
from pathload.sources.tables import UPDATE_SCHEMA, load


class UpdateSink:
    """foreachBatch target: applies each micro-batch in order of seq, once, and commits it to the session's store.

    The store's manifest holds each batch's number and where its arrays are, so a sink
    made anew over the same store goes on from the last whole batch: one that comes again
    is skipped, and one that died before its manifest was written is applied again.
    """

    def __init__(self, session: Session, done: Callable[[Session, int], None] | None = None):
        there = Session.resume(session.spark, session.store.path, session.strategy)
        self.session, self.last = there if there and there[1] >= 0 else (session, -1)
        self.done = done

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.last:
            return
        work = updates_from(batch.dropDuplicates(["seq"]))
        fresh = {x for w in work if w.op == "add" for x in (w.u, w.v)} - (set(self.session.csr.ids.tolist()) - self.session.dead)
        self.session = self.session.apply(work, tuple(sorted(fresh)), batch_id)
        self.last = batch_id
        if self.done:
            self.done(self.session, batch_id)


def run_update_stream(stream: DataFrame, session: Session, checkpoint: str | None = None, watermark: str = "1 hour", trigger: dict | None = None, done: Callable[[Session, int], None] | None = None) -> Session:
    """Consumes a stream of (seq, ts, op, u, v) and returns the session after what is there."""
    sink = UpdateSink(session, done)
    clean = stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["seq"])
    writer = clean.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint or shared_folder(stream.sparkSession))
    query = writer.trigger(**(trigger or {"availableNow": True})).start()
    query.awaitTermination()
    return sink.session


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of files; timestamps get a zone, as watermarks need."""
    schema = load(spark, sf_dir, "events").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """What a streaming frame yields for the input that is there, read back from files."""
    out = shared_folder(stream.sparkSession)
    if mode == "append":
        writer = stream.writeStream.format("parquet").option("path", out)
    else:
        writer = stream.writeStream.foreachBatch(lambda b, _: b.write.mode("overwrite").parquet(out))
    query = writer.outputMode(mode).option("checkpointLocation", shared_folder(stream.sparkSession)).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(out)


def tumbling(s: SparkSession, d: str) -> DataFrame:
    """Purchases an hour; the complete mode keeps the open windows."""
    counts = event_stream(s, d).where("event_type = 'purchase'").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return drained(counts, "complete").select(F.date_format("w.start", "yyyy-MM-dd HH").alias("h"), "n")


def deduplicated(s: SparkSession, d: str) -> DataFrame:
    return drained(event_stream(s, d).where("event_type = 'purchase'").withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


def sessions(s: SparkSession, d: str) -> DataFrame:
    """Purchases of a user in sessions of two hours' gap; the complete mode, without a watermark, keeps the open ones and drops no late row."""
    counts = event_stream(s, d).where("event_type = 'purchase'").groupBy("user_id", F.session_window("ts", "2 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return drained(counts, "complete").select("user_id", "w.start", "n")


def incremental_query(s: SparkSession, d: str, name: str = "user_pairs") -> DataFrame:
    """Mixed updates through a stream of files give the loads of one batch."""
    from pathload.queries import held, mixed_updates

    graph = held(s, d, name)
    rows = [(u.seq, u.op, u.u, u.v) for u in mixed_updates(s, graph)]
    path = shared_folder(s)
    s.createDataFrame(rows, "seq bigint, op string, u string, v string").withColumn("ts", F.timestamp_seconds(F.col("seq"))).select("seq", "ts", "op", "u", "v").write.parquet(path)
    session = run_update_stream(s.readStream.schema(UPDATE_SCHEMA).parquet(path), Session.start(graph, 2))
    return session.loads.vertex.select("id", F.round(F.col("vbc") + 1e-9, 6).alias("vbc"))
