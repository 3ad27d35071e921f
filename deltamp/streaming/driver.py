"""Structured Streaming: change events as files, one incremental batch for each micro-batch."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StreamingQuery

from deltamp.operators.incremental import IncrementalSession
from deltamp.operators.state import cut, hold, ids_of, shared_dir
from deltamp.plans.model import ModelSpec
from deltamp.sources import graphs as G
from deltamp.sources import temporal

EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def read_events(spark: SparkSession, folder: str, watermark: str = "30 days", files_per_batch: int = 1) -> DataFrame:
    """The event stream without redelivered events, as long as they come within the watermark."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(folder)
    return raw.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def changes_of(events: DataFrame) -> DataFrame:
    """Change rows (t, seq, op, a, b); the last (ts, event_id) of a pair decides."""
    k = F.get_json_object("props", "$.k").cast("long")
    user, item = F.col("user_id") * 4, k * 4 + 1
    rows = events.select(F.col("ts").alias("t"), F.col("event_id").alias("seq"), F.when(F.col("event_type") == "error", "del").otherwise("add").alias("op"), F.least(user, item).alias("a"), F.greatest(user, item).alias("b"))
    return rows.where("a IS NOT NULL AND a <> b")


class StreamRunner:
    """Applies micro-batches to a session, each in one commit with its number and the pairs' last times.

    The number is in the manifest, so a batch that the stream gives again after a restart changes nothing. ``last``: the last
    time (a, b, t) of each pair before the stream, not needed for a resumed session.
    """

    def __init__(self, session: IncrementalSession, last: DataFrame | None = None) -> None:
        self.session, self.state = session, session.state
        if not self.state.last.bases:
            self.state.last.create(last.select(F.col("a").alias("src"), F.col("b").alias("dst"), "t"), self.state.version)
            self.state.extra = {**self.state.extra, "stream_batch": -1}
            self.state.save()

    @property
    def done(self) -> int:
        return self.state.extra["stream_batch"]

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.done:
            return
        rows = hold(changes_of(batch))
        # an op that is older than what the pair has seen is ignored
        seen = self.state.last_times(ids_of(rows, "a")).toDF("a", "b", "_seen")
        rows = hold(rows.df.join(seen, ["a", "b"], "left").where("_seen IS NULL OR t > _seen").drop("_seen"))
        newest = rows.df.groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.max("t").alias("t"))
        self.session.apply(rows.df, extra={"stream_batch": batch_id}, also=[("last", newest)])


def start(runner: StreamRunner, events: DataFrame, checkpoint: str, trigger: dict | None = None) -> StreamingQuery:
    return events.writeStream.foreachBatch(runner).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def stream_user_item(spark: SparkSession, sf_dir: str, model: ModelSpec, held: int = 60, files: int = 3) -> IncrementalSession:
    """The newest ``held`` events as files of a stream over the graph of all earlier ones, run to the end."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select(*(f.name for f in EVENTS))
    newest = cut(events.orderBy(F.desc("ts"), F.desc("event_id")).limit(held))
    earlier = events.join(F.broadcast(newest.select("event_id")), "event_id", "left_anti")  # at most ``held`` rows
    folder = f"{shared_dir(spark)}/events-{uuid.uuid4().hex}"
    newest.repartitionByRange(files, "ts").write.parquet(f"{folder}/in")
    log = changes_of(events)
    nodes = cut(G.hashed_features(G.nodes_of(log), model.width))
    old = cut(changes_of(earlier).select("t", "op", "a", "b"))
    session = IncrementalSession(spark, model, nodes, cut(temporal.snapshot(old)), state_dir=f"{folder}/state").bootstrap()
    runner = StreamRunner(session, old.groupBy("a", "b").agg(F.max("t").alias("t")))
    start(runner, read_events(spark, f"{folder}/in"), f"{folder}/checkpoint").awaitTermination()
    return session


def windowed_counts(events: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """Changes by tumbling or sliding window and op."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(window.alias("w"), F.when(F.col("event_type") == "error", "del").otherwise("add").alias("op")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "op", "n")


def sessions(events: DataFrame, gap: str = "1 hour") -> DataFrame:
    """Activity of a user without a longer gap."""
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")


def expiring(log: DataFrame, days: int) -> DataFrame:
    """An edge's time to live: each insert is followed by a delete, unless another insert comes first."""
    from pyspark.sql import Window as W

    nxt = F.lead("t").over(W.partitionBy("a", "b").orderBy("t"))
    end = F.col("t") + F.make_interval(days=F.lit(days))
    adds = log.where("op = 'add'").withColumn("next", nxt)
    gone = adds.where(F.col("next").isNull() | (F.col("next") > end)).select(end.alias("t"), F.lit("del").alias("op"), "a", "b")
    return log.select("t", "op", "a", "b").unionByName(gone)
