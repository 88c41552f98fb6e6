"""Edges as streams over files of `events`: windows, late data, repeated edges, joins, and distances kept up to date as edges arrive.

Event times are cast to TIMESTAMP before a watermark. Every stream has a batch twin with the same rows, so tests compare the two.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphslices.schema import INF
from graphslices.session import cut, shared_dir


def stream_source(spark: SparkSession, path: str, files_a_batch: int = 4) -> DataFrame:
    """A folder (or file pattern) of Parquet files as a stream; its schema is read from what is there."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_batch).parquet(path)


def timed_edges(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """(src, dst, event_id, time) user to event type, with a watermark."""
    e = events.select(F.col("user_id").alias("src"), "event_type", "event_id", F.col("ts").cast("timestamp").alias("time"))
    return e.withWatermark("time", watermark)


def window_of(kind: str):
    return {"tumbling": F.window("time", "1 hour"), "sliding": F.window("time", "1 hour", "15 minutes"), "session": F.session_window("time", "30 minutes")}[kind]


def degrees_in_windows(edges: DataFrame, kind: str = "tumbling") -> DataFrame:
    """(start, finish, src, deg): for batches and streams alike. Session windows are kept per user."""
    w = window_of(kind).alias("w")
    return edges.groupBy(w, "src").agg(F.count("*").alias("deg")).select(F.col("w.start").alias("start"), F.col("w.end").alias("finish"), "src", "deg")


def dedupe_edges(edges: DataFrame) -> DataFrame:
    """One edge (src, event_type) while the watermark has not passed it."""
    return edges.dropDuplicatesWithinWatermark(["src", "event_type"]) if edges.isStreaming else edges.dropDuplicates(["src", "event_type"])


def enrich(edges: DataFrame, customers: DataFrame) -> DataFrame:
    """A stream's edges with attributes of a static table."""
    return edges.join(customers.select(F.col("c_custkey").alias("src"), "c_nationkey"), "src")


def coactivity(left: DataFrame, right: DataFrame, minutes: int = 5) -> DataFrame:
    """Pairs of users with an event of one type less than some minutes apart: a stream-stream join with a time bound on both sides.

    A few types are no key to join by: times are cut into slots of twice the bound, an event on the right lies in one, and one on the left is sent to the one or two that its span touches. So a pair meets once.
    """
    slot = lambda t: F.floor(F.unix_seconds(t) / (120 * minutes))
    span = F.expr(f"INTERVAL {minutes} MINUTES")
    a = left.select(F.col("src").alias("a"), F.col("event_type").alias("ta"), F.col("time").alias("at"), F.explode(F.sequence(slot(F.col("time") - span), slot(F.col("time") + span))).alias("sa"))
    b = right.select(F.col("src").alias("b"), F.col("event_type").alias("tb"), F.col("time").alias("bt"), slot(F.col("time")).alias("sb"))
    near = F.expr(f"bt >= at - INTERVAL {minutes} MINUTES AND bt <= at + INTERVAL {minutes} MINUTES AND a < b AND ta = tb AND sa = sb")
    return a.join(b, near).select("a", "b", F.col("ta").alias("event_type"), F.col("at"), F.col("bt"))


def drain_to_table(stream: DataFrame, mode: str = "append", checkpoint: str | None = None, each: Callable[[DataFrame], DataFrame] = lambda batch: batch) -> DataFrame:
    """Runs a stream over what is there and gives its rows, kept as Parquet where the mode allows it. For tests and backfills. each: what is done with a batch before it is written."""
    spark = stream.sparkSession
    name = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    out = f"{name}/rows"

    def keep(batch: DataFrame, i: int) -> None:
        each(batch).write.mode("overwrite" if mode == "complete" else "append").parquet(out)

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint or f"{name}/state").trigger(availableNow=True).foreachBatch(keep).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


class MinDistance:
    """Distances from a root under insertions: each batch of edges starts relaxations from the vertices it brings nearer. Deletions are not covered."""

    def __init__(self, spark: SparkSession, root: int):
        self.dist = cut(spark.createDataFrame([(root, 0)], "vertex long, dist int"))
        self.edges = cut(spark.createDataFrame([], "src long, dst long"))

    def insert(self, batch: DataFrame, batch_id: int = 0) -> None:
        both = batch.select("src", "dst").unionByName(batch.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        new = cut(both.distinct().join(self.edges, ["src", "dst"], "left_anti"))
        self.edges = cut(self.edges.unionByName(new))
        step = new
        while True:
            near = step.join(self.dist, F.col("src") == F.col("vertex")).groupBy(F.col("dst").alias("v")).agg((F.min("dist") + 1).alias("d"))
            better = cut(near.join(self.dist, F.col("v") == F.col("vertex"), "left").where(F.col("d") < F.coalesce("dist", F.lit(INF))).select(F.col("v").alias("vertex"), F.col("d").alias("dist")))
            if better.isEmpty():
                return
            self.dist = cut(self.dist.join(better.select("vertex"), "vertex", "left_anti").unionByName(better))
            step = self.edges.join(better.select(F.col("vertex").alias("src")), "src", "left_semi")


def stream_min_distance(stream: DataFrame, root: int, make_edges: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Feeds a stream's batches to MinDistance and gives (vertex, dist) at the end of what is there."""
    spark = stream.sparkSession
    state = MinDistance(spark, root)
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    q = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", base).foreachBatch(lambda b, i: state.insert(make_edges(b), i)).start()
    q.awaitTermination()
    return state.dist


# -- whole queries over a folder's events --------------------------------------------------------------------------------------------------


def stream_degrees(spark: SparkSession, d: str, kind: str = "tumbling") -> DataFrame:
    """A stream's windowed degrees, once all of events.parquet has been read: a complete result."""
    edges = timed_edges(stream_source(spark, f"{d}/events.parquet*"), "3650 days")
    return drain_to_table(degrees_in_windows(edges, kind), "complete")


def stream_dedupe(spark: SparkSession, d: str) -> DataFrame:
    edges = timed_edges(stream_source(spark, f"{d}/events.parquet*"), "3650 days")
    return drain_to_table(dedupe_edges(edges)).select("src", "event_type")


def stream_enrich(spark: SparkSession, d: str) -> DataFrame:
    edges = timed_edges(stream_source(spark, f"{d}/events.parquet*"))
    return drain_to_table(enrich(edges, spark.read.parquet(f"{d}/customer.parquet"))).select("event_id", "src", "c_nationkey")


def stream_coactivity(spark: SparkSession, d: str) -> DataFrame:
    only = lambda: timed_edges(stream_source(spark, f"{d}/events.parquet*").where("event_type = 'purchase'"), "3650 days")
    return drain_to_table(coactivity(only(), only()).select("a", "b"), each=DataFrame.distinct).distinct()


def stream_distance(spark: SparkSession, d: str) -> DataFrame:
    """Distances from the first user over the graph of users and purchases' hours, edge by edge as events arrive, in several batches."""
    parts = f"{shared_dir(spark)}/events-{uuid.uuid4().hex}"
    only = spark.read.parquet(f"{d}/events.parquet").where("event_type = 'purchase'")
    only.repartition(4, "event_id").write.parquet(parts)
    root = spark.read.parquet(f"{d}/events.parquet").agg(F.min(2 * F.col("user_id"))).first()[0]
    hour = F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / 3600)
    return stream_min_distance(stream_source(spark, f"{parts}/*.parquet", 1), root, lambda b: b.select((2 * F.col("user_id")).alias("src"), (2 * hour + 1).cast("long").alias("dst")))
