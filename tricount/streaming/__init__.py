"""Streams of events and edges: windowed counts, incremental exact counts, degrees, co-activity, late and repeated rows."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.exact import list_triangles
from ..operators.graph import canonicalize
from ..session import shared_folder

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str) -> DataFrame:
    """The table events as a stream; its zoneless times become instants, which watermarks need."""
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", "*.parquet").parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def staged(spark: SparkSession, events: DataFrame, batches: int = 1) -> str:
    """A folder with ``events`` in files that a stream reads one by one, in the order of event_id."""
    path = f"{shared_folder(spark)}/events-{uuid.uuid4().hex}"
    if batches == 1:
        events.write.mode("append").parquet(path)
        return path
    low, high = events.agg(F.min("event_id"), F.max("event_id")).collect()[0]
    step = (high - low) // batches + 1
    for b in range(batches):
        events.where(F.col("event_id").between(low + b * step, low + (b + 1) * step - 1)).coalesce(1).write.mode("append").parquet(path)
    return path


def drained(out: DataFrame, mode: str = "complete") -> DataFrame:
    """Run a stream over what there is and read its result back, from Parquet in the shared folder."""
    spark = out.sparkSession
    path = f"{shared_folder(spark)}/out-{uuid.uuid4().hex}"
    schema = out.schema
    sink = out.writeStream.outputMode(mode).option("checkpointLocation", f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}").trigger(availableNow=True)
    if mode == "append":
        q = sink.format("parquet").option("path", path).start()
    else:  # every batch gives the whole result: the last one counts
        q = sink.foreachBatch(lambda df, number: df.write.mode("overwrite").parquet(path)).start()
    q.awaitTermination()
    return spark.read.schema(schema).parquet(path)


def window_users(stream: DataFrame, width: str = "1 minute", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """start and users of each tumbling or sliding window."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return stream.withWatermark("ts", late).groupBy(w.alias("w")).agg(F.collect_set("user_id").alias("users")).select(F.unix_seconds("w.start").alias("start"), "users")


def window_counts(stream: DataFrame, width: str = "1 minute", slide: str | None = None) -> DataFrame:
    """start, users, triangles of each window's co-activity, where all users of a window are linked: C(n, 3)."""
    n = F.size("users").cast("long")
    return window_users(stream, width, slide).select("start", n.alias("users"), F.expr("cast(size(users) as bigint) * (size(users) - 1) * (size(users) - 2) div 6").alias("triangles"))


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """user_id, start, events of each session."""
    return stream.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count(F.lit(1)).alias("events")).select("user_id", F.unix_seconds("s.start").alias("start"), "events")


def user_activity(stream: DataFrame) -> DataFrame:
    """user_id and events so far; kept state is one count per user."""
    return stream.groupBy("user_id").agg(F.count(F.lit(1)).alias("events"))


def without_repeats(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events once each, if repeats come within the watermark; rows older than it are dropped."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def coactivity(left: DataFrame, right: DataFrame, seconds: int = 60, late: str = "10 minutes") -> DataFrame:
    """a, b: events of different users (the lower one first) of which b comes at most ``seconds`` after a.

    A watermarked join of two streams needs an equality: times fall into buckets of that width, and a right event stands in
    its own bucket and the one before, so each pair meets in one bucket only.
    """
    bucket = lambda c: F.expr(f"unix_seconds({c}) div {seconds}")
    x = left.withWatermark("ts", late).select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("t"), bucket("ts").alias("k"))
    y = right.withWatermark("ts", late).select(F.col("event_id").alias("b"), F.col("user_id").alias("v"), F.col("ts").alias("s"), F.explode(F.array(bucket("ts"), bucket("ts") - 1)).alias("j"))
    return x.join(y, F.expr(f"k = j AND s >= t AND s <= t + INTERVAL {seconds} SECONDS AND a <> b AND u < v")).select("a", "b")


def added_triangles(known: DataFrame, batch: DataFrame) -> DataFrame:
    """Triangles that the edges of ``batch`` (new, canonical) close: each is found from its first new side only.

    Sides are numbered old = 0 and new = 1. The three joins take the new side as first, second and third side, and let
    only old edges stand before it, so a triangle with two or three new sides counts once.
    """
    every = known.withColumn("new", F.lit(0)).unionByName(batch.withColumn("new", F.lit(1)))
    x = every.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.col("new").alias("ab"))
    y = every.select(F.col("src").alias("b"), F.col("dst").alias("c"), F.col("new").alias("bc"))
    z = every.select(F.col("src").alias("a"), F.col("dst").alias("c"), F.col("new").alias("ac"))
    first = x.where("ab = 1").join(y, "b").join(z, ["a", "c"])
    second = y.where("bc = 1").join(x.where("ab = 0"), "b").join(z, ["a", "c"])
    third = z.where("ac = 1").join(x.where("ab = 0"), "a").join(y.where("bc = 0"), ["b", "c"])
    return first.select("a", "b", "c").unionByName(second.select("a", "b", "c")).unionByName(third.select("a", "b", "c"))


class Incremental:
    """Exact count over a growing set of edges, kept in versions in a folder: a batch that is run again changes nothing."""

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder

    def _edges(self, before: int | None = None) -> DataFrame:
        rows = self.spark.read.schema("src long, dst long, batch long").parquet(f"{self.folder}/edges")
        return rows if before is None else rows.where(F.col("batch") < before)

    def start(self) -> None:
        self.spark.createDataFrame([], "src long, dst long, batch long").write.mode("ignore").parquet(f"{self.folder}/edges")

    def add(self, batch: DataFrame, number: int) -> None:
        """Add a batch of edges; for foreachBatch."""
        known = self._edges(number).select("src", "dst")
        new = canonicalize(batch.select("src", "dst")).join(known, ["src", "dst"], "left_anti").persist()
        found = added_triangles(known, new).agg(F.count(F.lit(1)).alias("triangles"))
        found.write.mode("overwrite").parquet(f"{self.folder}/counts/batch={number}")
        new.select("src", "dst").write.mode("overwrite").parquet(f"{self.folder}/edges/batch={number}")
        new.unpersist()

    def total(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.folder}/counts").agg(F.coalesce(F.sum("triangles"), F.lit(0)).alias("triangles"))

    def check(self) -> DataFrame:
        return list_triangles(self._edges().select("src", "dst").distinct()).agg(F.count(F.lit(1)).alias("triangles"))

    def follow(self, stream: DataFrame, edges_of: Callable[[DataFrame], DataFrame] = lambda df: df) -> None:
        """Run the stream over what there is, batch by batch."""
        self.start()
        q = stream.writeStream.foreachBatch(lambda df, number: self.add(edges_of(df), number)).option("checkpointLocation", f"{self.folder}/progress").trigger(availableNow=True).start()
        q.awaitTermination()
