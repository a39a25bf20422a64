"""Streams around the methods: user profiles by event-time windows, and a continuous inverse range query."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from inverse_engine.functions.geometry import columns, coordinates, max_dist2_of_set

#: The schema of `events` files (timestamps without zone).
EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_a_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_a_batch).parquet(path)


def _profile(grouped) -> DataFrame:
    return grouped.agg(F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"), F.count("*").alias("n"))


def user_profiles(events: DataFrame, width: str, slide: str | None = None, late: str | None = None) -> DataFrame:
    """(user_id, win, cents, n) by tumbling or sliding windows; `late` sets a watermark (streams)."""
    rows = events.withColumn("at", F.col("ts").cast("timestamp"))
    rows = rows.withWatermark("at", late) if late else rows
    win = F.window("at", width, slide) if slide else F.window("at", width)
    return _profile(rows.groupBy("user_id", win.alias("w"))).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("win"), "cents", "n")


def session_profiles(events: DataFrame, gap: str, late: str | None = None) -> DataFrame:
    rows = events.withColumn("at", F.col("ts").cast("timestamp"))
    rows = rows.withWatermark("at", late) if late else rows
    return _profile(rows.groupBy("user_id", F.session_window("at", gap).alias("w"))).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("win"), "cents", "n")


def continuous_eps_range(points: DataFrame, rows: DataFrame, d: int) -> DataFrame:
    """(set_id, id) for a stream of points (id, x0..) and fixed gathered sets with eps: a row needs no other, so output appends."""
    far = max_dist2_of_set(columns(coordinates(d)), F.col("qs"), d)
    return points.join(F.broadcast(rows), far <= F.col("eps") * F.col("eps")).select("set_id", "id")


def once_each(events: DataFrame, late: str) -> DataFrame:
    """Events without repetitions of their id within the watermark."""
    return events.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late).dropDuplicatesWithinWatermark(["event_id"]).drop("at")
