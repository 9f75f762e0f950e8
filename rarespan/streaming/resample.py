"""Streaming forms of resampling, bursts and deduplication. Each works on a static table too, with the same result over closed windows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rarespan.sources.series import cents

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A stream over a folder of event files, with ts as an instant (watermarks need one)."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return with_instant(raw)


def with_instant(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def deduplicated(events: DataFrame, delay: str = "2 hours") -> DataFrame:
    """One row for each event_id; on a stream, within the watermark."""
    if events.isStreaming:
        return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def tumbling(events: DataFrame, length: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """(series_id, step, x): sums of cents for each type and window; step counts windows of an hour from the epoch."""
    e = events.withWatermark("ts", delay) if events.isStreaming else events
    g = e.groupBy(F.window("ts", length), "event_type").agg(F.sum(cents("value")).alias("x"))
    return g.select(F.col("event_type").alias("series_id"), F.floor(F.unix_timestamp("window.start") / 3600).cast("long").alias("step"), "x")


def sliding(events: DataFrame, length: str = "24 hours", slide: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """(start, n, total): count and cents of overlapping windows."""
    e = events.withWatermark("ts", delay) if events.isStreaming else events
    g = e.groupBy(F.window("ts", length, slide)).agg(F.count("*").alias("n"), F.sum(cents("value")).alias("total"))
    return g.select(F.unix_timestamp("window.start").alias("start"), "n", "total")


def bursts(events: DataFrame, gap: str = "30 minutes", delay: str = "2 hours") -> DataFrame:
    """(user_id, start, stop, n, total): sessions of each user's activity."""
    e = events.withWatermark("ts", delay) if events.isStreaming else events
    g = e.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"), F.sum(cents("value")).alias("total"))
    return g.select("user_id", F.unix_timestamp("session_window.start").alias("start"), F.unix_timestamp("session_window.end").alias("stop"), "n", "total")
