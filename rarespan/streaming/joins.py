"""Joins of streams: events with static spans, and pairs of events that follow each other. Both work on static tables too."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def in_spans(rows: DataFrame, spans: DataFrame, at: str = "step", by: str = "series_id", width: int = 1024) -> DataFrame:
    """Rows of a stream (or table) that lie in spans (by, lo, hi, ...) of a static table, with the span's further columns.

    Spans are cut into bins of ``width`` steps, so the join is on equal (by, bin) whatever the spans' lengths; a row in several spans appears once for each.
    """
    bins = F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))
    cut = spans.withColumn("_bin", F.explode(bins))
    found = rows.withColumn("_bin", F.floor(F.col(at) / width)).join(cut, [by, "_bin"])
    return found.where(F.col(at).between(F.col("lo"), F.col("hi"))).drop("_bin")


def followed(first: DataFrame, second: DataFrame, by: str = "user_id", at: str = "ts", name: str = "event_id", within_s: int = 3600, delay: str = "2 hours") -> DataFrame:
    """(by, first_id, second_id, gap_us): rows of ``second`` of the same key at most ``within_s`` seconds after a row of ``first`` (equal times included).

    On streams both sides are bounded by their watermarks. Times are dealt to bins as wide as the allowed gap, and a first row asks two of them, so a busy key is split by
    time, and each pair meets once.
    """
    if first.isStreaming:
        first, second = first.withWatermark(at, delay), second.withWatermark(at, delay)
    bin_of = lambda c: F.floor(F.unix_seconds(F.col(c)) / within_s)
    a = first.select(F.col(by), F.col(name).alias("first_id"), F.col(at).alias("_from"), F.explode(F.array(bin_of(at), bin_of(at) + 1)).alias("_bin"))
    b = second.select(F.col(by), F.col(name).alias("second_id"), F.col(at).alias("_to"), bin_of(at).alias("_bin"))
    near = f"_to >= _from and _to <= _from + interval {within_s} seconds"
    found = a.join(b, [by, "_bin"]).where(near)
    return found.select(by, "first_id", "second_id", (F.unix_micros("_to") - F.unix_micros("_from")).alias("gap_us"))
