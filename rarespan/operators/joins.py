"""Joins that Spark has no operator for: nearest earlier row, and interval with point, both on bins."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, at: str, value: str, by: list[str] | None = None, width: int = 4096) -> DataFrame:
    """Adds to ``left`` the ``value`` of the latest row of ``right`` at or before its own ``at`` (a long); null if there is none.

    Both sides are dealt to bins of ``width`` steps and each bin is sorted by itself. What is carried into a bin from earlier ones is one row a
    bin, so the only window that runs over all bins of a key works on 1 / width of the steps. Ties on the right: the greatest value.
    """
    by = by or []
    own = left.columns
    marks = right.groupBy(*by, at).agg(F.max(value).alias("_v")).select(*by, F.col(at).alias("_at"), "_v")
    binned = lambda d, c: d.withColumn("_bin", F.floor(F.col(c) / width))
    asks = binned(left.withColumn("_at", F.col(at)), "_at").withColumn("_ask", F.lit(1)).withColumn("_v", F.lit(None).cast(dict(marks.dtypes)["_v"]))
    marks = binned(marks, "_at").withColumn("_ask", F.lit(0))
    both = asks.unionByName(marks, allowMissingColumns=True)
    inside = Window.partitionBy(*by, "_bin").orderBy("_at", "_ask").rowsBetween(Window.unboundedPreceding, 0)
    both = both.withColumn("_in", F.last("_v", ignorenulls=True).over(inside))
    last = marks.groupBy(*by, "_bin").agg(F.max(F.struct("_at", "_v"))["_v"].alias("_v"))
    bins = both.select(*by, "_bin").distinct().join(last, [*by, "_bin"], "left")
    key = by or [F.lit(0)]
    before = Window.partitionBy(*key).orderBy("_bin").rowsBetween(Window.unboundedPreceding, -1)
    carried = bins.withColumn("_c", F.last("_v", ignorenulls=True).over(before)).drop("_v")
    got = both.where("_ask = 1").drop("_v").join(carried, [*by, "_bin"])
    return got.select(*own, F.coalesce("_in", "_c").alias(value))


def interval_points(intervals: DataFrame, points: DataFrame, at: str, by: list[str] | None = None, width: int = 4096) -> DataFrame:
    """Rows of ``intervals`` (lo, hi) joined with the points inside: both meet on the bin, then the bounds decide."""
    by = by or []
    iv = intervals.withColumn("_bin", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))))
    pts = points.withColumn("_bin", F.floor(F.col(at) / width))
    return iv.join(pts, [*by, "_bin"]).where((F.col(at) >= F.col("lo")) & (F.col(at) <= F.col("hi"))).drop("_bin")
