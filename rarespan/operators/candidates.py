"""Ranking the places of low density."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rarespan.runtime import cut
from rarespan.schemas import CANDIDATE

SEGMENT = 1 << 17


def plateaus(curve: DataFrame, k: int | None = None) -> DataFrame:
    """Local minima of a run-length curve (series_id, lo, hi, de): runs lower than both neighbours, by value, then place. Any length."""
    over = Window.partitionBy("series_id").orderBy("lo")
    runs = curve.withColumn("_b", F.lag("de").over(over)).where("_b is null or _b <> de")
    runs = runs.withColumn("_n", F.lead("lo").over(over)).withColumn("_last", F.max("hi").over(Window.partitionBy("series_id")))
    runs = runs.withColumn("hi", F.coalesce(F.col("_n") - 1, F.col("_last")))
    runs = runs.withColumn("_l", F.lag("de").over(over)).withColumn("_r", F.lead("de").over(over))
    low = runs.where("(_l is null or de < _l) and (_r is null or de < _r) and not (_l is null and _r is null)")
    rank = F.row_number().over(Window.partitionBy("series_id").orderBy("de", "lo"))
    out = low.select("series_id", rank.alias("rank"), "lo", "hi", F.col("lo").alias("loc"), F.col("de").alias("value"))
    return out.where(F.col("rank") <= k) if k else out


def window_values(curve: DataFrame, n: int) -> DataFrame:
    """(series_id, pos, value): summed density of the window at each position, from a run-length curve."""
    points = curve.select("series_id", F.explode(F.sequence("lo", "hi")).alias("pos"), "de")
    over = Window.partitionBy("series_id").orderBy("pos").rowsBetween(0, n - 1)
    got = points.withColumn("value", F.sum("de").over(over)).withColumn("len", F.count("*").over(over))
    return got.where(f"len = {n}").select("series_id", "pos", F.round("value", 9).alias("value"))


def top_windows(values: DataFrame, n: int, k: int = 3, exclusion: int | None = None) -> DataFrame:
    """The k windows of smallest value (series_id, pos, value) that keep ``exclusion`` apart; ties to the left. k small aggregations, no sort."""
    exclusion = n if exclusion is None else exclusion
    rest, found = values, []
    for r in range(1, k + 1):
        best = rest.groupBy("series_id").agg(F.min(F.struct("value", "pos")).alias("m")).select("series_id", F.lit(r).alias("rank"), F.col("m.pos").alias("loc"), F.col("m.value").alias("value"))
        found.append(best)
        if r < k:
            near = best.select("series_id", F.col("loc").alias("_loc"))
            rest = rest.join(near, "series_id").where(F.abs(F.col("pos") - F.col("_loc")) >= exclusion).drop("_loc")
    out = found[0]
    for f in found[1:]:
        out = out.unionByName(f)
    return out.select("series_id", "rank", F.col("loc").alias("lo"), (F.col("loc") + n - 1).alias("hi"), "loc", "value")


def window_candidates(curve: DataFrame, n: int, k: int = 3, exclusion: int | None = None, edge: str = "keep") -> DataFrame:
    """CANDIDATE rows in window form, one kernel call a series; for series whose points fit a task. Same result as ``top_windows``."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        from rarespan.operators.kernel import window_candidates as pick

        pdf = pdf.sort_values("lo")
        size = (pdf["hi"] - pdf["lo"] + 1).to_numpy()
        base = int(pdf["lo"].iloc[0])
        got = pick(np.repeat(pdf["de"].to_numpy(float), size), n, k, exclusion, edge)
        rows = [(pdf["series_id"].iloc[0], r + 1, base + i, base + i + n - 1, base + i, v) for r, (i, v) in enumerate(got)]
        return pd.DataFrame(rows, columns=["series_id", "rank", "lo", "hi", "loc", "value"])

    return curve.select("series_id", "lo", "hi", "de").groupBy("series_id").applyInPandas(run, CANDIDATE)


def long_window_candidates(curve: DataFrame, n: int, k: int = 3, exclusion: int | None = None, edge: str = "keep", segment: int = SEGMENT) -> DataFrame:
    """CANDIDATE rows in window form for series of any length: same result as ``window_candidates``, no task holds more than ``segment`` + n points.

    Runs are dealt to segments of window starts, those within n - 1 of the next one to both. Each segment keeps its least window; the least of those is the series' next
    candidate, and only the segments that it touches are searched again for the one after.
    """
    exclusion = n if exclusion is None else exclusion
    size, margin = max(segment, n), n if edge == "drop" else 0
    runs = curve.select("series_id", "lo", "hi", F.col("de").cast("double").alias("de"))
    ends = runs.groupBy("series_id").agg((F.min("lo") + margin).alias("first"), (F.max("hi") - (n - 1 + margin)).alias("final")).where("first <= final")
    dealt = runs.join(ends, "series_id").withColumn("_a", F.greatest(F.col("lo") - (n - 1), "first")).withColumn("_b", F.least("hi", "final")).where("_a <= _b")
    segments = F.sequence(F.expr(f"(_a - first) div {size}"), F.expr(f"(_b - first) div {size}"))
    pieces = cut(dealt.select("series_id", "lo", "hi", "de", "first", "final", F.explode(segments).alias("seg")))

    def least(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("lo")
        own = pdf.iloc[0]
        start = int(own["first"] + own["seg"] * size)
        stop = min(start + size - 1, int(own["final"]))
        lo, hi = (np.clip(pdf[c].to_numpy(), start, stop + n - 1) for c in ("lo", "hi"))
        total = np.concatenate(([0.0], np.cumsum(np.repeat(pdf["de"].to_numpy(float), hi - lo + 1))))
        value = np.round(total[n:] - total[:-n], 9)
        for q in own["taken"]:
            value[max(0, q - exclusion + 1 - start) : max(0, q + exclusion - start)] = np.inf
        i = int(value.argmin())
        rows = [(own["series_id"], int(own["seg"]), int(own["first"]), start + i, float(value[i]))] if np.isfinite(value[i]) else []
        return pd.DataFrame(rows, columns=["series_id", "seg", "first", "pos", "value"])

    schema = "series_id string, seg long, first long, pos long, value double"
    best = cut(pieces.withColumn("taken", F.array().cast("array<bigint>")).groupBy("series_id", "seg").applyInPandas(least, schema))
    found = None
    for r in range(1, k + 1):
        top = best.groupBy("series_id").agg(F.min(F.struct("value", "pos", "first")).alias("m"))
        top = cut(top.select("series_id", F.lit(r).alias("rank"), F.col("m.pos").alias("loc"), F.col("m.value").alias("value"), F.col("m.first").alias("first")))
        found = top if found is None else found.unionByName(top)
        if r < k:
            taken = found.groupBy("series_id").agg(F.collect_list("loc").alias("taken"))
            near = F.sequence(F.expr(f"greatest(loc - {exclusion - 1} - first, 0) div {size}"), F.expr(f"(loc + {exclusion - 1} - first) div {size}"))
            touched = top.select("series_id", F.explode(near).alias("seg")).join(taken, "series_id")
            again = pieces.join(touched, ["series_id", "seg"]).groupBy("series_id", "seg").applyInPandas(least, schema)
            best = cut(best.join(touched, ["series_id", "seg"], "left_anti").unionByName(again))
    return found.select("series_id", "rank", F.col("loc").alias("lo"), (F.col("loc") + n - 1).alias("hi"), "loc", "value")
