"""The committee: drawing members, dropping flat curves, scaling, and the point-wise median."""

from __future__ import annotations

import math
from collections.abc import Iterator
from hashlib import md5

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rarespan.operators.layout import dealt_by, whole_groups
from rarespan.schemas import CURVE_RUN, PACKED_CURVE

_KEYS = ["series_id", "w", "a"]
SEGMENT = 1 << 20


def draw_params(n_members: int, w_max: int = 10, a_max: int = 10, seed: int = 42, w_cap: int | None = None) -> list[tuple[int, int]]:
    """Distinct pairs (w, a) from 2..w_max x 2..a_max in the order of md5("seed:w:a"); a smaller committee is a prefix of a larger one."""
    pairs = [(w, a) for w in range(2, w_max + 1) for a in range(2, a_max + 1) if w_cap is None or w <= w_cap]
    return sorted(pairs, key=lambda p: md5(f"{seed}:{p[0]}:{p[1]}".encode()).hexdigest())[:n_members]


def curve_stats(runs: DataFrame) -> DataFrame:
    """(series_id, w, a, len, total, top, spread): spread = len * sum d*d - (sum d)^2 is an exact integer that ranks like the deviation."""
    size = F.col("hi") - F.col("lo") + 1
    d = F.col("d").cast("long")
    return _spread(runs.groupBy(*_KEYS).agg(F.sum(size).alias("len"), F.sum(size * d).alias("total"), F.sum(size * d * d).alias("squares"), F.max("d").alias("top")))


def packed_stats(runs: DataFrame) -> DataFrame:
    """``curve_stats`` of PACKED_RUNS."""
    size = F.col("last") - F.col("first") + 1
    return _spread(runs.groupBy(*_KEYS).agg(F.sum(size).alias("len"), F.sum("total").alias("total"), F.sum("squares").alias("squares"), F.max("top").alias("top")))


def _spread(s: DataFrame) -> DataFrame:
    whole = lambda c: F.col(c).cast("decimal(19,0)")
    spread = (whole("len") * whole("squares") - whole("total") * whole("total")).cast("decimal(38,0)").alias("spread")
    return s.select(*_KEYS, F.col("len").cast("long").alias("len"), F.col("total").cast("long").alias("total"), F.col("top").cast("long").alias("top"), spread)


def deviation(stats: DataFrame) -> DataFrame:
    """Adds sd, the population deviation of the curve over its points, and level, its mean."""
    return stats.withColumn("sd", F.sqrt(F.col("spread").cast("double")) / F.col("len")).withColumn("level", F.col("total") / F.col("len"))


def kept_count(tau: float, members: int) -> int:
    return max(1, math.ceil(tau * members - 1e-9))


def keep_by_spread(stats: DataFrame, tau: float = 0.4) -> DataFrame:
    """The ceil(tau x members) steadiest-ranked curves of each series: largest spread first, ties by w, then a."""
    per = Window.partitionBy("series_id")
    rank = F.row_number().over(per.orderBy(F.desc("spread"), "w", "a"))
    most = F.greatest(F.lit(1), F.ceil(F.lit(tau) * F.count("*").over(per) - F.lit(1e-9)))
    return stats.withColumn("rank", rank).withColumn("most", most).where("rank <= most").drop("most")


def scaled(runs: DataFrame, kept: DataFrame, norm: str = "max") -> DataFrame:
    """Kept curves with value v: by their own maximum (zeros stay zeros; an all-zero curve too), min-max, or not scaled."""
    least = runs.groupBy(*_KEYS).agg(F.min("d").alias("low")) if norm == "minmax" else None
    got = runs.join(kept.select(*_KEYS, "top"), _KEYS)
    if norm == "max":
        v = F.when(F.col("top") > 0, F.col("d") / F.when(F.col("top") > 0, F.col("top"))).otherwise(0.0)
    elif norm == "minmax":
        got = got.join(least, _KEYS)
        gap = F.col("top") - F.col("low")
        v = F.when(gap > 0, (F.col("d") - F.col("low")) / F.when(gap > 0, gap)).otherwise(0.0)
    else:
        v = F.col("d").cast("double")
    return got.select(*_KEYS, "lo", "hi", v.alias("v"))


def combine(curves: DataFrame, how: str = "median", segment: int = SEGMENT) -> DataFrame:
    """CURVE_RUN rows: the point-wise combination of each series' curves (lo, hi, v).

    Runs are cut at multiples of ``segment`` positions and dealt by (series, segment), so a long series is combined by many tasks, and
    what a task holds is runs, not points.
    """
    first, last = F.expr(f"(lo - 1) div {segment}"), F.expr(f"(hi - 1) div {segment}")
    cut = curves.withColumn("seg", F.explode(F.sequence(first, last)))
    cut = cut.withColumn("lo", F.greatest("lo", F.col("seg") * segment + 1)).withColumn("hi", F.least("hi", (F.col("seg") + 1) * segment))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        from rarespan.operators.kernel import merge_curves

        parts = [(g["lo"].to_numpy(), g["v"].to_numpy(float)) for _, g in pdf.sort_values("lo").groupby(["w", "a"])]
        lo, hi, v = merge_curves(parts, int(pdf["lo"].min()), int(pdf["hi"].max()), how)
        return pd.DataFrame({"series_id": pdf["series_id"].iloc[0], "lo": lo, "hi": hi, "de": v, "kept": np.int32(len(parts))})

    return cut.select("series_id", "seg", "w", "a", "lo", "hi", "v").groupBy("series_id", "seg").applyInPandas(run, CURVE_RUN)


def combine_packed(runs: DataFrame, kept: DataFrame, how: str = "median") -> DataFrame:
    """PACKED_CURVE rows: kept curves of PACKED_RUNS scaled by their maximum and combined point by point, as by ``scaled`` and ``combine``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from rarespan.operators.kernel import merge_curves

        for rows, starts in whole_groups(batches, ["series_id", "seg"]):
            for lo, hi in zip(starts, starts[1:], strict=False):
                parts: dict[tuple, list] = {}
                own = rows.slice(lo, hi - lo).to_pylist()
                for r in own:  # a member's parts come in order
                    at, d = np.frombuffer(r["at"], np.int32) + np.int64(r["first"]), np.frombuffer(r["d"], np.int32)
                    parts.setdefault((r["w"], r["a"]), []).append((at, d / r["most"] if r["most"] else d.astype(float)))
                curves = [tuple(np.concatenate(c) for c in zip(*p, strict=True)) for p in parts.values()]
                first, last = min(r["first"] for r in own), max(r["last"] for r in own)
                at, _, de = merge_curves(curves, first, last, how)
                columns = [own[0]["series_id"]], [own[0]["seg"]], [first], [last], np.array([len(curves)], np.int32), [(at - first).astype(np.int32).tobytes()], [de.tobytes()]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], [c.split()[0] for c in PACKED_CURVE.split(", ")])

    got = runs.join(F.broadcast(kept.select(*_KEYS, F.col("top").alias("most"))), _KEYS).select("series_id", "seg", "w", "a", "first", "last", "at", "d", "most")
    return dealt_by(got, ["series_id", "seg"], ["w", "a", "first"]).mapInArrow(run, PACKED_CURVE)


def unpacked(curve: DataFrame) -> DataFrame:
    """CURVE_RUN rows of PACKED_CURVE."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                lo = np.frombuffer(r["at"], np.int32) + np.int64(r["first"])
                name, kept = (pa.repeat(pa.scalar(v, t), len(lo)) for v, t in ((r["series_id"], pa.string()), (r["kept"], pa.int32())))
                yield pa.RecordBatch.from_arrays([name, pa.array(lo), pa.array(np.append(lo[1:] - 1, r["last"])), pa.array(np.frombuffer(r["de"])), kept], ["series_id", "lo", "hi", "de", "kept"])

    return curve.mapInArrow(run, CURVE_RUN)
