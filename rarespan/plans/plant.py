"""Planted series: normal instances of one class, and instances of other classes put between them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rarespan.runtime import table


def shapes(spark: SparkSession, d: str, blend: float = 0.25, shape: str = "cumsum", length: int = 64) -> DataFrame:
    """(vec_id, label, k, v): instances of the labelled vectors, ``length`` values each.

    The raw vectors carry no class shape, so an instance is its class's prototype (mean vector, scaled to deviation 1, summed up for
    "cumsum") plus ``blend`` times its own vector scaled likewise; blend None gives the raw vector. Other lengths are interpolated linearly.
    """
    e = table(spark, d, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("k", "e")).withColumn("e", F.col("e").cast("double"))
    if blend is None:
        flat = e.select("vec_id", "label", "k", F.col("e").alias("v"))
    else:
        proto = e.groupBy("label", "k").agg(F.avg("e").alias("m"))
        per = Window.partitionBy("label")
        proto = proto.withColumn("m", (F.col("m") - F.avg("m").over(per)) / F.stddev_samp("m").over(per))
        own = Window.partitionBy("vec_id")
        e = e.withColumn("e", (F.col("e") - F.avg("e").over(own)) / F.stddev_samp("e").over(own))
        flat = e.join(F.broadcast(proto), ["label", "k"]).select("vec_id", "label", "k", (F.col("m") + F.lit(blend) * F.col("e")).alias("v"))
        if shape == "cumsum":
            flat = flat.withColumn("v", F.sum("v").over(Window.partitionBy("vec_id").orderBy("k").rowsBetween(Window.unboundedPreceding, 0)))
    if length == 64:
        return flat
    whole = flat.groupBy("vec_id", "label").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "v"))), lambda s: s["v"]).alias("vs"))
    fine = whole.select("vec_id", "label", "vs", F.posexplode(F.sequence(F.lit(0), F.lit(length - 1))).alias("k", "_i"))
    at = F.col("k") * F.lit(63.0 / (length - 1))
    i = F.least(F.floor(at).cast("int"), F.lit(62))
    a, b = F.element_at("vs", i + 1), F.element_at("vs", i + 2)
    return fine.select("vec_id", "label", "k", (a + (b - a) * (at - i)).alias("v"))


def _draw(spark: SparkSession, d: str, label: int, copies: int, normal: int, planted: int, seed: int) -> DataFrame:
    """(dataset, copy, vec_id, normal, rank): which instances each series takes, by md5 order."""
    ids = table(spark, d, "embeddings").select("vec_id", "label").withColumn("normal", F.col("label") == label)
    runs = ids.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    key = F.md5(F.concat_ws(":", F.lit(seed), F.lit(label), "copy", "vec_id"))
    rank = F.row_number().over(Window.partitionBy("copy", "normal").orderBy(key, "vec_id")) - 1
    return runs.withColumn("rank", rank).where(F.col("rank") < F.when(F.col("normal"), normal).otherwise(planted))


def planted(
    spark: SparkSession, d: str, label: int, copies: int = 25, normal: int = 20, anomalies: int = 1, blend: float | None = 0.25, length: int = 64, seed: int = 7, shape: str = "cumsum"
) -> tuple[DataFrame, DataFrame]:
    """(series, truth): series (dataset, series_id, pos, x) with ``anomalies`` instances inserted between 40 % and 80 % of the normal part.

    Places come from md5 numbers; with two anomalies, each takes its own half of the range. truth has dataset, series_id, true_loc, true_len.
    """
    drawn = _draw(spark, d, label, copies, normal, anomalies, seed)
    n = drawn.where("normal").groupBy("copy").agg(F.count("*").alias("have"))
    drawn = drawn.join(n, "copy")
    base = F.col("have") * length
    number = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), F.lit("place"), F.lit(label), "copy", "rank")), 1, 7), 16, 10).cast("long")
    low, high = F.ceil(base * 0.4), F.floor(base * 0.8)
    width = F.floor((high - low) / anomalies)
    place = (low + width * F.col("rank") + number % F.greatest(width - (length if anomalies > 1 else 0), F.lit(1))).cast("long")
    cuts = drawn.where("not normal").withColumn("at", place).select("copy", F.col("rank").alias("r"), "at", F.col("vec_id").alias("odd"))
    per = cuts.groupBy("copy").agg(F.array_sort(F.collect_list("at")).alias("ats"))
    v = shapes(spark, d, blend, shape, length).withColumn("x", F.floor(F.col("v") * 10_000 + 0.5).cast("long"))
    body = drawn.where("normal").join(per, "copy").join(v.drop("label"), "vec_id")
    raw = F.col("rank") * length + F.col("k")  # place in the normal part, from 0
    shift = F.size(F.filter("ats", lambda a: a <= raw))
    body = body.select("copy", (raw + shift * length + 1).cast("long").alias("pos"), "x")
    odd = cuts.join(per, "copy").join(v.drop("label"), F.col("odd") == F.col("vec_id"))
    before = F.size(F.filter("ats", lambda a: a < F.col("at")))
    start = F.col("at") + before * length
    odd_rows = odd.select("copy", (start + F.col("k") + 1).cast("long").alias("pos"), "x")
    name = F.concat(F.lit(f"{label}-"), F.lpad(F.col("copy").cast("string"), 2, "0"))
    series = body.unionByName(odd_rows).select(F.lit(label).alias("dataset"), name.alias("series_id"), "pos", "x")
    truth = cuts.join(per, "copy").select(F.lit(label).alias("dataset"), name.alias("series_id"), (start + 1).cast("long").alias("true_loc"), F.lit(length).alias("true_len"))
    return series, truth
