"""Reading and writing series in any of Spark's file formats, in-memory sources and generators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rarespan.schemas import SERIES_POINT

FORMATS = ("parquet", "orc", "csv", "json")


def read_series(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = SERIES_POINT, first: int | None = None, last: int | None = None) -> DataFrame:
    """A series table; a range of positions is pushed down to the files' statistics."""
    if fmt not in FORMATS:
        raise ValueError(f"format must be one of {FORMATS}")
    df = spark.read.schema(schema).format(fmt).options(**({"header": "true"} if fmt == "csv" else {})).load(path)
    if first is not None:
        df = df.where(F.col("pos") >= first)
    if last is not None:
        df = df.where(F.col("pos") <= last)
    return df


def write_series(df: DataFrame, path: str, fmt: str = "parquet", buckets: int | None = None, mode: str = "errorifexists") -> None:
    """Writes sorted by position, so that file statistics prune ranges; ``buckets`` adds a partition column by series."""
    keys = ["series_id"]
    if buckets:
        df = df.withColumn("series_bucket", F.pmod(F.xxhash64("series_id"), F.lit(buckets)).cast("int"))
        keys = ["series_bucket", *keys]
    out = df.repartition(*keys).sortWithinPartitions(*keys, "pos").write.format(fmt).mode(mode)
    if fmt == "csv":
        out = out.option("header", "true")
    (out.partitionBy("series_bucket") if buckets else out).save(path)


def save_bucketed(df: DataFrame, table: str, buckets: int) -> None:
    """A table bucketed by series and sorted by position: windows and joins by series need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, "series_id").sortBy("series_id", "pos").saveAsTable(table)


def read_tokens(spark: SparkSession, path: str, pattern: str = r"\s+") -> DataFrame:
    """(series_id, pos, word): the words of a text file's lines, each line a sequence."""
    lines = spark.read.text(path, wholetext=False).select(F.md5("value").alias("series_id"), F.split(F.trim("value"), pattern).alias("t"))
    return lines.select("series_id", F.posexplode("t").alias("p", "word")).select("series_id", (F.col("p") + 1).cast("long").alias("pos"), "word")


def from_rows(spark: SparkSession, values: dict[str, list[int]]) -> DataFrame:
    """A series table of Python lists."""
    return spark.createDataFrame([(k, i + 1, int(x)) for k, v in values.items() for i, x in enumerate(v)], SERIES_POINT)


def random_walk(spark: SparkSession, points: int, series: int = 1, seed: int = 1, step: int = 100, chunk: int = 1 << 16) -> DataFrame:
    """Series of hashed steps, summed up in two levels: inside chunks, then over the chunks' sums."""
    n = spark.range(points * series).select((F.floor(F.col("id") / points)).alias("s"), (F.col("id") % points + 1).alias("pos"))
    x = F.pmod(F.xxhash64(F.lit(seed), "s", "pos"), F.lit(2 * step + 1)) - step
    n = n.withColumn("x", x).withColumn("c", F.expr(f"(pos - 1) div {chunk}"))
    before = Window.partitionBy("s").orderBy("c").rowsBetween(Window.unboundedPreceding, -1)
    sums = n.groupBy("s", "c").agg(F.sum("x").alias("t")).withColumn("base", F.coalesce(F.sum("t").over(before), F.lit(0))).drop("t")
    inside = Window.partitionBy("s", "c").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    got = n.withColumn("y", F.sum("x").over(inside)).join(sums, ["s", "c"])
    return got.select(F.concat(F.lit("walk"), F.col("s")).alias("series_id"), "pos", (F.col("y") + F.col("base")).cast("long").alias("x"))


def cyclic(spark: SparkSession, period: int, cycles: int, odd: int | None = None, noise: int = 0, seed: int = 1) -> DataFrame:
    """A hashed pattern repeated ``cycles`` times with noise; cycle ``odd`` (from 0) has another pattern."""
    n = spark.range(period * cycles).select((F.col("id") + 1).alias("pos"), F.floor(F.col("id") / period).alias("c"), (F.col("id") % period).alias("k"))
    shape = lambda s: F.sin(F.col("k") * F.lit(6.283185307179586 / period) * (2 + s)) * 1000 + F.pmod(F.xxhash64(F.lit(seed + s), F.expr("k div 5")), F.lit(600))
    base = shape(0) if odd is None else F.when(F.col("c") == odd, shape(3)).otherwise(shape(0))
    jitter = F.pmod(F.xxhash64(F.lit(seed), F.lit("n"), "pos"), F.lit(2 * noise + 1)) - noise
    return n.select(F.lit("cyclic").alias("series_id"), "pos", (F.floor(base) + jitter).cast("long").alias("x"))
