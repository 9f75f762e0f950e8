"""Where streams end: Parquet files, and batches that may be written again after a failure without doubling rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery


def to_parquet(stream: DataFrame, path: str, checkpoint: str, available_now: bool = True) -> StreamingQuery:
    """The file sink: its own log in ``path`` makes each batch appear once."""
    return _start(stream.writeStream.format("parquet").outputMode("append").option("path", path), checkpoint, available_now)


def write_batch(rows: DataFrame, batch: int, path: str, keys: list[str]) -> None:
    """One batch in a folder of its own, one row a key (the smallest). A batch that is written again replaces its folder."""
    one = rows.groupBy(*keys).agg(F.min(F.struct(*(c for c in rows.columns if c not in keys))).alias("_row"))
    one.select(*keys, "_row.*").write.mode("overwrite").parquet(f"{path}/batch={batch}")


def to_batches(stream: DataFrame, path: str, checkpoint: str, keys: list[str], available_now: bool = True) -> StreamingQuery:
    """``write_batch`` for every batch; Spark numbers a repeated batch alike, so a replay changes nothing."""
    return _start(stream.writeStream.outputMode("append").foreachBatch(lambda rows, batch: write_batch(rows, batch, path, keys)), checkpoint, available_now)


def read_batches(spark: SparkSession, path: str, keys: list[str]) -> DataFrame:
    """All rows written, one a key: that of the earliest batch."""
    rows = spark.read.parquet(path)
    rest = [c for c in rows.columns if c not in (*keys, "batch")]
    return rows.groupBy(*keys).agg(F.min(F.struct("batch", *rest)).alias("_row")).select(*keys, *(F.col(f"_row.{c}").alias(c) for c in rest))


def dropped_late(query: StreamingQuery) -> int:
    """Rows that came after the watermark had passed them, over the progress reports the query still holds (after partial aggregation, where there is one)."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])


def _start(writer, checkpoint: str, available_now: bool) -> StreamingQuery:
    writer = writer.option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()
