"""Session helpers shared by every part of the library.

Lineage is cut with ``DataFrame.checkpoint`` only: its files lie in the folder
that ``spark.checkpoint.dir`` names, so they outlive a lost executor.
"""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder; one of our own only where none is configured and all runs in one process, as in tests."""
    sc = spark.sparkContext
    current = sc.getCheckpointDir()
    if current:
        return current
    configured = sc.getConf().get("spark.checkpoint.dir", None)
    if not configured and not sc.master.startswith("local["):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    sc.setCheckpointDir(configured or tempfile.mkdtemp(prefix="rarespan-checkpoint-"))
    return sc.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """Compute ``df`` once, keep it in the shared checkpoint folder and cut its lineage."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def cut_in_loop(df: DataFrame) -> DataFrame:
    """Like ``cut``, without the planner's size estimate. A checkpoint keeps it, and a join's estimate is the product of its sides', so in a loop of joins
    the number of its digits doubles every round and planning ends up multiplying huge integers; joins are then chosen by the sizes seen at run time.
    The estimate also starts from the compressed input and misses what an explode or a kernel adds, so a large table may be broadcast by way of the driver."""
    kept, spark = cut(df), df.sparkSession
    rows = kept._jdf.queryExecution().toRdd()
    return DataFrame(spark._jsparkSession.internalCreateDataFrame(rows, kept._jdf.schema(), False), spark)


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
