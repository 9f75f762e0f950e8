"""A corpus pipeline of five stages over ``documents``: toxicity, near-duplicates, personal data, mixture, packing.

Each stage takes (spark, docs, sf_dir) and works on every row that the stage before it kept; all but the last return the
columns of ``documents``. ``run`` writes each stage's result as Parquet into the session's checkpoint folder and reads it again.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rarespan.llm import mixing, near_copies, packing, pii, toxicity
from rarespan.runtime import ensure_checkpoint_dir, table

TOXIC_FROM = 0.5


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score below ``TOXIC_FROM``; learnt from the labelled rows outside the held-out fold. Null texts stay."""
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    return toxicity.score_documents(docs, model).where(F.col("toxicity") < TOXIC_FROM).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: that of the smallest id. Different texts that share an id are told apart; of repeated rows one stays.

    Linked are texts whose shingle fingerprints differ in at most 3 bits, or whose five-word similarity is 0.8 or more. Rows without an id come last: of a group of
    nothing else, that of the smallest hash of its text stays.
    """
    named = docs.withColumn("_text", F.xxhash64("text"))
    keep = near_copies.near_copies(docs).where("stays").select(F.col("doc_id").alias("_id"), "text_hash").distinct()
    row = F.min_by(F.struct(*docs.columns), F.xxhash64(*(c for c in docs.columns if c != "text"))).alias("row")
    kept = named.join(keep, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_text") == F.col("text_hash")), "left_semi")
    return kept.groupBy("doc_id", "_text").agg(row).select("row.*")


def mask_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data replaced by its kind; n_chars follows the new text."""
    masked = pii.redact(docs)
    return masked.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType)).select(*docs.columns)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mixture's copies say (0, 1 or 2 times)."""
    return mixing.resample(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token sequences of 2048 ids."""
    import public_tokenizers

    return packing.pack(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("personal_data", mask_personal_data),
    ("mixture", mix_sources),
    ("packing", pack_sequences),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = f"{ensure_checkpoint_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs
