"""The thin queries over the given tables: each applies one operator to its whole table and returns the agreed columns."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rarespan.runtime import table


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from rarespan.llm.packing import pack

    pieces = pack(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
    return pieces.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")


def op2_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from rarespan.llm.simhash import near_duplicates

    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op3_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    from rarespan.llm.lm import score_documents, train

    docs = table(spark, sf_dir, "documents")
    held_out = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) == 1, F.lit(False))
    model, counts = train(docs.where(~held_out))
    scored = score_documents(docs, model, counts)
    return scored.select("doc_id", held_out.alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from rarespan.llm.quality import score_documents

    found = score_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return found.select("doc_id", "held_out", "score", "predicted")


def op5_merkle(spark: SparkSession, sf_dir: str) -> DataFrame:
    from rarespan.llm.merkle import edit_comparison

    return edit_comparison(table(spark, sf_dir, "documents"))


def op6_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    from rarespan.llm.chat import format_conversations

    return format_conversations(table(spark, sf_dir, "conversations"))


def op7_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    from rarespan.llm.topk import top_k

    return top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from rarespan.llm.mixing import mixture

    return mixture(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from rarespan.llm.toxicity import score_documents, train

    docs = table(spark, sf_dir, "documents")
    model = train(docs, table(spark, sf_dir, "labels"))
    held_out = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) == 0, F.lit(False))
    scored = score_documents(docs.select("doc_id", "text"), model)
    return scored.select("doc_id", held_out.alias("held_out"), F.col("toxicity").alias("score"), (F.col("toxicity") >= 0.5).cast("int").alias("predicted"))


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from rarespan.llm.pii import digest, find_pii

    return digest(find_pii(table(spark, sf_dir, "documents")))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_packing": op1_packing,
    "op2_simhash_dedup": op2_simhash_dedup,
    "op3_lm_scoring": op3_lm_scoring,
    "op4_quality": op4_quality,
    "op5_merkle": op5_merkle,
    "op6_chat_format": op6_chat_format,
    "op7_topk": op7_topk,
    "op8_mixing": op8_mixing,
    "op9_toxicity": op9_toxicity,
    "op10_pii": op10_pii,
}
_TOPK = """
with v as (
    select vec_id, list_transform(embedding, lambda x: cast(floor(64 * cast(x as double)) as bigint)) as x from embeddings
    where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0
), s as (
    select q.vec_id as query_id, c.vec_id, cast(list_sum(list_transform(list_zip(q.x, c.x), lambda p: p[1] * p[2])) as bigint) as score
    from v q join v c on q.vec_id % 20 = 0 and q.vec_id <> c.vec_id
), r as (select *, cast(row_number() over (partition by query_id order by score desc, vec_id) as int) as rank from s)
select query_id, rank, vec_id, score from r where rank <= 20
"""

ORACLE_SQL: dict[str, str] = {"op7_topk": _TOPK}
