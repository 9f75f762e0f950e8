"""Document fingerprints: a Merkle tree over sections, paragraphs and phrases, with DataFrame functions only.

A text is cut at blank lines into sections, at line breaks into paragraphs and after runs of punctuation into phrases
(or after ``LEAF`` characters without any); nothing of it is left out. A phrase's hash is a leaf; a paragraph's node
hashes its leaves in order, a section's node its paragraphs, the root its sections. Equal roots mean equal texts; where
two trees differ, descending into the differing branches locates the edit.

The fingerprint is the root followed by the ``NODES`` smallest of the distinct hashes (32 bits) of all the tree's nodes: phrases, paragraphs, sections and the root.
It is bounded for any length of text, and for trees of fewer nodes it is all of them. The likeness of two documents is told from their fingerprints alone:
twice the shared nodes over the nodes of both, as far as both fingerprints reach. Equal sections bring all that lies below them; a phrase that moved to
another place keeps its own node but changes those above.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rarespan.runtime import shuffle_partitions

LEAF = 200
NODES = 128  # of a fingerprint; likeness of larger trees is off by about 1 / sqrt(NODES) at most
_MARKS = r".,!?;:|&%$#*…。"
_PHRASE = rf"[^{_MARKS}]{{0,{LEAF}}}[{_MARKS}]+|[^{_MARKS}]{{1,{LEAF}}}"
_SECTION = r"\n[ \t]*\n"


def tree(text: Column) -> Column:
    """array<sections> of array<paragraphs> of array<leaf hashes>; a null text is an empty one."""
    paragraphs = lambda s: F.transform(F.split(s, "\n", -1), phrases)
    phrases = lambda p: F.transform(F.regexp_extract_all(p, F.lit(_PHRASE), F.lit(0)), lambda x: F.xxhash64(x))
    return F.transform(F.split(F.coalesce(text, F.lit("")), _SECTION, -1), paragraphs)


def paragraph_nodes(text_tree: Column) -> Column:
    """array<sections> of the paragraphs' nodes, each a hash over its leaves in order."""
    return F.transform(text_tree, lambda s: F.transform(s, lambda p: F.md5(F.array_join(p.cast("array<string>"), ","))))


def section_nodes(paragraphs: Column) -> Column:
    return F.transform(paragraphs, lambda s: F.md5(F.array_join(s, ",")))


def root(sections: Column, text: Column) -> Column:
    """Hash over the section nodes; blank lines differ in their own white space, so the text's length and hash take part too."""
    t = F.coalesce(text, F.lit(""))
    return F.md5(F.concat_ws(",", F.array_join(sections, ","), F.char_length(t).cast("string"), F.xxhash64(t).cast("string")))


def least_nodes(text_tree: Column, paragraphs: Column, sections: Column, top: Column, most: int = NODES) -> Column:
    """The ``most`` smallest distinct node hashes of all levels, ascending, 32 bits of each."""
    inner = F.transform(F.concat(F.flatten(paragraphs), sections, F.array(top)), lambda h: F.xxhash64(h))
    every = F.transform(F.concat(F.flatten(F.flatten(text_tree)), inner), lambda h: h.bitwiseAND(F.lit(0xFFFFFFFF)).cast("long"))
    return F.slice(F.sort_array(F.array_distinct(every)), 1, most)


def printed(node: Column, nodes: Column) -> Column:
    return F.concat(node, F.lit(":"), F.array_join(F.transform(nodes, lambda h: F.lower(F.lpad(F.hex(h), 8, "0"))), ""))


def likeness(a: Column, b: Column, most: int = NODES) -> Column:
    """Twice the shared nodes over those of both, among the hashes up to where both fingerprints reach; 1 only for equal node sets."""
    reach = lambda x: F.when(F.size(x) >= most, F.element_at(x, -1)).otherwise(F.lit(1 << 32))
    end = F.least(reach(a), reach(b))
    within = F.size(F.filter(a, lambda h: h <= end)) + F.size(F.filter(b, lambda h: h <= end))
    return 2.0 * F.size(F.array_intersect(a, b)) / within


def with_nodes(docs: DataFrame, text: Column) -> DataFrame:
    """The rows with merkle_tree, merkle_paragraphs, merkle_sections, merkle_root and merkle_nodes added, level by level."""
    docs = docs.withColumn("merkle_tree", tree(text)).withColumn("merkle_paragraphs", paragraph_nodes(F.col("merkle_tree")))
    docs = docs.withColumn("merkle_sections", section_nodes(F.col("merkle_paragraphs"))).withColumn("merkle_root", root(F.col("merkle_sections"), text))
    return docs.withColumn("merkle_nodes", least_nodes(F.col("merkle_tree"), F.col("merkle_paragraphs"), F.col("merkle_sections"), F.col("merkle_root")))


def fingerprints(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The documents with the columns of ``with_nodes`` and fingerprint added.

    Columns of these names are replaced. Null and empty texts share one fingerprint. Every row gets its own, repeated or not.
    """
    return with_nodes(docs, F.col(text_col)).withColumn("fingerprint", printed(F.col("merkle_root"), F.col("merkle_nodes")))


def differing_branches(a: Column, b: Column) -> Column:
    """Places (section, paragraph; from 0) at which two trees differ, branches only one of them has included."""
    empty = F.array().cast("array<array<bigint>>")

    def section(i: Column) -> Column:
        x, y = F.coalesce(F.get(a, i), empty), F.coalesce(F.get(b, i), empty)
        spots = F.sequence(F.lit(0), F.greatest(F.size(x), F.size(y), F.lit(1)) - 1)
        return F.transform(F.filter(spots, lambda j: ~F.get(x, j).eqNullSafe(F.get(y, j))), lambda j: F.struct(i.alias("section"), j.alias("paragraph")))

    return F.flatten(F.transform(F.sequence(F.lit(0), F.greatest(F.size(a), F.size(b)) - 1), section))


def _bucket(id_col: Column, bounds: list[int]) -> Column:
    """How many of the ascending bounds lie below the id, by a search in two levels."""
    if not bounds:
        return F.lit(0)
    width = math.isqrt(len(bounds)) + 1
    rows = [bounds[i : i + width] for i in range(0, len(bounds), width)]
    below = lambda values, x: F.size(F.filter(values, lambda b: b < x))
    longs = lambda values: F.array(*map(F.lit, values)).cast("array<bigint>")
    head = below(longs([r[-1] for r in rows]), id_col)
    inner = F.element_at(F.array(*map(longs, [*rows, []])), head + 1)
    return F.least(head * width, F.lit(len(bounds))) + below(inner, id_col)


def with_next(docs: DataFrame, columns: dict[str, str], id_col: str = "doc_id", tie_col: str = "text", buckets: int | None = None) -> DataFrame:
    """Adds columns of the next row by descending id (nulls last, ties by ``tie_col``); the first row follows the last.

    Rows are dealt to ranges of ids whose bounds are ids that occur; the rows at a bound are sent to the neighbouring range too, so
    every range finds the successor of its last row and no window spans the table. ``columns`` maps new names to existing ones.
    """
    spark: SparkSession = docs.sparkSession
    n = min(4096, buckets or 4 * shuffle_partitions(spark))
    wanted = [i / n for i in range(1, n)] + [1.0]
    found = docs.agg(F.percentile_approx(id_col, wanted, 10 * n), F.max(id_col)).first()
    bounds = sorted(set(found[0] or []))
    top = found[1]
    bounds = [b for b in bounds if b != top]
    key = F.coalesce(_bucket(F.col(id_col), bounds), F.lit(0))
    guest = F.when(F.col(id_col) == F.lit(top), F.lit(0)).when(F.array_contains(F.array(*map(F.lit, bounds)).cast("array<bigint>"), F.col(id_col)), key + 1)
    home = F.struct(key.alias("bucket"), F.lit(0).alias("guest"))
    away = F.struct(guest.alias("bucket"), F.lit(1).alias("guest"))
    dealt = docs.select("*", F.inline(F.when(guest.isNotNull(), F.array(home, away)).otherwise(F.array(home))))
    order = Window.partitionBy("bucket").orderBy("guest", F.col(id_col).desc_nulls_last(), tie_col)
    for new, old in columns.items():
        head = F.first(old).over(order.rowsBetween(Window.unboundedPreceding, 0))
        follows = F.lead(F.struct(old)).over(order)
        dealt = dealt.withColumn(new, F.when(follows.isNull(), head).otherwise(follows[old]))
    return dealt.where("guest = 0").drop("bucket", "guest")


def edit_comparison(docs: DataFrame) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next for each document.

    The edited text has its last floor(n_chars / 2) code points replaced by the first as many of the next document. A lone document
    follows itself. Null texts count as empty; an empty table gives no rows; other columns are ignored.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    base = with_nodes(docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text")), F.col("text"))
    base = base.select("doc_id", "text", F.col("merkle_root").alias("root"), F.col("merkle_nodes").alias("nodes"))
    both = with_next(base, {"next_text": "text", "next_nodes": "nodes"}).withColumn("n_chars", F.char_length("text").cast("long"))
    half = F.expr("cast(n_chars div 2 as int)")
    n = F.col("n_chars").cast("int")
    both = both.withColumn("edited", F.concat(F.substring("text", F.lit(1), n - half), F.substring("next_text", F.lit(1), half)))
    both = with_nodes(both, F.col("edited"))
    return both.select(
        "doc_id",
        "n_chars",
        F.sha2("edited", 256).alias("edited_sha256"),
        printed(F.col("root"), F.col("nodes")).alias("fingerprint"),
        printed(F.col("merkle_root"), F.col("merkle_nodes")).alias("edited_fingerprint"),
        likeness(F.col("nodes"), F.col("merkle_nodes")).alias("near_edited"),
        likeness(F.col("nodes"), F.col("next_nodes")).alias("near_next"),
    )
