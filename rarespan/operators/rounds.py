"""The rounds inducer: a grammar by data-parallel pair replacement, in DataFrame form.

Rounds take turns. An even round pairs equal neighbours, from the start of each run; an odd one pairs a symbol of the left side with a following
symbol of the right side, where a hash of the round and the symbol tosses the side; so pairs of a round never overlap. Pairs that occur at least
twice are replaced by a new symbol named by the hash of its two parts, which needs no counter and no driver. Rules that are used once in the end are
dropped. One pass finds them all: a rule that is used once gives its parts to its only user, so no other rule's uses change. Without a number of rounds, they go on until no
pair repeats without overlap; then rules meet the same two constraints as those of the on-line inducer, though the grammar may differ from its.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rarespan.runtime import cut_in_loop

_KEYS = ["series_id", "w", "a"]


def _side(r: int, sym: str):
    return F.substring(F.md5(F.concat(F.lit(f"{r}:"), F.col(sym))), 1, 1).isin(*"01234567")


def repeating_pairs(seq: DataFrame) -> DataFrame:
    """(series_id, w, a, x, y): neighbours of (series_id, w, a, tok_ix, sym) that occur at least twice without overlap."""
    over = Window.partitionBy(*_KEYS).orderBy("tok_ix")
    t = seq.withColumn("y", F.lead("sym").over(over)).withColumn("before", F.lag("sym").over(over)).withColumn("rn", F.row_number().over(over))
    # of a run of n equal symbols, n div 2 pairs do not overlap
    t = t.withColumn("head", F.last(F.when(~F.col("sym").eqNullSafe(F.col("before")), F.col("rn")), ignorenulls=True).over(over.rowsBetween(Window.unboundedPreceding, 0)))
    pairs = t.where("y is not null and (y <> sym or (rn - head) % 2 = 0)")
    return pairs.groupBy(*_KEYS, F.col("sym").alias("x"), "y").count().where("count >= 2").drop("count")


def induce_rounds(tokens: DataFrame, rounds: int | None = None, most: int = 400) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(sequence, rules, spans) of run-collapsed tokens (series_id, w, a, tok_ix, word).

    sequence: series_id, w, a, tok_ix, sym, len - what is left at the top. rules: series_id, w, a, name, x, y, uses. spans: series_id, w, a, name, lo_tok,
    hi_tok - every instance of a rule that is used at least twice. Every round is one window over the remaining symbols, kept and cut off from its lineage.
    ``rounds`` None: until no pair repeats; more than ``most`` rounds are an error, never a grammar cut short. A pair is tried in a quarter of the odd rounds.
    """
    seq = tokens.select(*_KEYS, "tok_ix", F.col("word").alias("sym"), F.lit(1).cast("long").alias("len"))
    spans, rules = [], []
    over = Window.partitionBy(*_KEYS).orderBy("tok_ix")
    for r in range(most + 1 if rounds is None else rounds):
        if rounds is None and r % 8 == 0:
            if r:
                seq = cut_in_loop(seq)
            if repeating_pairs(seq).isEmpty():
                break
        if rounds is None and r == most:
            raise RuntimeError(f"pairs still repeat after {most} rounds")
        t = seq.withColumn("nxt", F.lead("sym").over(over)).withColumn("nlen", F.lead("len").over(over))
        if r % 2 == 0:
            t = t.withColumn("rn", F.row_number().over(over)).withColumn("head", F.when(~F.col("sym").eqNullSafe(F.lag("sym").over(over)), F.col("rn")))
            t = t.withColumn("head", F.last("head", ignorenulls=True).over(over.rowsBetween(Window.unboundedPreceding, 0)))
            cand = ((F.col("rn") - F.col("head")) % 2 == 0) & (F.col("nxt") == F.col("sym"))
        else:
            cand = (F.col("nxt") != F.col("sym")) & _side(r, "sym") & ~_side(r, "nxt")
        t = t.withColumn("cand", F.coalesce(cand, F.lit(False)))
        times = F.count("*").over(Window.partitionBy(*_KEYS, "sym", "nxt", "cand"))
        t = cut_in_loop(t.withColumn("rep", F.col("cand") & (times >= 2)).select(*_KEYS, "tok_ix", "sym", "len", "nxt", "nlen", "rep"))
        name = F.concat(F.lit("N"), F.md5(F.concat_ws("|", "sym", "nxt")))
        hit = t.where("rep")
        if hit.isEmpty():
            continue
        rules.append(hit.select(*_KEYS, name.alias("name"), F.col("sym").alias("x"), F.col("nxt").alias("y")).distinct())
        spans.append(hit.select(*_KEYS, name.alias("name"), F.col("tok_ix").alias("lo_tok"), (F.col("tok_ix") + F.col("len") + F.col("nlen") - 1).alias("hi_tok")))
        gone = F.coalesce(F.lag("rep").over(over), F.lit(False))
        t = t.withColumn("gone", gone).where("not gone")
        seq = t.select(*_KEYS, "tok_ix", F.when(F.col("rep"), name).otherwise(F.col("sym")).alias("sym"), (F.col("len") + F.when(F.col("rep"), F.col("nlen")).otherwise(0)).alias("len"))
    seq = cut_in_loop(seq)
    empty = seq.sparkSession.createDataFrame([], "series_id string, w int, a int, name string, x string, y string, lo_tok long, hi_tok long")
    all_rules, all_spans = empty.select(*_KEYS, "name", "x", "y"), empty.select(*_KEYS, "name", "lo_tok", "hi_tok")
    for a, b in zip(rules, spans, strict=True):
        all_rules, all_spans = all_rules.unionByName(a), all_spans.unionByName(b)
    all_rules = cut_in_loop(all_rules.distinct())
    parts = all_rules.select(*_KEYS, F.explode(F.array("x", "y")).alias("name")).unionByName(seq.select(*_KEYS, F.col("sym").alias("name")))
    used = parts.groupBy(*_KEYS, "name").agg(F.count("*").alias("uses"))
    all_rules = all_rules.join(used, [*_KEYS, "name"], "left").withColumn("uses", F.coalesce("uses", F.lit(0)))
    worth = all_rules.where("uses >= 2").select(*_KEYS, "name")
    return seq, all_rules, all_spans.join(worth, [*_KEYS, "name"], "left_semi")


def density_by_rounds(tokens: DataFrame, rounds: int | None = None) -> DataFrame:
    """(series_id, w, a, lo, hi, d) of tokens with pos and run_end: the rule density by the rounds inducer."""
    from rarespan.operators.density import density_from_spans

    tokens = cut_in_loop(tokens)
    _, _, spans = induce_rounds(tokens, rounds)
    at = tokens.select(*_KEYS, "tok_ix", "pos", "run_end")
    lo = at.select(*_KEYS, F.col("tok_ix").alias("lo_tok"), F.col("pos").alias("lo"))
    hi = at.select(*_KEYS, F.col("tok_ix").alias("hi_tok"), F.col("run_end").alias("hi"))
    placed = spans.join(lo, [*_KEYS, "lo_tok"]).join(hi, [*_KEYS, "hi_tok"]).withColumnRenamed("name", "rule")
    ends = tokens.groupBy("series_id").agg(F.max("run_end").alias("last_pos"))
    return density_from_spans(placed, ends, members=tokens)
