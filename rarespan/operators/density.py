"""Grammars, rule instances and density curves of token tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rarespan.operators import kernel
from rarespan.operators.inducer import OnlineInducer, expand, induce, instances, token_depth
from rarespan.operators.layout import dealt_by, whole_groups
from rarespan.runtime import shuffle_partitions
from rarespan.schemas import DENSITY_RUN, GRAMMAR_SYMBOL, PACKED_RUNS, RULE_SPAN

_KEYS = ["series_id", "w", "a"]


def _ids(pdf: pd.DataFrame) -> dict:
    return {"series_id": pdf["series_id"].iloc[0], "w": int(pdf["w"].iloc[0]), "a": int(pdf["a"].iloc[0])}


def grammars(tokens: DataFrame, together: bool = False) -> DataFrame:
    """GRAMMAR_SYMBOL rows of each (series, w, a): every rule's body, symbol by symbol, in order. Tokens must be run-collapsed.

    ``together``: the tokens already come with each member's rows next to each other and in order; so do the result's then, and nothing is shuffled.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, starts in whole_groups(batches, _KEYS):
            word = rows.column("word").dictionary_encode(null_encoding="encode")
            ids, names = word.indices.to_numpy(zero_copy_only=False), len(word.dictionary)
            rule, size, sym, owner = [], [], [], []
            for lo, hi in zip(starts, starts[1:], strict=False):
                bodies = induce(ids[lo:hi].tolist())
                rule += bodies
                size += map(len, bodies.values())
                for body in bodies.values():
                    sym += body
                owner.append(sum(map(len, bodies.values())))
            sym, size = np.array(sym, np.int64), np.array(size, np.int64)
            is_rule = (sym & 1).astype(bool)
            most = int(sym[is_rule].max() >> 1) + 1 if is_rule.any() else 0
            known = pa.concat_arrays([word.dictionary.cast(pa.string()), pa.array([f"R{r}" for r in range(most)], pa.string())])
            text = known.take(pa.array(np.where(is_rule, names, 0) + (sym >> 1)))
            ix = np.arange(len(sym)) - np.repeat(np.cumsum(size) - size, size)
            own = rows.select(_KEYS).take(pa.array(np.repeat(np.array(starts[:-1], np.int64), owner)))
            columns = [*own.columns, pa.array(np.repeat(np.array(rule, np.int32), size)), pa.array(ix.astype(np.int32)), text, pa.array(is_rule)]
            yield pa.RecordBatch.from_arrays(columns, [*_KEYS, "rule", "ix", "sym", "is_rule"])

    rows = tokens.select(*_KEYS, "pos", "word")
    return (rows if together else dealt_by(rows, _KEYS, ["pos"])).mapInArrow(run, GRAMMAR_SYMBOL)


def rule_spans(tokens: DataFrame, coverage: str = "token_span", n: int = 1) -> DataFrame:
    """RULE_SPAN rows: every rule instance, nested ones included, as token numbers and as positions.

    ``tokens`` has pos and run_end. token_span ends an instance where its last token's run ends, window_span where the last token's window does.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("pos")
        bodies, _ = kernel.grammar_rows(pdf["word"])
        got = instances(bodies)
        pos, end = pdf["pos"].to_numpy(), pdf["run_end"].to_numpy()
        rows = [(r, a, b, pos[a], end[b] if coverage == "token_span" else min(pos[b] + n - 1, end[-1])) for r, a, b in got]
        return pd.DataFrame(rows, columns=["rule", "lo_tok", "hi_tok", "lo", "hi"]).assign(**_ids(pdf))[[*_KEYS, "rule", "lo_tok", "hi_tok", "lo", "hi"]]

    return tokens.select(*_KEYS, "pos", "run_end", "word").groupBy(*_KEYS).applyInPandas(run, RULE_SPAN)


def expand_grammar(rules: DataFrame, together: bool = False) -> DataFrame:
    """(series_id, w, a, tok_ix, word): the tokens a grammar stands for, each rule replaced by its body until none is left. ``together`` as in ``grammars``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, starts in whole_groups(batches, _KEYS):
            word = rows.column("sym").dictionary_encode(null_encoding="encode")
            is_rule = rows.column("is_rule").to_numpy(zero_copy_only=False)
            value = word.indices.to_numpy(zero_copy_only=False).astype(np.int64) << 1
            value[is_rule] = np.array([int(s[1:]) for s in rows.column("sym").filter(rows.column("is_rule")).to_pylist()], np.int64) << 1 | 1
            rule, value, out, size = rows.column("rule").to_numpy(), value.tolist(), [], []
            for lo, hi in zip(starts, starts[1:], strict=False):
                edge = [lo, *(np.flatnonzero(rule[lo + 1 : hi] != rule[lo : hi - 1]) + lo + 1).tolist(), hi]
                bodies = {int(rule[a]): value[a:b] for a, b in zip(edge, edge[1:], strict=False)}
                got = expand(bodies) if len(bodies) > 1 else [v >> 1 for v in bodies[0]]
                out += got
                size.append(len(got))
            size = np.array(size, np.int64)
            own = rows.select(_KEYS).take(pa.array(np.repeat(np.array(starts[:-1], np.int64), size)))
            ix = np.arange(len(out)) - np.repeat(np.cumsum(size) - size, size)
            yield pa.RecordBatch.from_arrays([*own.columns, pa.array(ix), word.dictionary.take(pa.array(out, pa.int64()))], [*_KEYS, "tok_ix", "word"])

    rows = rules.select(*_KEYS, "rule", "ix", "sym", "is_rule")
    return (rows if together else dealt_by(rows, _KEYS, ["rule", "ix"])).mapInArrow(run, "series_id string, w int, a int, tok_ix long, word string")


def digram_violations(rules: DataFrame) -> DataFrame:
    """Pairs of neighbours that occur more than once without overlap; empty for a proper grammar."""
    over = Window.partitionBy(*_KEYS, "rule").orderBy("ix")
    pairs = rules.withColumn("nxt", F.lead("sym").over(over)).where("nxt is not null")
    run = pairs.withColumn("prev", F.lag("sym").over(over))
    island = run.withColumn("_new", F.when((F.col("prev") == F.col("sym")) & (F.col("sym") == F.col("nxt")), 0).otherwise(1))
    island = island.withColumn("_isle", F.sum("_new").over(over))
    once = island.groupBy(*_KEYS, "rule", "_isle", "sym", "nxt").agg(F.ceil(F.count("*") / 2).alias("times"))
    return once.groupBy(*_KEYS, "sym", "nxt").agg(F.sum("times").alias("times")).where("times > 1")


def utility_violations(rules: DataFrame) -> DataFrame:
    """Rules other than the start rule that are used less than twice; empty for a proper grammar."""
    used = rules.where("is_rule").groupBy(*_KEYS, F.col("sym")).count()
    have = rules.where("rule > 0").select(*_KEYS, F.concat(F.lit("R"), F.col("rule")).alias("sym")).distinct()
    return have.join(used, [*_KEYS, "sym"], "left").where(F.coalesce("count", F.lit(0)) < 2)


def density_from_spans(spans: DataFrame, ends: DataFrame, count: str = "instances", members: DataFrame | None = None) -> DataFrame:
    """DENSITY_RUN rows from instance intervals: +1 / -1 events, running sums. ``ends`` has series_id and last_pos.

    ``members`` (series_id, w, a) names those that have a curve even without any span; else they are those of the spans. count="rules" counts a rule once however many of its instances cover a point.
    """
    if count == "rules":
        over = Window.partitionBy(*_KEYS, "rule").orderBy("lo", "hi")
        top = F.max("hi").over(over.rowsBetween(Window.unboundedPreceding, -1))
        isle = spans.withColumn("_new", F.when(F.col("lo") <= top + 1, 0).otherwise(1)).withColumn("_isle", F.sum("_new").over(over))
        spans = isle.groupBy(*_KEYS, "rule", "_isle").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    steps = spans.select(*_KEYS, F.inline(F.array(F.struct(F.col("lo").alias("pos"), F.lit(1).alias("s")), F.struct((F.col("hi") + 1).alias("pos"), F.lit(-1).alias("s")))))
    series = (spans if members is None else members).select(*_KEYS).distinct().join(ends, "series_id")
    steps = steps.unionByName(series.select(*_KEYS, F.lit(1).cast("long").alias("pos"), F.lit(0).alias("s")))
    net = steps.groupBy(*_KEYS, "pos").agg(F.sum("s").alias("s"))
    over = Window.partitionBy(*_KEYS).orderBy("pos")
    runs = net.withColumn("d", F.sum("s").over(over)).withColumn("_n", F.lead("pos").over(over))
    runs = runs.withColumn("_b", F.lag("d").over(over)).where("_b is null or d <> _b").withColumn("_n", F.lead("pos").over(over))
    return runs.join(ends, "series_id").select(*_KEYS, F.col("pos").alias("lo"), F.coalesce(F.col("_n") - 1, F.col("last_pos")).alias("hi"), "d").where("lo <= hi")


def density(tokens: DataFrame, ends: DataFrame, coverage: str = "token_span", n: int = 1, part: int | None = None) -> DataFrame:
    """DENSITY_RUN rows of each (series, w, a), induced and swept in one kernel call.

    ``part`` cuts the token sequence at multiples of so many positions and gives every part a grammar of its own, which bounds a task and
    spreads one long series over many; None: one grammar a series.
    """
    rows = tokens.select(*_KEYS, "pos", "word").join(ends, "series_id")
    rows = rows.withColumn("part", F.expr(f"(pos - 1) div {part}") if part else F.lit(0).cast("long"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("pos")
        k, last = int(pdf["part"].iloc[0]), int(pdf["last_pos"].iloc[0])
        lead, end = (k * part + 1, min((k + 1) * part, last)) if part else (1, last)
        lo, hi, d = kernel.density_runs(pdf["pos"].to_numpy(), pdf["word"].to_numpy(str), end, lead, coverage, n)
        return pd.DataFrame({"lo": lo, "hi": hi, "d": d}).assign(**_ids(pdf))[[*_KEYS, "lo", "hi", "d"]]

    dealt = rows.repartition(shuffle_partitions(tokens.sparkSession), *_KEYS, "part")  # small in bytes, long in work: not to be coalesced
    return dealt.groupBy(*_KEYS, "part").applyInPandas(run, DENSITY_RUN)


SEGMENT = 1 << 17


def packed_density(packed: DataFrame, ends: DataFrame, part: int | None = None, segment: int = SEGMENT) -> DataFrame:
    """PACKED_RUNS rows from PACKED_TOKENS: the same curves as ``density`` gives, one row for each ``segment`` positions of a member, with the sums for its spread.

    A task reads a member's chunks one after the other and keeps their offsets, the distinct words and the grammar, not the tokens.
    """

    def curve(offsets: list[tuple[int, np.ndarray]], bodies: dict[int, list[int]], lead: int, end: int) -> Iterator[tuple]:
        kind = np.int32 if end < 1 << 31 else np.int64
        depth = token_depth(bodies)
        bodies.clear()
        pos = np.concatenate([at.astype(kind) + kind(start) for start, at in offsets])
        offsets.clear()
        if pos[0] > lead:
            pos, depth = np.concatenate((np.array([lead], kind), pos)), np.concatenate((np.zeros(1, depth.dtype), depth))
        keep = np.ones(len(depth), bool)
        keep[1:] = depth[1:] != depth[:-1]
        pos, depth = pos[keep], depth[keep]
        for seg in range((lead - 1) // segment, (end - 1) // segment + 1):
            first, last = max(lead, seg * segment + 1), min(end, (seg + 1) * segment)
            i, j = np.searchsorted(pos, [first, last], "right")
            at, d = np.maximum(pos[i - 1 : j], first).astype(np.int64), depth[i - 1 : j].astype(np.int64)
            size = np.append(at[1:], last + 1) - at
            yield seg, first, last, (at - first).astype(np.int32).tobytes(), d.astype(np.int32).tobytes(), int((size * d).sum()), int((size * d * d).sum()), int(d.max())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, offsets, known, grammar, previous, last_pos = None, [], {}, OnlineInducer(), -1, 0

        def whole() -> Iterator[pa.RecordBatch]:
            nonlocal known, grammar
            if not offsets:
                return
            series, w, a, k = key
            bodies, known, grammar = grammar.bodies(), {}, None
            lead, end = (k * part + 1, min((k + 1) * part, last_pos)) if part else (1, last_pos)
            for row in curve(offsets, bodies, lead, end):
                yield pa.RecordBatch.from_pylist([dict(zip(names, (series, w, a, *row), strict=True))], schema)

        for batch in batches:
            for i in range(batch.num_rows):
                series, w, a, k, start, at, word, end = (c[i].as_py() for c in batch.columns)
                if (series, w, a, k) != key:
                    yield from whole()
                    key, offsets, known, grammar, previous, last_pos = (series, w, a, k), [], {}, OnlineInducer(), -1, end
                at, ids = np.frombuffer(at, np.int32), [known.setdefault(t, len(known)) for t in np.frombuffer(word, f"S{w}").tolist()]
                if ids[0] == previous:  # a run of equal words goes on from the chunk before
                    at, ids = at[1:], ids[1:]
                if ids:
                    offsets.append((start, at))
                    grammar.extend(ids)
                    previous = ids[-1]
        yield from whole()

    names = [c.split()[0] for c in PACKED_RUNS.split(", ")]
    kinds = {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
    schema = pa.schema([(c.split()[0], kinds[c.split()[1]]) for c in PACKED_RUNS.split(", ")])
    rows = packed.join(F.broadcast(ends), "series_id").select(*_KEYS, "part", "start", "at", "word", "last_pos")
    return dealt_by(rows, [*_KEYS, "part"], ["start"]).mapInArrow(run, PACKED_RUNS)


def uncovered(runs: DataFrame) -> DataFrame:
    """Maximal intervals that no rule covers: the incompressible stretches."""
    return runs.where("d = 0").select(*_KEYS, "lo", "hi")
