"""Detectors: one (w, a) run, and the committee; and the single-run baselines."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rarespan.operators import candidates as cand
from rarespan.operators import committee as com
from rarespan.operators import kernel
from rarespan.operators.density import density, packed_density
from rarespan.operators.layout import CORE, dealt_by, whole_groups, with_chunks
from rarespan.runtime import cut, shuffle_partitions
from rarespan.schemas import CANDIDATE, PACKED_TOKENS, TOKEN


@dataclass(frozen=True)
class Preset:
    n_members: int = 50
    w_max: int = 10
    a_max: int = 10
    tau: float = 0.4
    k: int = 3
    seed: int = 42


DEFAULT = Preset()
RECOMMENDED = Preset(n_members=25, tau=0.2)


def series_ends(df: DataFrame) -> DataFrame:
    return df.groupBy("series_id").agg(F.max("pos").alias("last_pos"))


def tokens_by_kernel(df: DataFrame, n: int, params: list[tuple[int, int]] | None = None, core: int = CORE, chosen: DataFrame | None = None) -> DataFrame:
    """TOKEN rows of a series table (series_id, pos, x), runs collapsed within each chunk.

    ``params`` holds the resolutions for all series; ``chosen`` (series_id, w, a) gives each series its own instead. Chunks carry n - 1 values of
    their neighbour, so every window is seen exactly once and no word depends on the chunking.
    """
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, found in _words_of_chunks(batches, n, params, core):
            if not found:
                continue
            size = np.array([len(f[4]) for f in found], np.int64)
            names = rows.column("series_id").take(pa.array(np.repeat(np.array([f[0] for f in found], np.int64), size)))
            w, a = (np.repeat(np.array([f[i] for f in found], np.int32), size) for i in (1, 2))
            pos = np.concatenate([f[4] + f[3] for f in found])
            edge = np.concatenate(([0], np.cumsum(w, dtype=np.int64)))
            text = pa.LargeStringArray.from_buffers(len(pos), pa.py_buffer(edge), pa.py_buffer(b"".join(f[5].tobytes() for f in found))).cast(pa.string())
            yield pa.RecordBatch.from_arrays([names, pa.array(w), pa.array(a), pa.array(pos), text], ["series_id", "w", "a", "pos", "word"])

    return _dealt_chunks(df, n, core, chosen).mapInArrow(run, TOKEN)


def _dealt_chunks(df: DataFrame, n: int, core: int, chosen: DataFrame | None) -> DataFrame:
    rows = df.select("series_id", "pos", "x")
    if chosen is not None:
        rows = rows.join(chosen, "series_id")
    return dealt_by(with_chunks(rows, n, core), ["series_id", "chunk"], ["pos"])


def _words_of_chunks(batches: Iterator[pa.RecordBatch], n: int, params: list[tuple[int, int]] | None, core: int) -> Iterator[tuple[pa.RecordBatch, list[tuple]]]:
    """(rows, [(row of the chunk's first value, w, a, position of its first window, offsets, words)]) of whole chunks."""
    for rows, starts in whole_groups(batches, ["series_id", "chunk"]):
        x, chunk, found = rows.column("x").to_numpy(zero_copy_only=False), rows.column("chunk").to_numpy(), []
        for lo, hi in zip(starts, starts[1:], strict=False):
            own = params or [(rows.column("w")[lo].as_py(), rows.column("a")[lo].as_py())]
            found += [(lo, w, a, int(chunk[lo]) * core + 1, at, words) for w, a, at, words in kernel.chunk_tokens(x[lo:hi], n, core, own, max(a for _, a in own))]
        yield rows, found


def packed_tokens(df: DataFrame, n: int, params: list[tuple[int, int]], core: int = CORE, part: int | None = None) -> DataFrame:
    """PACKED_TOKENS rows: what ``tokens_by_kernel`` gives, one row for each member and chunk (and part), so that a long series' many tokens are few rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, found in _words_of_chunks(batches, n, params, core):
            out = []
            for lo, w, a, start, at, words in found:
                parts = (at + (start - 1)) // part if part else np.zeros(len(at), np.int64)
                edge = [0, *(np.flatnonzero(parts[1:] != parts[:-1]) + 1).tolist(), len(at)]
                out += [(lo, w, a, int(parts[i]), start, at[i:j].astype(np.int32).tobytes(), words[i:j].tobytes()) for i, j in zip(edge, edge[1:], strict=False)]
            if out:
                columns = list(zip(*out, strict=True))
                kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.binary()]
                names = rows.column("series_id").take(pa.array(columns[0], pa.int64()))
                yield pa.RecordBatch.from_arrays([names, *(pa.array(c, k) for c, k in zip(columns[1:], kinds, strict=True))], [c.split()[0] for c in PACKED_TOKENS.split(", ")])

    return _dealt_chunks(df, n, core, None).mapInArrow(run, PACKED_TOKENS)


def member_runs(df: DataFrame, n: int, params: list[tuple[int, int]] | None = None, core: int = CORE, part: int | None = None, chosen: DataFrame | None = None) -> DataFrame:
    """DENSITY_RUN rows of each member, computed once and kept."""
    return cut(density(tokens_by_kernel(df, n, params, core, chosen), series_ends(df), part=part))


def detect_single(df: DataFrame, n: int, w: int, a: int, k: int = 3, part: int | None = None) -> DataFrame:
    """CANDIDATE rows of one resolution's density curve. With ``part``, for series of any length, no task holds a whole series."""
    runs = density(tokens_by_kernel(df, n, [(w, a)]), series_ends(df), part=part)
    pick = cand.long_window_candidates if part else cand.window_candidates
    return pick(runs.withColumn("de", F.col("d").cast("double")), n, k)


def committee_curve(runs: DataFrame, tau: float = 0.4, how: str = "median", norm: str = "max") -> DataFrame:
    """CURVE_RUN rows from members' density runs: flat curves dropped, the others scaled and combined."""
    kept = com.keep_by_spread(com.curve_stats(runs), tau)
    return com.combine(com.scaled(runs, kept, norm), how)


SHORT = 16_384


def by_series(df: DataFrame, one: Callable[[str, np.ndarray], list[tuple]], schema: str) -> DataFrame:
    """Rows of ``one`` (name, values in order) for each series. For short series, many of them in each task; rows come sorted, and a task holds one series at a time."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        name, held = None, []

        def whole() -> list[tuple]:
            return one(name, np.concatenate(held)) if held else []

        for pdf in frames:
            names, x = pdf["series_id"].to_numpy(object), pdf["x"].to_numpy(np.int64)
            edge = np.flatnonzero(np.concatenate(([True], names[1:] != names[:-1]))).tolist() if len(x) else []
            rows = []
            for lo, hi in zip(edge, [*edge[1:], len(x)], strict=True):
                if held and names[lo] != name:
                    rows += whole()
                    held = []
                name = names[lo]
                held.append(x[lo:hi])
            yield pd.DataFrame(rows, columns=columns)
        yield pd.DataFrame(whole(), columns=columns)

    columns = [c.split()[0] for c in schema.split(", ")]
    dealt = df.select("series_id", "pos", "x").repartition(4 * shuffle_partitions(df.sparkSession), "series_id")
    return dealt.sortWithinPartitions("series_id", "pos").select("series_id", "x").mapInPandas(run, schema)


def _short_committee(df: DataFrame, n: int, params: list[tuple[int, int]], tau: float, k: int) -> DataFrame:
    """Candidates of short series, one kernel call each."""

    def one(name: str, x: np.ndarray) -> list[tuple]:
        return [(name, r + 1, i + 1, i + n, i + 1, v) for r, (i, v) in enumerate(kernel.committee_one(x, n, params, tau, k))]

    return by_series(df, one, CANDIDATE)


def detect_committee(
    df: DataFrame,
    n: int,
    n_members: int = 50,
    w_max: int = 10,
    a_max: int = 10,
    tau: float = 0.4,
    k: int = 3,
    seed: int = 42,
    core: int = CORE,
    part: int | None = None,
    short: int = SHORT,
) -> DataFrame:
    """CANDIDATE rows of the committee's curve.

    Series of up to ``short`` points go through all stages in one kernel call, one after the other in a task; longer ones are
    cut into chunks, and their members are induced by separate tasks. Both give the same candidates.
    """
    params = com.draw_params(n_members, w_max, a_max, seed, w_cap=n)
    df = cut(df.select("series_id", "pos", "x"))
    long = cut(series_ends(df).where(F.col("last_pos") > short).select("series_id"))
    if long.isEmpty():
        return _short_committee(df, n, params, tau, k)
    # each has more than ``short`` points, so they are few; joined by a shuffle, all points of one would go to one task
    few, high = _short_committee(df.join(F.broadcast(long), "series_id", "left_anti"), n, params, tau, k), df.join(F.broadcast(long), "series_id", "left_semi")
    return few.unionByName(cand.long_window_candidates(long_committee_curve(high, n, params, tau, core, part), n, k))


def long_committee_curve(df: DataFrame, n: int, params: list[tuple[int, int]], tau: float = 0.4, core: int = CORE, part: int | None = None) -> DataFrame:
    """``committee_curve`` of ``member_runs``, with tokens, members' curves and the result packed by the segment between the steps, not row by row."""
    runs = cut(packed_density(packed_tokens(df, n, params, core, part), series_ends(df), part))
    return com.unpacked(cut(com.combine_packed(runs, com.keep_by_spread(com.packed_stats(runs), tau))))


def random_choice(df: DataFrame, w_max: int = 10, a_max: int = 10, seed: int = 42) -> DataFrame:
    """(series_id, w, a): one pair a series, by a hash of its name."""
    n = (w_max - 1) * (a_max - 1)
    pick = F.pmod(F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), "series_id")), 1, 8), 16, 10).cast("long"), F.lit(n))
    one = df.select("series_id").distinct().withColumn("_i", pick)
    return one.select("series_id", (F.expr(f"_i div {a_max - 1}") + 2).cast("int").alias("w"), (F.col("_i") % (a_max - 1) + 2).cast("int").alias("a"))


def _by_choice(df: DataFrame, n: int, chosen: DataFrame, k: int) -> DataFrame:
    runs = density(tokens_by_kernel(df, n, chosen=chosen), series_ends(df))
    return cand.window_candidates(runs.withColumn("de", F.col("d").cast("double")), n, k)


def baseline_random(df: DataFrame, n: int, w_max: int = 10, a_max: int = 10, seed: int = 42, k: int = 3) -> DataFrame:
    """One random resolution a series."""
    return _by_choice(df, n, random_choice(df, w_max, a_max, seed), k)


def baseline_fixed(df: DataFrame, n: int, w: int = 4, a: int = 4, k: int = 3) -> DataFrame:
    """One resolution for all series."""
    return detect_single(df, n, w, a, k)


def objectives(x: np.ndarray, n: int, pairs: list[tuple[int, int]], a_max: int) -> list[tuple[int, int, float, float, float]]:
    """(w, a, mdl, coverage, reconstruction) of each pair over one series' head."""
    from statistics import NormalDist

    from rarespan.functions.breakpoints import cuts

    if len(x) < n:
        return []
    x, p1, t1, v = kernel.window_sums(x, n)
    root = np.sqrt(np.maximum(v, 0).astype(float) * (n / (n - 1)))
    out = []
    for w, a, _, words in kernel.chunk_tokens(x, n, len(x), pairs, a_max):
        bodies, _ = kernel.grammar_rows(words.astype(str))
        size, m = sum(map(len, bodies.values())) + len(bodies), len(words)
        covered = kernel.token_depth(bodies) > 0
        coef = kernel.coefficients(x, n, w, p1, root, t1)
        centre = np.array([NormalDist().inv_cdf((i + 0.5) / a) for i in range(a)])
        error = float(((coef - centre[np.searchsorted(np.array(cuts(a)), coef, side="right")]) ** 2).mean())
        out.append((w, a, size / m, float(covered.mean()), error * size))
    return out


def selection_objectives(df: DataFrame, n: int, train_frac: float = 0.1, w_max: int = 10, a_max: int = 10) -> DataFrame:
    """(series_id, w, a, mdl, coverage, reconstruction) over the head of each series, for every pair of the grid.

    mdl: symbols of the grammar plus its rules, per token. coverage: share of tokens under a rule. reconstruction: mean
    squared difference between windows' segment means and their letters' centres, times the grammar's size.
    """
    head = df.join(series_ends(df), "series_id").where((F.col("pos") <= F.greatest(F.lit(2 * n), F.floor(F.col("last_pos") * train_frac)))).drop("last_pos")
    pairs = [(w, a) for w in range(2, min(w_max, n) + 1) for a in range(2, a_max + 1)]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        got = objectives(pdf.sort_values("pos")["x"].to_numpy(np.int64), n, pairs, a_max)
        return pd.DataFrame([(pdf["series_id"].iloc[0], *g) for g in got], columns=["series_id", "w", "a", "mdl", "coverage", "reconstruction"])

    return head.select("series_id", "pos", "x").groupBy("series_id").applyInPandas(run, "series_id string, w int, a int, mdl double, coverage double, reconstruction double")


def selected_choice(grid: DataFrame, objective: str = "mdl") -> DataFrame:
    """(series_id, w, a) of smallest objective; with mdl, those that cover half the tokens come first."""
    first = (F.col("coverage") < 0.5).cast("int") if objective == "mdl" else F.lit(0)
    best = grid.groupBy("series_id").agg(F.min(F.struct(first.alias("f"), F.col(objective).alias("o"), "w", "a")).alias("m"))
    return best.select("series_id", "m.w", "m.a")


def baseline_selected(df: DataFrame, n: int, train_frac: float = 0.1, objective: str = "mdl", w_max: int = 10, a_max: int = 10, k: int = 3) -> DataFrame:
    """The resolution of smallest objective on the head of each series; with mdl, those that cover half the tokens come first."""
    return _by_choice(df, n, selected_choice(selection_objectives(df, n, train_frac, w_max, a_max), objective), k)
