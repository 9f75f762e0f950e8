"""The experiments on planted series, as tables of results. All choices are seeded, so runs agree."""

from __future__ import annotations

import math
from decimal import Decimal
from functools import reduce
from hashlib import md5

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rarespan.operators import committee as com
from rarespan.operators import discord, kernel, measures
from rarespan.plans import detect
from rarespan.plans.plant import planted
from rarespan.runtime import cut, shuffle_partitions

N = 64
LENGTHS = (82, 132, 150, 150, 275, 1024)  # of the instances of each dataset
LABELS = tuple(range(6))
COPIES = 25

_KEPT: dict[tuple, tuple] = {}


def once(make):
    """A wrapper that computes a kept (checkpointed) result once a session and arguments; several tables report on the same runs."""

    def run(spark: SparkSession, d: str, **kw):
        key = (spark.sparkContext.applicationId, make.__name__, d, *sorted(kw.items()))
        if key not in _KEPT:
            _KEPT[key] = make(spark, d, **kw)
        return _KEPT[key]

    return run


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


@once
def data(spark: SparkSession, d: str, labels: tuple[int, ...] = LABELS, copies: int = COPIES, lengths: tuple[int, ...] | None = None, **kw) -> tuple[DataFrame, DataFrame]:
    """(series, truth) of ``copies`` planted series of each label, with instances of 64 values or of each label's own length."""
    made = [planted(spark, d, c, copies, length=lengths[i] if lengths else N, **kw) for i, c in enumerate(labels)]
    kept = [(cut(s), cut(t)) for s, t in made]  # one by one: a plan of all of them at once takes the driver's memory
    return _union([s for s, _ in kept]), _union([t for _, t in kept])


def evaluate(cands: DataFrame, truth: DataFrame, method: str) -> DataFrame:
    """Scored candidates: dataset, series_id, method, rank, loc, score."""
    return measures.score(cands, truth).select("dataset", "series_id", F.lit(method).alias("method"), "rank", "loc", "score")


def all_methods(series: DataFrame, truth: DataFrame, n: int = N, members: int = 50, w_max: int = 10, a_max: int = 10, tau: float = 0.4, seed: int = 42) -> DataFrame:
    """Scored candidates of the committee and the four baselines."""
    s = series.select("series_id", "pos", "x")
    runs = {
        "committee": detect.detect_committee(s, n, members, w_max, a_max, tau, seed=seed),
        "single/random": detect.baseline_random(s, n, w_max, a_max, seed),
        "single/fixed": detect.baseline_fixed(s, n),
        "single/selected": detect.baseline_selected(s, n, w_max=w_max, a_max=a_max),
        "discord": discord.discord_profile(s, n, tiles=4),
    }
    return cut(_union([evaluate(c, truth, m) for m, c in runs.items()]))


def methods_one(name: str, x: np.ndarray, n: int, members: int = 50, w_max: int = 10, a_max: int = 10, tau: float = 0.4, seed: int = 42, train: float = 0.1) -> list[tuple[str, str, int, int]]:
    """(method, series_id, rank, loc): what ``all_methods`` gives for one short series, in one call, so that many datasets need no jobs of their own."""
    grid_pairs = [(w, a) for w in range(2, min(w_max, n) + 1) for a in range(2, a_max + 1)]
    i = int(md5(f"{seed}:{name}".encode()).hexdigest()[:8], 16) % ((w_max - 1) * (a_max - 1))
    picked = {"single/random": (i // (a_max - 1) + 2, i % (a_max - 1) + 2), "single/fixed": (4, 4)}
    head = detect.objectives(x[: max(2 * n, math.floor(len(x) * train))], n, grid_pairs, a_max)
    if head:
        picked["single/selected"] = min((cover < 0.5, mdl, w, a) for w, a, mdl, cover, _ in head)[2:]
    curves = {(w, a): np.repeat(d.astype(float), hi - lo + 1) for w, a, lo, hi, d in kernel.pair_curves(x, n, sorted(set(picked.values())))}
    found = {m: kernel.window_candidates(curves[p], n) for m, p in picked.items() if p in curves}
    found["committee"] = kernel.committee_one(x, n, com.draw_params(members, w_max, a_max, seed, w_cap=n), tau, 3)
    rows = [(m, name, r + 1, at + 1) for m, got in found.items() for r, (at, _) in enumerate(got)]
    return rows + [("discord", name, r + 1, at) for r, (at, _) in enumerate(discord.one_series(x, n))]


@once
def compared(spark: SparkSession, d: str, labels: tuple[int, ...] = LABELS, copies: int = COPIES, lengths: tuple[int, ...] = LENGTHS) -> DataFrame:
    """Scored candidates of all five methods on every dataset, each with windows of its instances' length."""
    labels = labels[: len(lengths)]
    series, truth = data(spark, d, labels=labels, copies=copies, lengths=lengths)
    of = dict(zip(labels, lengths, strict=False))
    found = detect.by_series(series, lambda name, x: methods_one(name, x, of[int(name.split("-")[0])]), "method string, series_id string, rank int, loc long")
    return cut(measures.score(found, truth).select("dataset", "series_id", "method", "rank", "loc", "score"))


def accuracy(spark: SparkSession, d: str, **kw) -> DataFrame:
    """dataset, method, avg_score, hit_rate for the committee and the baselines."""
    scored = compared(spark, d, **kw)
    return measures.average_score(measures.best_of(scored)).join(measures.hit_rate(scored), ["dataset", "method"])


def duels(spark: SparkSession, d: str, **kw) -> DataFrame:
    """Wins, ties, losses and one-sided misses of the committee against each baseline."""
    best = measures.best_of(compared(spark, d, **kw))
    return measures.win_tie_loss(best).join(measures.one_sided_misses(best), ["dataset", "method"])


def scatter(spark: SparkSession, d: str, **kw) -> DataFrame:
    """Score of the committee beside each baseline's, series by series."""
    return measures.paired(measures.best_of(compared(spark, d, **kw)))


def grid(df: DataFrame, n: int, runs: list[tuple[list[tuple[int, int]], float]], k: int = 3, singles: bool = False) -> DataFrame:
    """(series_id, run, w, a, rank, lo, hi, loc, value): candidates of every committee (run 0 ..; w and a 0) and, if asked, of every single pair (run -1).

    For many short series: a series is one kernel call, which makes the curve of a pair once for all committees that have it.
    """
    import pandas as pd

    names = ["series_id", "run", "w", "a", "rank", "lo", "hi", "loc", "value"]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        name = pdf["series_id"].iloc[0]
        many, each = kernel.committee_grid(pdf.sort_values("pos")["x"].to_numpy(), n, runs, k, singles)
        found = [(i, 0, 0, got) for i, got in enumerate(many)] + [(-1, w, a, got) for (w, a), got in each.items()]
        rows = [(name, i, w, a, r + 1, at + 1, at + n, at + 1, v) for i, w, a, got in found for r, (at, v) in enumerate(got)]
        return pd.DataFrame(rows, columns=names)

    dealt = df.select("series_id", "pos", "x").repartition(max(8, shuffle_partitions(df.sparkSession)), "series_id")
    return dealt.groupBy("series_id").applyInPandas(run, "series_id string, run int, w int, a int, rank int, lo long, hi long, loc long, value double")


WIDEST = ((5, 5), (10, 10), (15, 15), (20, 20), (5, 10), (15, 10), (20, 10), (10, 5), (10, 15), (10, 20))


@once
def range_scores(spark: SparkSession, d: str, pairs: tuple[tuple[int, int], ...] = WIDEST, **kw) -> DataFrame:
    """Scored candidates (with w_max, a_max) of the committee and the three single-run policies for each range of resolutions."""
    series, truth = data(spark, d, **kw)
    s = series.select("series_id", "pos", "x")
    whole = [(w, a) for w in range(2, max(w for w, _ in pairs) + 1) for a in range(2, max(a for _, a in pairs) + 1)]
    runs = [(com.draw_params(50, w, a, w_cap=N), 0.4) for w, a in pairs]
    found = cut(grid(s, N, [*runs, (whole, 1.0)], singles=True))
    ranges = cut(detect.selection_objectives(s, N, w_max=max(w for w, _ in pairs), a_max=max(a for _, a in pairs)))
    alone = found.where("run = -1").drop("run")
    out = []
    for i, (w, a) in enumerate(pairs):
        chosen = {
            "single/random": detect.random_choice(s, w, a),
            "single/fixed": s.select("series_id").distinct().withColumn("w", F.lit(4)).withColumn("a", F.lit(4)),
            "single/selected": detect.selected_choice(ranges.where((F.col("w") <= w) & (F.col("a") <= a))),
        }
        got = [evaluate(found.where(F.col("run") == i), truth, "committee")]
        got += [evaluate(alone.join(c, ["series_id", "w", "a"]), truth, m) for m, c in chosen.items()]
        out.append(_union(got).withColumn("w_max", F.lit(w)).withColumn("a_max", F.lit(a)))
    return cut(_union(out))


def ranges(spark: SparkSession, d: str, pairs: tuple[tuple[int, int], ...], **kw) -> DataFrame:
    """Wins, ties and losses against the best single run (of random, fixed and selected) for each (w_max, a_max)."""
    scored, out = range_scores(spark, d, **kw), []
    for w_max, a_max in pairs:
        best = measures.best_of(scored.where((F.col("w_max") == w_max) & (F.col("a_max") == a_max)))
        wtl = measures.win_tie_loss(best).join(measures.best_single(best), ["dataset", "method"])
        out.append(wtl.select(F.lit(w_max).alias("w_max"), F.lit(a_max).alias("a_max"), "dataset", "method", "wins", "ties", "losses"))
    return _union(out)


def _table(found: DataFrame, truth: DataFrame, key: DataFrame, names: list[str]) -> DataFrame:
    """avg_score and hit_rate of each run's candidates; ``key`` gives a run its names."""
    scored = measures.score(found, truth).join(F.broadcast(key), "run")
    best = scored.where("rank <= 3").groupBy("dataset", "series_id", *names).agg(F.max("score").alias("score"))
    return best.groupBy(*names, "dataset").agg(F.avg("score").alias("avg_score"), F.avg((F.col("score") > 0).cast("double")).alias("hit_rate"))


def sizes(spark: SparkSession, d: str, members: tuple[int, ...] = (5, 10, 25, 50), **kw) -> DataFrame:
    """Score and hit rate for each committee size; members are a prefix of the largest draw."""
    series, truth = data(spark, d, **kw)
    params = com.draw_params(max(members), w_cap=N)
    found = grid(series, N, [(params[:n], 0.4) for n in members])
    return _table(found, truth, spark.createDataFrame(list(enumerate(members)), "run int, members int"), ["members"])


def selectivity(spark: SparkSession, d: str, taus: tuple[float, ...] = (0.05, 0.1, 0.2, 0.4, 0.8, 1.0), repeats: int = 20, members: int = 50, **kw) -> DataFrame:
    """Mean and deviation over repeats of the average score for each share of curves kept; each repeat draws its own members."""
    series, truth = data(spark, d, **kw)
    keys = [(r, tau) for r in range(repeats) for tau in taus]
    found = grid(series, N, [(com.draw_params(members, seed=100 + r, w_cap=N), tau) for r, tau in keys])
    per = _table(found, truth, spark.createDataFrame([(i, *k) for i, k in enumerate(keys)], "run int, repeat int, tau double"), ["repeat", "tau"])
    return per.groupBy("tau", "dataset").agg(F.avg("avg_score").alias("mean"), F.coalesce(F.stddev_samp("avg_score"), F.lit(0.0)).alias("sd"))


def lengths(spark: SparkSession, d: str, shares: tuple[float, ...] = (0.6, 0.7, 0.8, 0.9, 1.0), members: int = 50, **kw) -> DataFrame:
    """Score and hit rate for windows shorter than the planted instance."""
    series, truth = data(spark, d, **kw)
    out = []
    for share in shares:
        n = int(N * share)
        found = grid(series, n, [(com.draw_params(members, w_cap=n), 0.4)])
        out.append(_table(found, truth, spark.createDataFrame([(0, share)], "run int, share double"), ["share"]))
    return _union(out)


def two_anomalies(spark: SparkSession, d: str, copies: int = 10, label: int = 5, members: int = 50, length: int = 1024, normal: int = 40) -> DataFrame:
    """How many of two planted anomalies the first three candidates overlap, for each series of ``normal`` + 2 instances."""
    series, truth = data(spark, d, labels=(label,), copies=copies, lengths=(length,), normal=normal, anomalies=2)
    found = detect.detect_committee(series.select("series_id", "pos", "x"), length, members)
    return measures.truths_found(found, truth)


def landscape(df: DataFrame, true_loc: int, n: int, w_max: int = 10, a_max: int = 10) -> DataFrame:
    """Score of every single (w, a) run on each series, one row a w, one column an a. For many short series: each is one kernel call."""
    pairs = [(w, a) for w in range(2, w_max + 1) for a in range(2, a_max + 1)]

    def one(name: str, x: np.ndarray) -> list[tuple]:
        found = ((w, a, kernel.window_candidates(np.repeat(d.astype(float), hi - lo + 1), n)) for w, a, lo, hi, d in kernel.pair_curves(x, n, pairs))
        return [(name, w, a, max(1.0 - min(1.0, abs(at + 1 - true_loc) / n) for at, _ in got)) for w, a, got in found if got]

    scores = detect.by_series(df, one, "series_id string, w int, a int, score double")
    return scores.groupBy("series_id", "w").pivot("a", list(range(2, a_max + 1))).agg(F.max("score"))


def extreme_curves(df: DataFrame, n: int, members: int = 50) -> DataFrame:
    """Deviation and level of the two most and the two least varied member curves. For many short series: each is one kernel call."""
    params = com.draw_params(members, w_cap=n)

    def one(name: str, x: np.ndarray) -> list[tuple]:
        found = ((w, a, hi - lo + 1, d) for w, a, lo, hi, d in kernel.pair_curves(x, n, params))
        return [(name, w, a, int(size.sum()), int((size * d).sum()), int(d.max()), Decimal(kernel.spread(size, d))) for w, a, size, d in found]

    stats = detect.by_series(df, one, "series_id string, w int, a int, len long, total long, top long, spread decimal(38)")
    ranked = com.keep_by_spread(com.deviation(stats), 1.0)
    return ranked.where((F.col("rank") <= 2) | (F.col("rank") > min(members, 81) - 2)).select("series_id", "w", "a", "rank", F.round("sd", 6).alias("sd"), F.round("level", 6).alias("level"))


def incompressible_share(tokens: DataFrame) -> DataFrame:
    """(series_id, tokens, loose): of an already discrete token sequence, how many tokens no rule covers."""
    import pandas as pd

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        bodies, _ = kernel.grammar_rows(pdf.sort_values("pos")["word"])
        depth = kernel.token_depth(bodies)
        return pd.DataFrame({"series_id": [pdf["series_id"].iloc[0]], "tokens": [len(depth)], "loose": [int((depth == 0).sum())]})

    return tokens.groupBy("series_id").applyInPandas(run, "series_id string, tokens long, loose long")


def run_times(spark: SparkSession, d: str, points: tuple[int, ...] = (2_000, 4_000, 8_000), sizes: tuple[int, ...] = (100, 200)) -> DataFrame:
    """(method, n, points, seconds) of the committee and the discord baseline over heads of one long series; each run is computed once and thrown away."""
    from rarespan.sources.series import from_orders

    walk, rows = cut(from_orders(spark, d, "walk")), []
    for m in points:
        head = cut(walk.where(F.col("pos") <= m))
        for n in sizes:
            rows.append(("committee", n, m, measures.timed(detect.detect_committee(head, n))))
            rows.append(("discord", n, m, measures.timed(discord.discord_profile(head, n, tiles=8))))
    return spark.createDataFrame(rows, "method string, n int, points int, seconds double")
