"""Nearest-neighbour baselines: the window farthest from its nearest neighbour. All are quadratic in the series' length."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rarespan.operators import kernel
from rarespan.operators.windows import znorm
from rarespan.schemas import CANDIDATE


def top_of(pos: np.ndarray, distance: np.ndarray, n: int, k: int, exclusion: int) -> list[tuple[int, float]]:
    """The k windows (position, distance) of largest distance that keep ``exclusion`` apart; ties to the left."""
    d, out = np.round(distance.astype(float), 9), []
    for _ in range(k):
        if not len(d) or not np.isfinite(d).any():
            break
        i = int(np.nanargmax(np.where(np.isfinite(d), d, -np.inf)))
        out.append((int(pos[i]), float(d[i])))
        d[np.abs(pos - pos[i]) < exclusion] = -np.inf
    return out


def one_series(x: np.ndarray, n: int, k: int = 3) -> list[tuple[int, float]]:
    """``discord_profile`` of one short series: the same windows (position from 1, distance)."""
    m = len(x) - n + 1
    if m <= n:
        return []
    d2 = kernel.profile_tile(x, n, n, m)
    at = np.flatnonzero(np.isfinite(d2))
    return top_of(at + 1, np.sqrt(np.maximum(d2[at], 0.0)), n, k, n)


def _top(profile: DataFrame, n: int, k: int, exclusion: int) -> DataFrame:
    """The k windows of largest distance that keep ``exclusion`` apart, as candidates; ties to the left."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("pos")
        got = top_of(pdf["pos"].to_numpy(), pdf["distance"].to_numpy(float), n, k, exclusion)
        rows = [(pdf["series_id"].iloc[0], r + 1, at, at + n - 1, at, v) for r, (at, v) in enumerate(got)]
        return pd.DataFrame(rows, columns=["series_id", "rank", "lo", "hi", "loc", "value"])

    return profile.groupBy("series_id").applyInPandas(run, CANDIDATE)


def bruteforce_profile(df: DataFrame, n: int, exclusion: int | None = None) -> DataFrame:
    """(series_id, pos, distance) by comparing all pairs of windows; for short series only."""
    z = znorm(df, n, ddof=0)
    far = n if exclusion is None else exclusion
    other = z.select("series_id", F.col("pos").alias("q"), F.col("z").alias("y"))
    gap = F.aggregate(F.zip_with("z", "y", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
    pairs = z.join(other, "series_id").where(F.abs(F.col("pos") - F.col("q")) >= far)
    return pairs.groupBy("series_id", "pos").agg(F.sqrt(F.min(gap)).alias("distance"))


def profile(df: DataFrame, n: int, exclusion: int | None = None, tiles: int = 64) -> DataFrame:
    """(series_id, pos, distance) by running sums along diagonals, which are dealt to tiles; each tile carries its series as one array."""
    far = n if exclusion is None else exclusion
    whole = df.groupBy("series_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "x"))), lambda s: s["x"]).alias("xs"))
    spread = whole.withColumn("tile", F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)))).repartition(tiles, "series_id", "tile")

    def run(frames):
        for pdf in frames:
            for sid, xs, tile in zip(pdf["series_id"], pdf["xs"], pdf["tile"], strict=True):
                x = np.asarray(xs, np.int64)
                m = len(x) - n + 1
                if m <= far:
                    continue
                # equal work: diagonal d has m - d cells
                share = np.cumsum(np.arange(m - far, 0, -1, dtype=float))
                cutoff = np.searchsorted(share, share[-1] * np.arange(tiles + 1) / tiles)
                a, b = far + int(cutoff[tile]), far + (int(cutoff[tile + 1]) if tile + 1 < tiles else m)
                if a < b:
                    d2 = kernel.profile_tile(x, n, a, b)
                    at = np.flatnonzero(np.isfinite(d2))
                    yield pd.DataFrame({"series_id": sid, "pos": at + 1, "d2": np.maximum(d2[at], 0.0)})

    part = spread.mapInPandas(run, "series_id string, pos long, d2 double")
    return part.groupBy("series_id", "pos").agg(F.sqrt(F.min("d2")).alias("distance"))


def discord_bruteforce(df: DataFrame, n: int, k: int = 3, exclusion: int | None = None) -> DataFrame:
    return _top(bruteforce_profile(df, n, exclusion), n, k, exclusion or n)


def discord_profile(df: DataFrame, n: int, k: int = 3, exclusion: int | None = None, tiles: int = 64) -> DataFrame:
    return _top(profile(df, n, exclusion, tiles), n, k, exclusion or n)


def discord_ordered(df: DataFrame, n: int, k: int = 3, w: int = 3, a: int = 3, exclusion: int | None = None) -> DataFrame:
    """Early abandoning: windows with rare words first, neighbours with the same word first, left as soon as they cannot win any more."""
    far = n if exclusion is None else exclusion

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        x = pdf.sort_values("pos")["x"].to_numpy(np.int64)
        m = len(x) - n + 1
        if m <= far:
            return pd.DataFrame({"series_id": [], "rank": [], "lo": [], "hi": [], "loc": [], "value": []})
        frame = np.lib.stride_tricks.sliding_window_view(x.astype(float), n)
        sd = frame.std(1)
        z = (frame - frame.mean(1)[:, None]) / np.where(sd > 0, sd, 1)[:, None]
        z[sd == 0] = 0
        word = np.empty(m, object)
        for _, _, at, words in kernel.chunk_tokens(x, n, m, [(w, a)], a):
            word[:] = np.repeat(words, np.diff(np.append(at, m)))
        _, code, times = np.unique(word.astype(str), return_inverse=True, return_counts=True)
        order = np.argsort(times[code], kind="stable")
        rows, banned = [], np.zeros(m, bool)
        for r in range(1, k + 1):
            best, where = -1.0, -1
            for i in order:
                if banned[i]:
                    continue
                ok = np.abs(np.arange(m) - i) >= far
                same = np.flatnonzero(ok & (code == code[i]))
                nearest = np.sqrt(((z[same] - z[i]) ** 2).sum(1).min()) if len(same) else np.inf
                if nearest < best:
                    continue
                other = np.flatnonzero(ok & (code != code[i]))
                for lo in range(0, len(other), 64):
                    nearest = min(nearest, np.sqrt(((z[other[lo : lo + 64]] - z[i]) ** 2).sum(1).min()))
                    if nearest < best:
                        break
                if nearest > best + 1e-9 or (abs(nearest - best) <= 1e-9 and i < where):
                    best, where = nearest, int(i)
            if where < 0 or not np.isfinite(best):
                break
            rows.append((pdf["series_id"].iloc[0], r, where + 1, where + n, where + 1, round(float(best), 9)))
            banned |= np.abs(np.arange(m) - where) < far
        return pd.DataFrame(rows, columns=["series_id", "rank", "lo", "hi", "loc", "value"])

    return df.select("series_id", "pos", "x").groupBy("series_id").applyInPandas(run, CANDIDATE)
