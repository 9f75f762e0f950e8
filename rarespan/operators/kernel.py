"""Array kernels: words of a chunk at many resolutions, density runs, curve merging, discords."""

from __future__ import annotations

import numpy as np

from rarespan.functions.breakpoints import summary_breaks, symbol_matrix
from rarespan.operators.inducer import induce, instances, token_depth


def coefficients(x: np.ndarray, n: int, w: int, p1: np.ndarray, root: np.ndarray, t1: np.ndarray) -> np.ndarray:
    """[w, windows] z-normalised segment means from prefix sums ``p1`` (p1[0] = 0); ``root`` is 0 for flat windows."""
    m = len(x) - n + 1
    at = np.arange(m)
    out = np.empty((w, m))
    padded = np.append(x, 0)
    edge = w * p1[at]
    for i in range(1, w + 1):
        q, r = divmod(i * n, w)
        nxt = w * p1[at + q] + (r * padded[at + q] if r else 0)
        np.subtract(nxt - edge, t1, out=out[i - 1])
        edge = nxt
    with np.errstate(divide="ignore", invalid="ignore"):
        out /= root
    out[:, root == 0] = 0.0
    return out


def window_sums(x: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(values, prefix sums, window sums, n x n x variance of each window), all in whole numbers and exact.

    Values are taken from the middle of their range, which changes no word. Sums that pass 64 bits wrap around and cancel in the differences; where a window's own result
    might not fit, squares are summed, and the last is returned, in Python's integers. Results of 2**72 or more are an error.
    """
    x = np.asarray(x, np.int64)
    low, high = int(x.min()), int(x.max())
    x = x - (low + high) // 2
    p1 = np.concatenate(([0], np.cumsum(x)))
    t1 = p1[n:] - p1[:-n]
    whole = (n * (high - low)) ** 2 < 1 << 62
    far, t = (x, t1) if whole else (x.astype(object), t1.astype(object))
    p2 = np.concatenate((np.zeros(1, far.dtype), np.cumsum(far * far)))
    v = n * (p2[n:] - p2[:-n]) - t * t
    if high - low >= 1 << 53 or (not whole and max(v, default=0) >= 1 << 72):
        raise OverflowError(f"values from {low} to {high} vary too much for exact sums over {n} of them; scale them down")
    return x, p1, t1, v


def chunk_tokens(x: np.ndarray, n: int, core: int, params: list[tuple[int, int]], a_max: int):
    """Yields (w, a, window offsets, words) of the first ``core`` windows of an integer chunk, runs collapsed.

    One search among the summary cuts serves all alphabets of a w; windows in which no interval changes are dropped before the alphabets fan out.
    """
    x = np.asarray(x, np.int64)
    m = min(core, len(x) - n + 1)
    if m <= 0:
        return
    x, p1, t1, v = window_sums(x[: m + n - 1], n)
    root = np.sqrt(np.maximum(v, 0).astype(float) * (n / (n - 1)))
    breaks = np.array(summary_breaks(a_max))
    table = np.array(symbol_matrix(a_max), np.uint8)
    by_w: dict[int, list[int]] = {}
    for w, a in params:
        by_w.setdefault(w, []).append(a)
    for w, alphabets in by_w.items():
        index = np.searchsorted(breaks, coefficients(x, n, w, p1, root, t1), side="right").astype(np.uint8)
        change = np.ones(m, bool)
        change[1:] = (index[:, 1:] != index[:, :-1]).any(0)
        at = np.flatnonzero(change)
        short = index[:, at]
        for a in alphabets:
            letters = table[:, a - 2][short]
            keep = np.ones(len(at), bool)
            keep[1:] = (letters[:, 1:] != letters[:, :-1]).any(0)
            word = np.ascontiguousarray((letters[:, keep] + np.uint8(97)).T)
            yield w, a, at[keep], word.view(f"S{w}").ravel()


def density_runs(pos: np.ndarray, words, end: int, lead: int = 1, coverage: str = "token_span", n: int = 1) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(lo, hi, d) runs over positions lead..end of the rule density of tokens that start at ``pos``, runs of equal words collapsed.

    token_span: a token reaches up to the next one. window_span: an instance reaches to the end of its last token's window.
    """
    none = np.array([lead]), np.array([end]), np.array([0])
    if len(pos) == 0:
        return none if end >= lead else tuple(np.zeros(0, np.int64) for _ in range(3))
    _, ids = np.unique(words, return_inverse=True)
    first = np.ones(len(ids), bool)
    first[1:] = ids[1:] != ids[:-1]
    pos, ids = np.asarray(pos, np.int64)[first], ids[first]
    bodies = induce(ids.tolist())
    if coverage == "token_span":
        depth = token_depth(bodies)
        start = np.concatenate(([lead], pos)) if pos[0] > lead else pos
        depth = np.concatenate(([0], depth)) if pos[0] > lead else depth
    else:
        got = instances(bodies)
        if not got:
            return none
        lo = pos[[g[1] for g in got]]
        hi = np.minimum(pos[[g[2] for g in got]] + n - 1, end)
        spot, back = np.unique(np.concatenate([lo, hi + 1]), return_inverse=True)
        step = np.bincount(back, np.repeat([1, -1], len(lo)), len(spot)).cumsum().astype(np.int64)
        inside = spot <= end
        start, depth = spot[inside], step[inside]
        if start[0] > lead:
            start, depth = np.concatenate(([lead], start)), np.concatenate(([0], depth))
    keep = np.ones(len(depth), bool)
    keep[1:] = depth[1:] != depth[:-1]
    start, depth = start[keep], depth[keep]
    return start, np.append(start[1:] - 1, end), depth.astype(np.int64)


def merge_curves(runs: list[tuple[np.ndarray, np.ndarray]], lo: int, hi: int, how: str = "median") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Point-wise combination over lo..hi of run-length curves (starts, values); equal neighbours are joined."""
    edge = np.unique(np.concatenate([[lo], *(np.clip(s, lo, hi) for s, _ in runs)]))
    grid = np.stack([v[np.maximum(np.searchsorted(s, edge, "right") - 1, 0)] for s, v in runs])
    value = {"median": np.median, "mean": np.mean, "min": np.min, "max": np.max}[how](grid, axis=0)
    keep = np.ones(len(value), bool)
    keep[1:] = value[1:] != value[:-1]
    edge, value = edge[keep], value[keep]
    return edge, np.append(edge[1:] - 1, hi), value


def window_candidates(curve: np.ndarray, n: int, k: int = 3, exclusion: int | None = None, edge: str = "keep") -> list[tuple[int, float]]:
    """Up to k windows (start from 0, summed density) of smallest sum, each at least ``exclusion`` away from those before; ties to the left."""
    exclusion = n if exclusion is None else exclusion
    total = np.concatenate(([0.0], np.cumsum(curve)))
    value = np.round(total[n:] - total[:-n], 9)
    if edge == "drop":
        value[: min(n, len(value))] = np.inf
        value[max(0, len(value) - n) :] = np.inf
    out = []
    for _ in range(k):
        if not len(value) or not np.isfinite(value).any():
            break
        i = int(value.argmin())
        out.append((i, float(value[i])))
        value[max(0, i - exclusion + 1) : i + exclusion] = np.inf
    return out


def profile_tile(x: np.ndarray, n: int, first: int, last: int) -> np.ndarray:
    """Squared nearest distances of all windows over the diagonals first <= q - p < last, by running sums of products along each diagonal."""
    m = len(x) - n + 1
    if m <= 0:
        return np.zeros(0)
    if np.issubdtype(x.dtype, np.integer):  # sums of whole numbers are exact; what wraps around cancels in the differences
        x = x.astype(np.int64) - (int(x.min()) + int(x.max())) // 2
        if n * int(np.abs(x).max()) ** 2 * n >= 1 << 63:
            x = x.astype(float)
    p1, p2 = (np.concatenate((np.zeros(1, x.dtype), np.cumsum(v))) for v in (x, x * x))
    t1, t2 = p1[n:] - p1[:-n], p2[n:] - p2[:-n]
    mean = t1 / n
    sd = np.sqrt(np.maximum(n * t2 - t1 * t1, 0)) / n
    best = np.full(m, -np.inf)
    flat = sd < 1e-12
    safe = np.where(flat, 1.0, sd)
    for d in range(first, min(last, m)):
        prod = np.concatenate((np.zeros(1, x.dtype), np.cumsum(x[:-d] * x[d:])))
        dots = prod[n:] - prod[:-n]
        corr = (dots - n * mean[: m - d] * mean[d:]) / (n * safe[: m - d] * safe[d:])
        either, both = flat[: m - d] | flat[d:], flat[: m - d] & flat[d:]
        corr = np.where(both, 1.0, np.where(either, 0.5, corr))
        np.maximum(best[: m - d], corr, out=best[: m - d])
        np.maximum(best[d:], corr, out=best[d:])
    return 2.0 * n * (1.0 - np.minimum(best, 1.0))


def grammar_rows(words) -> tuple[dict[int, list[int]], list[str]]:
    """Grammar and terminal names of a word sequence, terminals numbered by first occurrence."""
    seen: dict[str, int] = {}
    ids = [seen.setdefault(w, len(seen)) for w in words]
    return induce(ids), list(seen)



def spread(size: np.ndarray, d: np.ndarray) -> int:
    """Points x sum of squares - squared sum of a run-length curve, exactly."""
    return int(size.sum()) * int((size * d * d).sum()) - int((size * d).sum()) ** 2


def pair_curves(x: np.ndarray, n: int, pairs: list[tuple[int, int]]):
    """Yields (w, a, lo, hi, d), the density runs of each pair, of one short series."""
    for w, a, at, words in chunk_tokens(x, n, len(x), pairs, max(a for _, a in pairs)):
        yield w, a, *density_runs(at + 1, words, len(x))


def committee_grid(x: np.ndarray, n: int, runs: list[tuple[list[tuple[int, int]], float]], k: int, singles: bool = True) -> tuple[list[list[tuple[int, float]]], dict[tuple[int, int], list[tuple[int, float]]]]:
    """(candidates of each committee, candidates of each single pair) of one short series. A run is (pairs, share kept); every pair's curve is made once for all."""
    end = len(x)
    curves = {(w, a): (-spread(hi - lo + 1, d), w, a, lo, hi, d) for w, a, lo, hi, d in pair_curves(x, n, sorted({p for own, _ in runs for p in own}))}
    committees = []
    for own, tau in runs:
        some = sorted((curves[p] for p in set(own) if p in curves), key=lambda c: c[:3])
        some = some[: max(1, int(np.ceil(tau * len(some) - 1e-9)))]
        if not some:
            committees.append([])
            continue
        lo, hi, v = merge_curves([(c[3], c[5] / c[5].max() if c[5].max() > 0 else c[5].astype(float)) for c in some], 1, end)
        committees.append(window_candidates(np.repeat(v, hi - lo + 1), n, k))
    each = {p: window_candidates(np.repeat(c[5].astype(float), c[4] - c[3] + 1), n, k) for p, c in curves.items()} if singles else {}
    return committees, each


def committee_one(x: np.ndarray, n: int, params: list[tuple[int, int]], tau: float, k: int) -> list[tuple[int, float]]:
    """Candidates (start from 0, value) of a whole short series: the stages of the committee in one call, with the same result."""
    end = len(x)
    curves = []
    for w, a, at, words in chunk_tokens(x, n, end, params, max(a for _, a in params)):
        lo, hi, d = density_runs(at + 1, words, end)
        size = hi - lo + 1
        curves.append((-spread(size, d), w, a, lo, d))
    if not curves:
        return []
    curves.sort(key=lambda c: c[:3])
    kept = curves[: max(1, int(np.ceil(tau * len(curves) - 1e-9)))]
    lo, hi, v = merge_curves([(s, d / d.max() if d.max() > 0 else d.astype(float)) for _, _, _, s, d in kept], 1, end)
    return window_candidates(np.repeat(v, hi - lo + 1), n, k)
