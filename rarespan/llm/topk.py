"""Exact top-k inner products by branch and bound over columns.

Vectors are stored dimension by dimension, those of largest spread first. For a query the partial scores of all candidates
of a block grow by ``STEP`` dimensions at a time. What the remaining dimensions can add is at most the product of the remaining
norms of both vectors, so a candidate whose partial score plus that mass stays below the k-th best score known is out, and the
survivors are compacted before the next step. The first threshold comes from completing the k best partial scores.

Queries and candidates meet block by block: every block pair is one bounded task, and a task hands on at most k rows a query.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

K = 20
STEP = 16
QUERY_BLOCK = 1024
CANDIDATE_BLOCK = 16_384
_EXACT = 2.0**53


def quantised(column: Column, scale: float = 64.0) -> Column:
    """floor(scale x component) as longs, components as doubles; null for vectors that are null or hold nulls or non-finite numbers.

    Components beyond the range of a long are put at its ends.
    """
    x = F.transform(column, lambda c: F.floor(F.least(F.greatest(c.cast("double") * scale, F.lit(-9.2e18)), F.lit(9.2e18))).cast("long"))
    bad = F.exists(column, lambda c: c.isNull() | F.isnan(c) | (F.abs(c.cast("double")) == F.lit(float("inf"))))
    return F.when(column.isNotNull() & ~F.coalesce(bad, F.lit(True)), x)


def best_in_block(queries: np.ndarray, query_ids: np.ndarray, rows: np.ndarray, row_ids: np.ndarray, k: int = K) -> tuple[list, list, list]:
    """(query ids, row ids, scores) of each query's k best rows, its own id excluded, ties to the smaller id."""
    dims = rows.shape[1]
    reach = float(np.abs(queries).max(initial=0)) * float(np.abs(rows).max(initial=0)) * dims
    if reach >= _EXACT:
        return _plain(queries, query_ids, rows, row_ids, k)
    spread = np.argsort(-(rows.astype(float) ** 2).sum(0), kind="stable")
    order = np.argsort(row_ids, kind="stable")
    ids = row_ids[order]
    columns = np.ascontiguousarray(rows[order][:, spread].T, dtype=float)
    q = np.ascontiguousarray(queries[:, spread], dtype=float)
    edges = [*range(0, dims, STEP), dims]
    mass = lambda m, axis: [np.sqrt((np.take(m, range(e, dims), axis) ** 2).sum(axis)) * (1 + 1e-12) + 1e-9 for e in edges[1:]]
    row_mass, query_mass = mass(columns, 0), mass(q, 1)
    first = q[:, : edges[1]] @ columns[: edges[1]]
    out_q, out_r, out_s = [], [], []
    for i, own in enumerate(query_ids.tolist()):
        partial, live = first[i], None
        lo, hi = np.searchsorted(ids, own, "left"), np.searchsorted(ids, own, "right")
        if lo < hi:
            partial = partial.copy()
            partial[lo:hi] = -np.inf
        n = len(partial) - (hi - lo)
        if n <= 0:
            continue
        kk = min(k, n)
        lead = np.argpartition(-partial, kk - 1)[:kk]
        bar = (q[i] @ columns[:, lead]).min()
        for step in range(1, len(edges) - 1):
            keep = np.flatnonzero(partial + query_mass[step - 1][i] * (row_mass[step - 1] if live is None else row_mass[step - 1][live]) >= bar)
            live = keep if live is None else live[keep]
            partial = partial[keep] + q[i, edges[step] : edges[step + 1]] @ columns[edges[step] : edges[step + 1], live]
        if live is None:
            live = np.flatnonzero(partial > -np.inf)
            partial = partial[live]
        keep = np.flatnonzero(partial >= bar)
        top = keep[np.lexsort((ids[live[keep]], -partial[keep]))][:k]
        out_q += [own] * len(top)
        out_r += ids[live[top]].tolist()
        out_s += [int(s) for s in partial[top]]
    return out_q, out_r, out_s


def _plain(queries, query_ids, rows, row_ids, k):
    """Scores too large for exact doubles: Python integers, put at the ends of a long where they leave it."""
    out_q, out_r, out_s = [], [], []
    big = rows.astype(object)
    for q, own in zip(queries.astype(object), query_ids.tolist(), strict=True):
        score = [max(-(2**63), min(2**63 - 1, int(s))) for s in big @ q]
        best = sorted((-s, r) for s, r in zip(score, row_ids.tolist(), strict=True) if r != own)[:k]
        out_q += [own] * len(best)
        out_r += [r for _, r in best]
        out_s += [-s for s, _ in best]
    return out_q, out_r, out_s


def top_k(vectors: DataFrame, is_query: Column, k: int = K, scale: float = 64.0, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank (from 1), vec_id, score: each query's k rows of highest integer inner product.

    Vectors of different length are compared as if filled up with zeros. Rows with unusable vectors or null ids take no part; a
    query has no row if there is no other candidate; repeated ids are candidates each for itself, but never for a query of the same id.
    """
    usable = vectors.select(F.col(id_col).cast("long").alias("id"), quantised(F.col(vector_col), scale).alias("x"), is_query.alias("is_query"))
    usable = usable.where("id is not null and x is not null")
    n, n_queries = usable.agg(F.count("*"), F.count(F.when(F.col("is_query"), 1))).first()
    qb, cb = max(1, math.ceil(n_queries / QUERY_BLOCK)), max(1, math.ceil(n / CANDIDATE_BLOCK))
    spot = lambda m: F.pmod(F.xxhash64("id"), F.lit(m)).cast("int")
    asked = usable.where("is_query").select(F.lit(True).alias("asks"), "id", "x", spot(qb).alias("qb"), F.explode(F.sequence(F.lit(0), F.lit(cb - 1))).alias("cb"))
    offered = usable.select(F.lit(False).alias("asks"), "id", "x", F.explode(F.sequence(F.lit(0), F.lit(qb - 1))).alias("qb"), spot(cb).alias("cb"))

    def meet(pdf: pd.DataFrame) -> pd.DataFrame:
        dims = max(map(len, pdf["x"]), default=0)
        x = np.zeros((len(pdf), max(dims, 1)), np.int64)
        for i, v in enumerate(pdf["x"]):
            x[i, : len(v)] = v
        asks, ids = pdf["asks"].to_numpy(bool), pdf["id"].to_numpy(np.int64)
        if not asks.any() or asks.all():
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []}, dtype="int64")
        got = best_in_block(x[asks], ids[asks], x[~asks], ids[~asks], k)
        return pd.DataFrame(dict(zip(("query_id", "vec_id", "score"), (np.array(g, np.int64) for g in got), strict=True)))

    part = asked.unionByName(offered).groupBy("qb", "cb").applyInPandas(meet, "query_id long, vec_id long, score long")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return part.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
