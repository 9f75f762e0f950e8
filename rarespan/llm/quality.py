"""Quality by a sparse rule ensemble.

Statistics of a text are gathered once by vectorised kernels. Boosted shallow trees are grown on a bounded sample of labelled
documents; every path from a root to a node becomes a conjunctive rule over the statistics. A lasso logistic model over the
rules (and the clipped statistics themselves) keeps a few of them, and these are compiled into one Spark column expression,
so that scoring runs inside the query plan without the model's code.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as St

from rarespan.llm import textkit as T
from rarespan.llm.logistic import fit_lasso_logistic
from rarespan.llm.sampling import bounded
from rarespan.runtime import cut

SAMPLE = 20_000  # at most so many labelled rows are learnt from
TREES, DEPTH, RATE, LEAST = 40, 3, 0.2, 10
PENALTY = 0.001

STATISTICS = (
    "log_bytes", "log_words", "word_length", "longest_word", "upper", "digit", "mark", "symbol", "wide", "line_length",
    "log_lines", "repeated_lines", "distinct_words", "top_word", "twin_words", "odd_words", "stops", "short_words", "repeated_grams", "upper_words",
)

_KIND = np.zeros(256, np.uint8)
_KIND[ord("A") : ord("Z") + 1] = 1
_KIND[ord("0") : ord("9") + 1] = 2
_KIND[[ord(c) for c in ".,;:!?'\"()-"]] = 3
_KIND[[ord(c) for c in "#$%&*+/<=>@[\\]^_`{|}~"]] = 4
_KIND[128:] = 5


def _share_of_distinct(values: np.ndarray, doc: np.ndarray, n_docs: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of each text, and the count of its most frequent one."""
    distinct, top = np.zeros(n_docs), np.zeros(n_docs)
    if not len(values):
        return distinct, top
    order = np.lexsort((values, doc))
    v, d = values[order], doc[order]
    head = np.flatnonzero(np.concatenate(([True], (v[1:] != v[:-1]) | (d[1:] != d[:-1]))))
    size = np.diff(np.append(head, len(v)))
    np.add.at(distinct, d[head], 1)
    np.maximum.at(top, d[head], size)
    return distinct, top


def statistics(raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """One row of STATISTICS for each text; all zero for texts without words."""
    n = len(offsets) - 1
    out = np.zeros((n, len(STATISTICS)))
    w = T.words(raw, offsets, lower=False)
    if not len(w.start):
        return out
    size = np.diff(offsets).astype(float)
    safe = np.maximum(size, 1)
    many = np.maximum(w.per_doc, 1)
    doc = np.repeat(np.arange(n), np.diff(offsets))
    kind = _KIND[raw]
    counts = np.bincount(doc * 6 + kind, minlength=6 * n).reshape(n, 6)
    full = np.flatnonzero(w.per_doc)
    first = w.first[full]
    length = (w.end - w.start).astype(float)
    col = dict(zip(STATISTICS, range(len(STATISTICS)), strict=True))

    def put(name: str, value) -> None:
        out[:, col[name]] = value

    def per_word(value: np.ndarray, how=np.add) -> np.ndarray:
        got = np.zeros(n)
        got[full] = how.reduceat(value.astype(float), first)
        return got

    put("log_bytes", np.log1p(size))
    put("log_words", np.log1p(w.per_doc))
    put("word_length", per_word(length) / many)
    put("longest_word", np.log1p(per_word(length, np.maximum)))
    for name, k in (("upper", 1), ("digit", 2), ("mark", 3), ("symbol", 4), ("wide", 5)):
        put(name, counts[:, k] / safe)
    breaks = np.flatnonzero(raw == 0x0A)
    line_start = np.unique(np.concatenate([offsets[:-1][size > 0], breaks + 1]))
    line_start = line_start[line_start < len(raw)]
    line_doc = np.searchsorted(offsets, line_start, "right") - 1
    lines = np.bincount(line_doc, minlength=n)
    put("log_lines", np.log1p(lines))
    put("line_length", np.log1p(size / np.maximum(lines, 1)))
    line_key = T.tile_hashes(raw[line_start[0] :], line_start - line_start[0])
    distinct, _ = _share_of_distinct(line_key, line_doc, n)
    put("repeated_lines", 1 - distinct / np.maximum(lines, 1))
    h = T.word_hashes(w)
    distinct, top = _share_of_distinct(h, w.doc, n)
    put("distinct_words", distinct / many)
    put("top_word", top / many)
    twin = np.zeros(len(h))
    twin[1:] = (h[1:] == h[:-1]) & (w.doc[1:] == w.doc[:-1])
    put("twin_words", per_word(twin) / many)
    word_kind = _KIND[w.buf]
    odd = np.concatenate(([0], np.cumsum(word_kind == 4)))
    put("odd_words", per_word(odd[w.end] > odd[w.start]) / many)
    upper = np.concatenate(([0], np.cumsum(word_kind == 1)))
    put("upper_words", per_word(upper[w.end] - upper[w.start] >= 2) / many)
    last = w.buf[w.end - 1]
    put("stops", per_word((last == 0x2E) | (last == 0x21) | (last == 0x3F)) / many)
    put("short_words", per_word(length <= 3) / many)
    gram = h.copy()
    gram[:-1] = T.pair_hashes(h[:-1], h[1:])
    inside = np.ones(len(h), bool)
    inside[w.first[full] + w.per_doc[full] - 1] = False
    distinct, _ = _share_of_distinct(gram[inside], w.doc[inside], n)
    put("repeated_grams", 1 - np.where(w.per_doc > 1, distinct / np.maximum(w.per_doc - 1, 1), 1))
    out[w.per_doc == 0] = 0
    return np.round(out, 6)


def with_statistics(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """doc_id and the statistics of each whole text; null texts count as empty, repeated rows stay, other columns go."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, offsets = T.text_buffers(b.column(1))
            parts = [statistics(raw[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]) for lo, hi in T.blocks(offsets)]
            x = np.concatenate(parts) if parts else np.zeros((0, len(STATISTICS)))
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(x[:, j].copy()) for j in range(len(STATISTICS)))], ["doc_id", *STATISTICS])

    schema = St.StructType([St.StructField("doc_id", St.LongType()), *(St.StructField(s, St.DoubleType()) for s in STATISTICS)])
    return docs.select(F.col("doc_id").cast("long"), F.col(text_col)).mapInArrow(run, schema)


@dataclass(frozen=True)
class Rule:
    """All of the bounds hold: (statistic, threshold, above)."""

    bounds: tuple[tuple[int, float, bool], ...]

    def holds(self, x: np.ndarray) -> np.ndarray:
        out = np.ones(len(x), bool)
        for j, t, above in self.bounds:
            out &= (x[:, j] > t) if above else (x[:, j] <= t)
        return out

    def column(self) -> Column:
        out = F.lit(True)
        for j, t, above in self.bounds:
            out = out & ((F.col(STATISTICS[j]) > F.lit(t)) if above else (F.col(STATISTICS[j]) <= F.lit(t)))
        return out


def _grow(x: np.ndarray, target: np.ndarray, cuts: list[np.ndarray], bins: np.ndarray, rows: np.ndarray, path: tuple, depth: int, rules: list[Rule], value: np.ndarray):
    """Least-squares splits on binned statistics; each node below the root gives a rule."""
    if path:
        rules.append(Rule(path))
    value[rows] = target[rows].mean()
    if depth == 0 or len(rows) < 2 * LEAST:
        return
    best = (1e-9, None)
    total, n = target[rows].sum(), len(rows)
    for j, cut_points in enumerate(cuts):
        if not len(cut_points):
            continue
        b = bins[rows, j]
        count = np.bincount(b, minlength=len(cut_points) + 1)[:-1].cumsum()
        left = np.bincount(b, target[rows], minlength=len(cut_points) + 1)[:-1].cumsum()
        fit = (count >= LEAST) & (n - count >= LEAST)
        gain = np.where(fit, left**2 / np.maximum(count, 1) + (total - left) ** 2 / np.maximum(n - count, 1) - total**2 / n, -1)
        k = int(gain.argmax())
        if gain[k] > best[0]:
            best = (gain[k], (j, k))
    if best[1] is None:
        return
    j, k = best[1]
    t = float(cuts[j][k])
    low = rows[bins[rows, j] <= k]
    high = rows[bins[rows, j] > k]
    _grow(x, target, cuts, bins, low, (*path, (j, t, False)), depth - 1, rules, value)
    _grow(x, target, cuts, bins, high, (*path, (j, t, True)), depth - 1, rules, value)


def extract_rules(x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH, seed: int = 3) -> list[Rule]:
    """Paths of gradient-boosted trees, each grown on a random half of the rows."""
    rng = np.random.default_rng(seed)
    cuts = [np.unique(np.quantile(c, np.linspace(0.02, 0.98, 49))) for c in x.T]
    bins = np.column_stack([np.searchsorted(c, v, "left") for c, v in zip(cuts, x.T, strict=True)])
    p = np.clip(y.mean(), 1e-3, 1 - 1e-3)
    z = np.full(len(y), np.log(p / (1 - p)))
    rules: list[Rule] = []
    for _ in range(trees):
        residual = y - 1 / (1 + np.exp(-z))
        rows = np.flatnonzero(rng.random(len(y)) < 0.5)
        if len(rows) < 2 * LEAST:
            break
        value, own = np.zeros(len(y)), []
        _grow(x, residual, cuts, bins, rows, (), depth, own, value)
        rules += own
        pred, seen = np.zeros(len(y)), np.zeros(len(y))
        for r in own:  # deeper rules come after their parents, so the last one that holds is the leaf
            hold = r.holds(x)
            pred[hold] = residual[rows][r.holds(x[rows])].mean() if r.holds(x[rows]).any() else 0.0
            seen[hold] = 1
        z += RATE * 4 * np.where(seen > 0, pred, 0)
    return list(dict.fromkeys(rules))


@dataclass
class RuleModel:
    """Intercept, weighted rules, and weighted statistics clipped to [low, high] and scaled."""

    intercept: float = 0.0
    rules: list[tuple[Rule, float]] = field(default_factory=list)
    linear: list[tuple[int, float, float, float]] = field(default_factory=list)
    constant: float | None = None

    def column(self) -> Column:
        """The probability of label 1 as one column expression over the statistics."""
        if self.constant is not None:
            return F.lit(self.constant)
        terms = [F.lit(self.intercept)]
        terms += [F.when(r.column(), F.lit(w)).otherwise(F.lit(0.0)) for r, w in self.rules]
        terms += [F.lit(w) * F.least(F.greatest(F.col(STATISTICS[j]), F.lit(lo)), F.lit(hi)) for j, lo, hi, w in self.linear]
        total = terms[0]
        for t in terms[1:]:
            total = total + t
        return 1 / (1 + F.exp(-total))


def fit_rules(x: np.ndarray, y: np.ndarray, penalty: float = PENALTY) -> RuleModel:
    if len(y) == 0 or y.min() == y.max():
        return RuleModel(constant=float(y.mean()) if len(y) else 0.5)
    rules = extract_rules(x, y)
    hold = np.column_stack([r.holds(x) for r in rules]).astype(float) if rules else np.zeros((len(x), 0))
    low, high = np.quantile(x, 0.02, axis=0), np.quantile(x, 0.98, axis=0)
    clipped = np.clip(x, low, high)
    mean, scale = clipped.mean(0), np.maximum(clipped.std(0), 1e-9)
    share = hold.mean(0)
    spread = np.maximum(np.sqrt(share * (1 - share)), 1e-3)
    z = np.column_stack([(hold - share) / spread, 0.4 * (clipped - mean) / scale])
    b, w = fit_lasso_logistic(z, y, penalty)
    rule_w, line_w = w[: len(rules)] / spread, 0.4 * w[len(rules) :] / scale
    b -= float((rule_w * share).sum() + (line_w * mean).sum())
    kept = [(r, float(v)) for r, v in zip(rules, rule_w, strict=True) if v]
    lines = [(j, float(low[j]), float(high[j]), float(v)) for j, v in enumerate(line_w) if v]
    return RuleModel(b, kept, lines)


def train(stats: DataFrame, labels: DataFrame, folds: int = 4, held_out: int = 2, most: int = SAMPLE) -> RuleModel:
    """A model from at most ``most`` labelled rows outside the held-out fold, chosen by a hash of their ids."""
    fold = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(folds))
    usable = labels.where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("quality").alias("y")).where(fold != held_out)
    rows = stats.join(F.broadcast(bounded(usable, most)), "doc_id").orderBy(F.xxhash64("doc_id"), "doc_id", *STATISTICS).limit(most)
    got = rows.toPandas()
    return fit_rules(got[list(STATISTICS)].to_numpy(float), got["y"].to_numpy(float))


def score_documents(docs: DataFrame, labels: DataFrame, threshold: float = 0.7, folds: int = 4, held_out: int = 2, most: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, score, predicted and the statistics for each document.

    Texts without words (null, empty, white space) are scored like any other, by all-zero statistics. Without labels of both classes the
    score is their mean, or 0.5 without any. Every row of a repeated id has a row; a null id is not held out.
    """
    stats = cut(with_statistics(docs))
    model = train(stats, labels, folds, held_out, most)
    fold = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(folds))
    scored = stats.withColumn("score", model.column().cast("double")).withColumn("held_out", F.coalesce(fold == held_out, F.lit(False)))
    return scored.select("doc_id", "held_out", "score", (F.col("score") >= threshold).cast("int").alias("predicted"), *STATISTICS)
