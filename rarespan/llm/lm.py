"""Language-model scores from a log-frequency Bloom filter.

N-gram counts of the training documents, words and n-grams up to ``ORDER``, are gathered over the whole corpus, and every one of them is kept.
A count c is quantised to level 1 + floor(log2(c)); an n-gram of level q is put into the filter as q keys (n-gram, 1) .. (n-gram, q),
so its level is read back by probing level after level until one is absent. The filter has ``BITS_PER_KEY`` bits for each key, so it grows
with the corpus; all keys of an n-gram fall into one of its segments, which are built by separate tasks, and the bits of a key into one 64-bit word.

A filter of up to ``BROADCAST`` bytes is broadcast to the workers. A larger one never leaves its tasks: blocks of texts send their n-grams to the segments
and get the levels back. Both ways probe the same bits, so scores do not depend on the way.

P(w | v) mixes estimates (max(low(v, w) - DISCOUNT, 0) + k * P(w)) / (high(v) + k) with a strong and a weak k: low is the least count of the pair's level,
high the greatest of the history's, so the probabilities of a history's words sum to one at most; the discount keeps what a text says only about itself from
counting as evidence. Longer n-grams are mixed with the shorter likewise. P(w) gives each word the mean count of its level (the most frequent ones their own), plus one half, which sums to one exactly.

Beside it stands the exact unigram base score. Counts of the most frequent words are broadcast (``HEADS`` at most); the others are
joined on the word's hash. Words are told apart by 64-bit hashes throughout.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rarespan.llm import textkit as T
from rarespan.runtime import cut, shuffle_partitions

ORDER = 2
SEGMENTS = 256  # at least
BUCKETS = 4096
SEGMENT_BYTES = 1 << 22  # a segment has about so many at most
BITS_PER_KEY = 10
BROADCAST = 256 << 20
HEADS = 1 << 18
MIXTURE = ((0.8, 3000.0), (0.2, 5.0))  # (share, k): the weak one follows passages seen before
DISCOUNT = 0.9
LEVELS = 64
_END = np.uint64(0x5EED0E4D)
_BEGIN = np.uint64(0x5EED0B36)
_STEP = np.uint64(0x9E3779B97F4A7C15)
_GROUP = 400_000


def level(counts: np.ndarray) -> np.ndarray:
    return np.frexp(np.maximum(counts, 1).astype(float))[1].astype(np.int64)


def least(levels: np.ndarray) -> np.ndarray:
    return np.where(levels > 0, 2.0 ** (np.maximum(levels, 1) - 1), 0.0)


def greatest(levels: np.ndarray) -> np.ndarray:
    return np.where(levels > 0, 2.0**levels - 1, 0.0)


def _level_of(c: Column) -> Column:
    return (F.floor(F.log2(c.cast("double")) + 1e-9) + 1).cast("int")


def tokens(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(token hash, hash of the token before, tokens per text); the last token of each text is the end."""
    w = T.words(raw, offsets)
    n = w.per_doc + 1
    last = np.cumsum(n) - 1
    key = np.empty(int(n.sum()), np.uint64)
    is_end = np.zeros(len(key), bool)
    is_end[last] = True
    key[is_end] = _END
    key[~is_end] = T.word_hashes(w)
    before = np.empty_like(key)
    before[1:] = key[:-1]
    before[last - n + 1] = _BEGIN
    return key, before, n


def _continued(keys: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(key of the token before, whether there is one in the same text) of tokens in texts of ``n`` tokens."""
    inside = np.ones(len(keys), bool)
    inside[np.cumsum(n) - n] = False
    return np.concatenate((keys[:1], keys[:-1])), inside


def _merge(keys: list, counts: list) -> tuple[np.ndarray, np.ndarray]:
    k, c = np.concatenate(keys), np.concatenate(counts)
    unique, back = np.unique(k, return_inverse=True)
    return unique, np.bincount(back, c, len(unique)).astype(np.int64)


def ngram_counts(docs: DataFrame, order: int) -> DataFrame:
    """(h, c): counts of words (order 1), of pairs of neighbours (2) or of n-grams of words (3 and more) over whole texts, the end included."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys: list[np.ndarray] = []
        counts: list[np.ndarray] = []
        held = 0

        def flush():
            k, c = _merge(keys, counts)
            keys.clear()
            counts.clear()
            return pa.RecordBatch.from_arrays([pa.array(k.view(np.int64)), pa.array(c)], ["h", "c"])

        for b in batches:
            raw, offsets = T.text_buffers(b.column(0))
            for lo, hi in T.blocks(offsets):
                at = offsets[lo : hi + 1]
                key, before, n = tokens(raw[at[0] : at[-1]], at - at[0])
                unique, c = np.unique(grams(key, before, n, order)[order - 1], return_counts=True)
                keys.append(unique)
                counts.append(c.astype(np.int64))
                held += len(unique)
                if held > _GROUP:
                    yield flush()
                    held = 0
        if keys:
            yield flush()

    return docs.select("text").mapInArrow(run, "h long, c long").groupBy("h").agg(F.sum("c").alias("c"))


def grams(key: np.ndarray, before: np.ndarray, n: np.ndarray, order: int) -> list[np.ndarray]:
    """Hashes of the n-grams that end at each token, for 1 .. order; from order 3 on, only at tokens that have so many before them."""
    out = [key]
    if order >= 2:
        out.append(T.pair_hashes(before, key))
    whole, history = np.ones(len(key), bool), out[-1]
    for _ in range(3, order + 1):
        history, inside = _continued(history, n)
        whole = whole & inside & np.concatenate((whole[:1], whole[:-1]))
        history = T.pair_hashes(history, key)
        out.append(history[whole])
    return out


def segment_of(key: np.ndarray, segments: int) -> np.ndarray:
    return (key >> np.uint64(32)) * np.uint64(segments) >> np.uint64(32)


def _places(key: np.ndarray, lev: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Each key's word within its segment of ``size`` words, and its four bits there."""
    x = T.mix64(key + lev.astype(np.uint64) * _STEP)
    mask = np.uint64(1) << (x & np.uint64(63))
    for shift in (6, 12, 18):
        mask |= np.uint64(1) << ((x >> np.uint64(shift)) & np.uint64(63))
    return ((x >> np.uint64(32)) * np.uint64(size) >> np.uint64(32)).astype(np.int64), mask


@dataclass
class Filter:
    """``words`` holds ``segments`` equal parts of 64-bit words. A single segment can stand for itself."""

    words: np.ndarray
    segments: int = SEGMENTS

    def levels(self, key: np.ndarray) -> np.ndarray:
        """Level of each n-gram: repeated membership probes until the first absent level."""
        out = np.zeros(len(key), np.uint8)
        size = len(self.words) // self.segments
        base = segment_of(key, self.segments).astype(np.int64) * size
        live, lev = np.arange(len(key)), 1
        while len(live) and size and lev < LEVELS:
            at, mask = _places(key[live], np.full(1, lev), size)
            live = live[self.words[base[live] + at] & mask == mask]
            out[live] = lev
            lev += 1
        return out


def filter_shape(keys: int, bits_per_key: int = BITS_PER_KEY) -> tuple[int, int]:
    """(segments, 64-bit words of each) for so many keys; segments are a power of two, so that buckets and segments nest."""
    words, segments = keys * bits_per_key // 64 + 1, SEGMENTS
    while words * 8 > segments * SEGMENT_BYTES:
        segments *= 2
    return segments, words // segments + 1


def packed(counts: DataFrame) -> DataFrame:
    """(s, h, q, keys) of (h, c): n-grams and their levels end to end in binaries, a row for many n-grams of one of ``BUCKETS`` ranges; keys is the sum of the levels."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0

        def flush():
            key, q = np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held])
            held.clear()
            order = np.argsort(key)
            key, q = key[order], q[order]
            part = segment_of(key, BUCKETS).astype(np.int32)
            edge = np.flatnonzero(np.diff(part, prepend=-1))
            cut_at = list(zip(edge.tolist(), [*edge[1:].tolist(), len(key)], strict=True))
            total = np.add.reduceat(q.astype(np.int64), edge) if len(edge) else np.zeros(0, np.int64)
            columns = [pa.array(part[edge]), pa.array([key[a:z].tobytes() for a, z in cut_at], pa.binary()), pa.array([q[a:z].tobytes() for a, z in cut_at], pa.binary()), pa.array(total)]
            return pa.RecordBatch.from_arrays(columns, ["s", "h", "q", "keys"])

        for b in batches:
            held.append((b.column(0).to_numpy(zero_copy_only=False).view(np.uint64), level(b.column(1).to_numpy(zero_copy_only=False)).astype(np.uint8)))
            size += len(b)
            if size > _GROUP:
                yield flush()
                size = 0
        if held:
            yield flush()

    return counts.select("h", "c").mapInArrow(run, "s int, h binary, q binary, keys long")


def build_filter(grams: DataFrame, segments: int, size: int) -> DataFrame:
    """(s, bits): the filter of ``packed`` rows, a row a segment of ``size`` words; segments without keys have none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        maps: dict[int, np.ndarray] = {}
        for b in batches:
            for held, levels in zip(b.column(0), b.column(1), strict=True):
                k, n = np.frombuffer(held.as_buffer(), np.uint64), np.frombuffer(levels.as_buffer(), np.uint8).astype(np.int64)
                row = np.repeat(np.arange(len(k)), n)
                lev = np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n) + 1
                at, mask = _places(k[row], lev, size)
                part = segment_of(k, segments).astype(np.int64)[row]
                edge = np.flatnonzero(np.diff(part, prepend=-1))
                for a, z in zip(edge.tolist(), [*edge[1:].tolist(), len(part)], strict=True):
                    np.bitwise_or.at(maps.setdefault(int(part[a]), np.zeros(size, np.uint64)), at[a:z], mask[a:z])
        for s, bitmap in maps.items():
            yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([bitmap.tobytes()], pa.binary())], ["s", "bits"])

    own = F.expr(f"s div {max(1, BUCKETS // segments)}").alias("own")
    n = min(segments, BUCKETS, shuffle_partitions(grams.sparkSession))
    return grams.select("h", "q", own).repartition(n, "own").select("h", "q").mapInArrow(run, "s int, bits binary")


@dataclass
class Model:
    """What scoring needs. ``unigram[q]`` is the probability of a word of level q (0: not in the filter). ``filter`` is None where it is too large to be
    broadcast; then ``parts`` holds it as rows (s, bits), ``shape`` tells segments and words of each. All else is of bounded size."""

    filter: Filter | None
    parts: DataFrame | None
    shape: tuple[int, int]
    unigram: np.ndarray
    n_docs: int
    n_tokens: int
    n_types: int
    heads: np.ndarray
    head_counts: np.ndarray
    mixture: tuple = MIXTURE
    order: int = ORDER

    def shared(self) -> Model:
        """The part that is broadcast."""
        return Model(self.filter, None, self.shape, self.unigram, self.n_docs, self.n_tokens, self.n_types, self.heads, self.head_counts, self.mixture, self.order)

    def head(self, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place among the heads, whether it is one) of each word."""
        spot = np.minimum(np.searchsorted(self.heads, key), max(len(self.heads) - 1, 0))
        return spot, self.heads[spot] == key if len(self.heads) else np.zeros(len(key), bool)

    def asked(self, key: np.ndarray, before: np.ndarray, n: np.ndarray) -> np.ndarray:
        """The n-grams whose levels the scores of these tokens need: distinct, ascending."""
        return np.unique(np.concatenate([before, *grams(key, before, n, self.order)]))

    def log10(self, key: np.ndarray, before: np.ndarray, n: np.ndarray | None = None, levels: Callable[[np.ndarray], np.ndarray] | None = None) -> np.ndarray:
        """log10 P(token | tokens before) of each token of texts of ``n`` tokens (one text, if not told)."""
        n = np.array([len(key)]) if n is None else n
        asked = self.asked(key, before, n)
        found = (levels or self.filter.levels)(asked).astype(np.int64)
        own = grams(key, before, n, self.order)
        at = lambda k: np.searchsorted(asked, k)
        spot, is_head = self.head(asked)
        total = self.n_tokens + 0.5 * (self.n_types + 1)
        count = self.head_counts[spot] if len(self.heads) else np.zeros(len(asked))
        word = np.where(is_head, (count + 0.5) / total, self.unigram[found])
        p = word[at(key)]
        if self.order >= 2:
            high = np.where(is_head, count, greatest(found))[at(before)]
            high = np.where(before == _BEGIN, self.n_docs, high)
            p = self._mixed(np.minimum(least(found[at(own[1])]), high), high, p)
        whole, shorter = np.ones(len(key), bool), found[at(own[1])] if self.order >= 3 else None
        for k in range(3, self.order + 1):
            level_before, inside = _continued(shorter, n)
            whole = whole & inside & np.concatenate((whole[:1], whole[:-1]))
            longer = np.zeros(len(key), np.int64)
            longer[whole] = found[at(own[k - 1])]
            high = greatest(level_before)
            p = np.where(whole, self._mixed(np.minimum(least(longer), high), high, p), p)
            shorter = longer
        return np.log10(p)

    def _mixed(self, low: np.ndarray, high: np.ndarray, shorter: np.ndarray) -> np.ndarray:
        seen = np.maximum(low - DISCOUNT, 0)
        return sum(share * (seen + k * shorter) / (high + k) for share, k in self.mixture)


def train(
    docs: DataFrame, heads: int = HEADS, mixture: tuple = MIXTURE, order: int = ORDER, bits_per_key: int = BITS_PER_KEY, broadcast: int = BROADCAST
) -> tuple[Model, DataFrame]:
    """The model of the training documents (column text), and their exact word counts (h, c). No n-gram of up to ``order`` words is left out."""
    uni = cut(ngram_counts(docs, 1))
    levels = uni.groupBy(_level_of(F.col("c")).alias("q")).agg(F.count("*").alias("n"), F.sum("c").alias("c")).collect()
    uni_levels = {r["q"]: (r["n"], r["c"]) for r in levels}
    grams = packed(uni)
    for k in range(2, order + 1):
        grams = grams.unionByName(packed(ngram_counts(docs, k)))
    grams = cut(grams)
    segments, size = filter_shape(grams.agg(F.sum("keys")).first()[0] or 0, bits_per_key)
    parts = cut(build_filter(grams, segments, size))
    made = None
    if segments * size * 8 <= broadcast:
        made = Filter(np.zeros(segments * size, np.uint64), segments)
        found = parts.toArrow()
        for s, bits in zip(found.column("s").to_pylist(), found.column("bits"), strict=True):
            made.words[s * size : (s + 1) * size] = np.frombuffer(bits.as_buffer(), np.uint64)
    n_types, n_tokens = sum(v[0] for v in uni_levels.values()), sum(v[1] for v in uni_levels.values())
    total = n_tokens + 0.5 * (n_types + 1)
    unigram = np.zeros(LEVELS + 1)
    unigram[0] = 0.5 / total
    for q in range(1, len(unigram)):  # levels without a word are reached by false positives only
        n, c = uni_levels.get(q, (0, 0))
        unigram[q] = (c / n + 0.5) / total if n else unigram[q - 1]
    bar, taken = 1 << 30, 0
    for q in sorted(uni_levels, reverse=True):
        taken += uni_levels[q][0]
        if taken > heads:
            break
        bar = q
    head = uni.where(_level_of(F.col("c")) >= bar).select("h", "c").toArrow()
    names = head.column("h").to_numpy().view(np.uint64)
    by = np.argsort(names)
    ends = uni.where(F.col("h") == int(_END)).agg(F.max("c")).first()[0] or 0
    return Model(made, parts if made is None else None, (segments, size), unigram, int(ends), int(n_tokens), int(n_types), names[by], head.column("c").to_numpy()[by], mixture, order), uni


_SCORED = "row long, doc_id long, n_tokens long, known long, base double, score double, tail array<long>, times array<long>"


def _scored(m: Model, head_log: np.ndarray, raw: np.ndarray, at: np.ndarray, doc_id: pa.Array, row: int, levels: Callable | None = None) -> pa.RecordBatch:
    """A block's scores; the words that are not heads go on, with their number in each text."""
    key, before, n = tokens(raw, at)
    first = np.cumsum(n) - n
    score = np.add.reduceat(m.log10(key, before, n, levels), first)
    spot, is_head = m.head(key)
    base = np.zeros(len(key))
    base[is_head] = head_log[spot[is_head]]
    known = np.add.reduceat(is_head.astype(np.int64), first)
    base = np.add.reduceat(base, first)
    doc = np.repeat(np.arange(len(n)), n)[~is_head]
    tail = key[~is_head]
    order = np.lexsort((tail, doc))
    tail, doc = tail[order], doc[order]
    edge = np.flatnonzero(np.concatenate(([True], (tail[1:] != tail[:-1]) | (doc[1:] != doc[:-1])))) if len(tail) else np.zeros(0, np.int64)
    times = np.diff(np.append(edge, len(tail)))
    per_doc = np.concatenate(([0], np.cumsum(np.bincount(doc[edge], minlength=len(n))))).astype(np.int32)
    return pa.RecordBatch.from_arrays(
        [pa.array(row + np.arange(len(n))), doc_id, pa.array(n), pa.array(known), pa.array(base), pa.array(score),
         pa.ListArray.from_arrays(pa.array(per_doc), pa.array(tail[edge].view(np.int64))), pa.ListArray.from_arrays(pa.array(per_doc), pa.array(times))],
        ["row", "doc_id", "n_tokens", "known", "base", "score", "tail", "times"],
    )


def _by_broadcast(docs: DataFrame, model: Model) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(model.shared())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, row = shared.value, TaskContext.get().partitionId() << 40
        head_log = np.log10(m.head_counts + 0.5)
        for b in batches:
            raw, offsets = T.text_buffers(b.column(1))
            for lo, hi in T.blocks(offsets):
                at = offsets[lo : hi + 1]
                yield _scored(m, head_log, raw[at[0] : at[-1]], at - at[0], b.column(0).slice(lo, hi - lo), row)
                row += hi - lo

    return docs.mapInArrow(run, _SCORED)


def _by_segments(docs: DataFrame, model: Model) -> DataFrame:
    """The same rows where the filter stays in its tasks: a block of texts asks each segment for its n-grams' levels, in one row each way."""
    spark = docs.sparkSession
    shared, n, segments = spark.sparkContext.broadcast(model.shared()), shuffle_partitions(spark), model.shape[0]

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = TaskContext.get().partitionId() << 40
        for b in batches:
            _, offsets = T.text_buffers(b.column(1))
            for lo, hi in T.blocks(offsets):
                ids, texts = pa.array([b.column(0).slice(lo, hi - lo).to_pylist()], pa.list_(pa.int64())), pa.array([b.column(1).slice(lo, hi - lo).to_pylist()], pa.list_(pa.string()))
                yield pa.RecordBatch.from_arrays([pa.array([block]), ids, texts], ["block", "ids", "texts"])
                block += hi - lo

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, block in enumerate(b.column(0).to_pylist()):
                raw, at = T.text_buffers(b.column(1)[i].values)
                key = shared.value.asked(*tokens(raw, at))
                part = segment_of(key, segments)
                edge = np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1])))
                rows = [key[x:y].tobytes() for x, y in zip(edge.tolist(), [*edge[1:].tolist(), len(key)], strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(part[edge].astype(np.int32)), pa.array(np.full(len(rows), block)), pa.array(rows, pa.binary())], ["s", "block", "data"])

    def answer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, own = -1, None
        for b in batches:
            out = []
            for s, block, data in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if block < 0:
                    here, own = s, Filter(np.frombuffer(data, np.uint64), 1)
                    continue
                key = np.frombuffer(data, np.uint64)
                # the place within the segment depends on the key alone, so one segment answers for itself
                out.append((block, s, (own.levels(key) if here == s else np.zeros(len(key), np.uint8)).tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array([o[0] for o in out], pa.int64()), pa.array([o[1] for o in out], pa.int32()), pa.array([o[2] for o in out], pa.binary())], ["block", "s", "data"])

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, held, got = shared.value, None, []
        head_log = np.log10(m.head_counts + 0.5)

        def close():
            block, ids, texts = held
            raw, at = T.text_buffers(pa.array(texts, pa.string()))
            return _scored(m, head_log, raw, at, pa.array(ids, pa.int64()), block, lambda key: np.frombuffer(b"".join(got), np.uint8))

        for b in batches:
            for block, s, data, ids, texts in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if s < 0:
                    if held:
                        yield close()
                    held, got = (block, ids, texts), []
                else:
                    got.append(data)
        if held:
            yield close()

    texts = cut(docs.mapInArrow(deal, "block long, ids array<long>, texts array<string>"))
    asked = texts.select("block", "texts").mapInArrow(ask, "s int, block long, data binary")
    both = asked.unionByName(model.parts.select("s", F.lit(-1).cast("long").alias("block"), F.col("bits").alias("data")))
    told = both.repartition(n, "s").sortWithinPartitions("s", "block").mapInArrow(answer, "block long, s int, data binary")
    none = F.lit(None)
    told = told.select("block", "s", "data", none.cast("array<long>").alias("ids"), none.cast("array<string>").alias("texts"))
    told = told.unionByName(texts.select("block", F.lit(-1).alias("s"), none.cast("binary").alias("data"), "ids", "texts"))
    return told.repartition(n, "block").sortWithinPartitions("block", "s").mapInArrow(score, _SCORED)


def score_documents(docs: DataFrame, model: Model, counts: DataFrame) -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score and score of each text; null texts count as empty (the end alone).

    Every row of a repeated id has a row; an empty table gives none; other columns are ignored.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    scored = cut(_by_segments(docs, model) if model.filter is None else _by_broadcast(docs, model))
    pairs = scored.select("row", F.explode(F.arrays_zip("tail", "times")).alias("x")).select("row", F.col("x.tail").alias("h"), F.col("x.times").alias("times"))
    rare = (
        pairs.join(counts, "h", "left")
        .groupBy("row")
        .agg(F.sum(F.col("times") * F.log10(F.coalesce("c", F.lit(0)) + F.lit(0.5))).alias("more"), F.sum(F.when(F.col("c") > 0, F.col("times")).otherwise(0)).alias("more_known"))
    )
    each = F.lit(math.log10(model.n_tokens + 0.5 * (model.n_types + 1)))
    return scored.drop("tail", "times").join(rare, "row", "left").select(
        "doc_id",
        "n_tokens",
        (F.col("known") + F.coalesce("more_known", F.lit(0))).cast("long").alias("n_known"),
        F.lit(model.n_tokens).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("more", F.lit(0.0)) - F.col("n_tokens") * each).alias("base_score"),
        "score",
    )
