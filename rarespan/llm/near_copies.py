"""Near copies by five-word similarity, found by an exact prefix search over the shingles themselves.

The fingerprint over shingles of ``simhash`` links what differs in a few places only. All other links are texts whose sets of five-word shingles have a
similarity of ``SIMILARITY`` or more. Two such sets share most of their shingles, so however all shingles are ordered, the first fifth (and one) of the one meets
the first fifth of the other. Each set posts its first fifth; where postings meet, pairs of fitting size whose ``BITS`` sketch bits are not too far apart are candidates.
The order only decides how much is compared, never what is found: shingles that many texts share come last, rarer ones first.
Candidates are gathered into clusters, and inside a cluster texts link if the similarity counted on their whole sets is at least ``SIMILARITY``; large
clusters are dealt over tasks in parts. Links at 3 bits of the shingle fingerprint hold as they are.

A group of n near copies gives a spanning forest, never all pairs. Texts of equal fingerprint and equal set are one node throughout.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rarespan.llm import textkit as T
from rarespan.llm.components import components
from rarespan.llm.simhash import RADIUS, anchors, shingle_fingerprints
from rarespan.runtime import cut, shuffle_partitions

BINS = 128
BITS = 128
FAR = 32  # of BITS: sets of similarity 0.8 differ in 12.8 on average, beyond 32 about once in a million
COMMON = 16  # sampled texts that share a shingle before it moves to the end of the order
COMMON_KEPT = 1 << 17
SAMPLED = 40_000  # texts among which common shingles are looked for
SHINGLE = 5
SIMILARITY = 0.8
BLOCK_KEYS = 1 << 14  # shingles of a part of a large cluster
REST_KEYS = 1 << 19  # shingles of a block of what is compared with all of a large cluster
STARS = 2  # passes over the parts before blocks are compared
_EMPTY = np.uint32(0xFFFFFFFF)


def shingle_sets(w: T.Words, n_docs: int, shingle: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(sorted distinct shingle hashes of all texts, end to end; size of each text's set). A text shorter than a shingle is one shingle."""
    if not len(w.start):
        return np.zeros(0, np.uint64), np.zeros(n_docs, np.int64)
    h = T.word_hashes(w)
    n = np.where(w.per_doc == 0, 0, np.maximum(1, w.per_doc - shingle + 1))
    run = h.copy()
    for k in range(1, shingle):
        run[:-k] = T.pair_hashes(run[:-k], h[k:])
    doc = np.repeat(np.arange(n_docs), n)
    head = w.first[doc] + np.arange(len(doc)) - np.repeat(np.concatenate(([0], np.cumsum(n)[:-1])), n)
    key = run[head]
    for d in np.flatnonzero((w.per_doc > 0) & (w.per_doc < shingle)):  # the whole sequence is the only shingle
        key[np.searchsorted(doc, d)] = T.mix64(h[w.first[d] : w.first[d] + w.per_doc[d]] * np.arange(1, 2 * w.per_doc[d], 2, dtype=np.uint64)).sum(dtype=np.uint64)
    key = T.mix64(key)
    order = np.lexsort((key, doc))
    key, doc = key[order], doc[order]
    first = np.concatenate(([True], (key[1:] != key[:-1]) | (doc[1:] != doc[:-1])))
    return key[first], np.bincount(doc[first], minlength=n_docs)


def sketches(key: np.ndarray, size: np.ndarray, bins: int = BINS) -> np.ndarray:
    """uint32 matrix of texts x bins: the smallest shingle hash of each bin, all ones where a bin is empty."""
    out = np.full((len(size), bins), _EMPTY)
    value = np.minimum((key & np.uint64(0xFFFFFFFF)).astype(np.uint32), np.uint32(0xFFFFFFFE))
    np.minimum.at(out, (np.repeat(np.arange(len(size)), size), (key >> np.uint64(40)).astype(np.int64) % bins), value)
    return out


def sketch_bits(sketch: np.ndarray) -> np.ndarray:
    """uint64 matrix of texts x 2: one bit of each bin's smallest hash."""
    one = (T.mix64(sketch.astype(np.uint64)) & np.uint64(1)).reshape(len(sketch), -1, 64)
    return (one << np.arange(64, dtype=np.uint64)).sum(axis=2, dtype=np.uint64)


def alike(keys: list[np.ndarray]):
    """near(i, rest) on a list of sorted sets: whether the similarity of i and each of rest is ``SIMILARITY`` or more, in whole numbers."""
    size = np.array([len(k) for k in keys], np.int64)
    _, term = np.unique(np.concatenate(keys), return_inverse=True)
    ends = np.concatenate(([0], np.cumsum(size)))
    mark = np.zeros(int(term.max(initial=0)) + 1, bool)

    def near(i: int, rest: np.ndarray) -> np.ndarray:
        fit = (5 * size[rest] >= 4 * size[i]) & (5 * size[i] >= 4 * size[rest]) & (size[rest] > 0)
        out = np.zeros(len(rest), bool)
        some = rest[fit]
        if len(some) and size[i]:
            mark[term[ends[i] : ends[i + 1]]] = True
            n = size[some]
            first = np.cumsum(n) - n
            hits = mark[term[np.repeat(ends[some] - first, n) + np.arange(int(n.sum()))]]
            both = np.add.reduceat(hits.astype(np.int64), first)
            mark[term[ends[i] : ends[i + 1]]] = False
            out[fit] = 9 * both >= 4 * (size[i] + n)  # both / (union) >= 4 / 5
        return out

    return near


def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, sig, fp, sketch, keys) of (doc_id, text), a block at a time; further columns follow as they are."""
    for b in batches:
        raw, offsets = T.text_buffers(b.column(1))
        for lo, hi in T.blocks(offsets):
            at = offsets[lo : hi + 1] - offsets[lo]
            part = raw[offsets[lo] : offsets[hi]]
            fp = shingle_fingerprints(part, at, 3)
            key, size = shingle_sets(T.words(part, at), hi - lo)
            ends = np.concatenate(([0], np.cumsum(size)))
            total = np.concatenate((np.zeros(1, np.uint64), np.cumsum(T.mix64(key ^ np.uint64(0x9E3779B97F4A7C15)), dtype=np.uint64)))
            sig = T.pair_hashes(T.pair_hashes(fp, total[ends[1:]] - total[ends[:-1]]), size.astype(np.uint64))
            sets = pa.array([key[i:j].tobytes() for i, j in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)], pa.binary())
            yield pa.RecordBatch.from_arrays(
                [b.column(0).slice(lo, hi - lo), pa.array(sig.view(np.int64)), pa.array(fp.view(np.int64)), pa.array([r.tobytes() for r in sketches(key, size)], pa.binary()), sets, *(c.slice(lo, hi - lo) for c in b.columns[2:])],
                ["doc_id", "sig", "fp", "sketch", "keys", *b.schema.names[2:]],
            )


def signatures(docs: DataFrame) -> DataFrame:
    """(doc_id, sig, fp, sketch, keys): fp over 3-word shingles, keys the sorted set of five-word ones; sig is equal where fp and the set are."""
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_sign, "doc_id long, sig long, fp long, sketch binary, keys binary")


def _in_one_pass(sets: DataFrame, step, schema: str) -> DataFrame:
    """``step`` over batches (node, sketch, keys); of a table of texts these never leave the Python worker, since sets are larger than texts."""
    if "keys" in sets.columns:
        return sets.select("node", "sketch", "keys").mapInArrow(step, schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from step(pa.RecordBatch.from_arrays([b.column(1), b.column(3), b.column(4)], ["node", "sketch", "keys"]) for b in _sign(batches))

    return sets.select("doc_id", "text").mapInArrow(run, schema)


def common_shingles(sets: DataFrame, least: int = COMMON, most: int = COMMON_KEPT, sampled: int = SAMPLED) -> tuple[np.ndarray, np.ndarray]:
    """(low halves of the shingle hashes that many of (node, sketch, keys) or (doc_id, text) share, sorted; in how many). It steers the order alone, so a sample and a limit do no harm."""
    n = sets.count()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for b in batches:
            for v in b.column(2):
                held.append(np.frombuffer(v.as_py(), np.uint64).astype(np.uint32))
                size += len(held[-1])
                if size > 500_000:
                    k, c = np.unique(np.concatenate(held), return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(k.view(np.int32)), pa.array(c.astype(np.int32))], ["k", "c"])
                    held, size = [], 0
        if size:
            k, c = np.unique(np.concatenate(held), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(k.view(np.int32)), pa.array(c.astype(np.int32))], ["k", "c"])

    if n > sampled:
        sets = sets.where(F.pmod(F.xxhash64(sets.columns[-1]), F.lit(1_000_000)) < int(1_000_000 * sampled / n))
    found = _in_one_pass(sets, run, "k int, c int").groupBy("k").agg(F.sum("c").alias("c")).where(F.col("c") >= least)
    rows = found.orderBy(F.desc("c"), "k").limit(most).collect()
    k = np.array([r["k"] for r in rows], np.int32).view(np.uint32)
    order = np.argsort(k)
    return k[order], np.array([r["c"] for r in rows], np.int64)[order]


def prefix(keys: np.ndarray, common: np.ndarray, times: np.ndarray) -> np.ndarray:
    """The part of one sorted set that meets every set of similarity 0.8 or more: all but ceil(0.8 size) - 1 shingles, the rarest first."""
    short = len(keys) - -(-4 * len(keys) // 5) + 1
    low = keys.astype(np.uint32)
    if not len(common):
        return low[:short]
    at = np.minimum(np.searchsorted(common, low), len(common) - 1)
    known = np.where(common[at] == low, times[at], 0)
    return low[np.argsort(known, kind="stable")[:short]]


def shingle_edges(sets: DataFrame, small: int = 8) -> DataFrame:
    """Candidate edges (a, b) of (node, sketch, keys) or of texts (doc_id, text): sets that share a shingle of both prefixes, fit in size and lie within FAR sketch bits; a spanning forest a shingle.

    No pair of similarity 0.8 or more stays apart, but for the chance named at FAR.
    """
    common, times = common_shingles(sets)
    shared = sets.sparkSession.sparkContext.broadcast((common, times))

    def post(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            _, first = np.unique(b.column(0).to_numpy(zero_copy_only=False), return_index=True)
            b = b.take(pa.array(first))
            node = b.column(0).to_numpy(zero_copy_only=False)
            for lo in range(0, len(node), 500):
                some = [np.frombuffer(v.as_py(), np.uint64) for v in b.column(2).slice(lo, 500)]
                if not some:
                    continue
                bits = sketch_bits(np.stack([np.frombuffer(v.as_py(), np.uint32) for v in b.column(1).slice(lo, 500)])).view(np.int64)
                heads = [prefix(k, *shared.value) if len(k) else np.zeros(0, np.uint32) for k in some]
                row = np.repeat(np.arange(len(some)), [len(k) for k in heads])
                size = np.array([len(k) for k in some], np.int32)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.concatenate(heads).view(np.int32)), pa.array(node[lo : lo + 500][row]), pa.array(size[row]), pa.array(bits[row, 0]), pa.array(bits[row, 1])], ["k", "node", "size", "b0", "b1"]
                )

    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, node, size, b0, b1 in _runs(batches):
            order = np.lexsort((node, key))
            order = order[np.concatenate(([True], (np.diff(key[order]) != 0) | (np.diff(node[order]) != 0)))]  # repeated texts post alike
            key, node, size, b0, b1 = (c[order] for c in (key, node, size, b0, b1))
            b0, b1, size = b0.view(np.uint64), b1.view(np.uint64), size.astype(np.int64)

            def near(i, j):
                fit = (5 * size[j] >= 4 * size[i]) & (5 * size[i] >= 4 * size[j])
                return fit & (T.popcount(b0[i] ^ b0[j]).astype(np.int64) + T.popcount(b1[i] ^ b1[j]) <= FAR)

            starts = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
            sizes = np.diff(np.append(starts, len(key)))
            limit, tiny = np.repeat(starts + sizes, sizes), np.repeat(sizes <= small, sizes)
            pairs = []
            for d in range(1, small):
                i = np.flatnonzero((np.arange(len(key)) + d < limit) & tiny)
                if not len(i):
                    break
                i = i[near(i, i + d)]
                pairs.append((node[i], node[i + d]))
            for k in np.flatnonzero(sizes > small):
                pairs += _sweep(node[starts[k] : starts[k] + sizes[k]], lambda i, rest, s=starts[k]: near(s + np.array([i]), s + rest))
            found = _distinct(pairs)
            yield from _edges(found)

    n = shuffle_partitions(sets.sparkSession)
    posted = _in_one_pass(sets, post, "k int, node long, size int, b0 long, b1 long")
    return posted.repartition(n, "k").sortWithinPartitions("k").mapInArrow(link, "a long, b long")


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, ...]]:
    """Whole groups of rows sorted by their first column, joined over batches: (key, other columns ..)."""
    held: list | None = None
    for b in batches:
        cols = [np.array(c.to_pylist(), object) if pa.types.is_binary(c.type) else c.to_numpy(zero_copy_only=False) for c in b.columns]
        if held is not None:
            cols = [np.concatenate(p) for p in zip(held, cols, strict=True)]
        if not len(cols[0]):
            continue
        last = int(np.searchsorted(cols[0], cols[0][-1], "left"))
        held = [c[last:] for c in cols]
        if last:
            yield tuple(c[:last] for c in cols)
    if held is not None and len(held[0]):
        yield tuple(held)


def _distinct(pairs: list[tuple[np.ndarray, np.ndarray]]) -> list[tuple[np.ndarray, np.ndarray]]:
    if not pairs:
        return pairs
    a, b = np.concatenate([p[0] for p in pairs]), np.concatenate([p[1] for p in pairs])
    both = np.unique(np.column_stack([np.minimum(a, b), np.maximum(a, b)]), axis=0)
    return [(both[:, 0].copy(), both[:, 1].copy())]


def _edges(pairs: list[tuple[np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
    if pairs:
        a, b = np.concatenate([p[0] for p in pairs]), np.concatenate([p[1] for p in pairs])
        if len(a):
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])


def _sweep(nodes: np.ndarray, near) -> list[tuple[np.ndarray, np.ndarray]]:
    """Spanning edges of one group: what is reached is not compared again. ``near(i, rest)`` tells which of ``rest`` are linked to i."""
    out, rest = [], np.arange(len(nodes))
    while len(rest) > 1:
        front, rest = [int(rest[0])], rest[1:]
        while front and len(rest):
            i = front.pop()
            hit = near(i, rest)
            if hit.any():
                got = rest[hit]
                out.append((np.full(len(got), nodes[i]), nodes[got]))
                front += got.tolist()
                rest = rest[~hit]
    return out


def fingerprint_edges(rows: DataFrame, small: int = 8) -> DataFrame:
    """Edges (a, b) among nodes of (node, fp) rows whose fingerprints differ in at most 3 bits, a spanning forest an anchor."""

    def replicate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            node, fp = (b.column(i).to_numpy(zero_copy_only=False) for i in range(2))
            for lo in range(0, len(fp), 50_000):
                row, key, _ = anchors(fp[lo : lo + 50_000].view(np.uint64))
                yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(fp[lo:][row]), pa.array(node[lo:][row])], ["anchor", "fp", "node"])

    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, fp, node in _runs(batches):
            fp = fp.view(np.uint64)
            starts = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
            sizes = np.diff(np.append(starts, len(key)))
            limit, tiny = np.repeat(starts + sizes, sizes), np.repeat(sizes <= small, sizes)
            pairs = []
            for d in range(1, small):
                i = np.flatnonzero((np.arange(len(key)) + d < limit) & tiny)
                if not len(i):
                    break
                i = i[T.popcount(fp[i] ^ fp[i + d]) <= RADIUS]
                pairs.append((node[i], node[i + d]))
            for k in np.flatnonzero(sizes > small):
                own = slice(starts[k], starts[k] + sizes[k])
                f = fp[own]
                pairs += _sweep(node[own], lambda i, rest, f=f: T.popcount(f[rest] ^ f[i]) <= RADIUS)
            yield from _edges(pairs)

    n = shuffle_partitions(rows.sparkSession)
    spread = rows.mapInArrow(replicate, "anchor long, fp long, node long")
    return spread.repartition(n, "anchor").sortWithinPartitions("anchor").mapInArrow(link, "a long, b long")


def _by_key(columns: list[np.ndarray]) -> Iterator[slice]:
    """Slices of equal first column."""
    starts = np.flatnonzero(np.concatenate(([True], columns[0][1:] != columns[0][:-1]))).tolist()
    yield from (slice(x, y) for x, y in zip(starts, [*starts[1:], len(columns[0])], strict=True))


def _small_clusters(members: DataFrame) -> DataFrame:
    """Edges within clusters (root, node, keys) that fit a task each."""

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, node, sets in _runs(batches):
            pairs = []
            for own in _by_key([key]):
                names, first = np.unique(node[own], return_index=True)
                if len(names) > 1:
                    pairs += _sweep(names, alike([np.frombuffer(sets[own][i], np.uint64) for i in first]))
            yield from _edges(pairs)

    n = shuffle_partitions(members.sparkSession)
    return members.select("root", "node", "keys").repartition(n, "root").sortWithinPartitions("root").mapInArrow(check, "a long, b long")


def _centres(members: DataFrame) -> DataFrame:
    """(root, c0, c1): the sketch bits that most texts of a cluster (root, b0, b1) have. Bits are counted on the map side, so a large cluster is a few rows."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            root, b0, b1 = (c.to_numpy(zero_copy_only=False) for c in b.columns)
            names, at = np.unique(root, return_inverse=True)
            ones = np.zeros((len(names), BITS), np.int64)
            for i in range(BITS):
                bit = (b0 if i < 64 else b1).view(np.uint64) >> np.uint64(i % 64) & np.uint64(1)
                ones[:, i] = np.bincount(at, bit, len(names))
            each = np.repeat(np.bincount(at, minlength=len(names)), BITS)
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(names, BITS)), pa.array(np.tile(np.arange(BITS, dtype=np.int32), len(names))), pa.array(ones.ravel()), pa.array(each)], ["root", "i", "ones", "n"])

    bits = members.select("root", "b0", "b1").mapInArrow(count, "root long, i int, ones long, n long").groupBy("root", "i").agg((2 * F.sum("ones") > F.sum("n")).alias("set"))
    value = lambda half: F.bit_or(F.when(F.col("set") & (F.expr("i div 64") == half), F.expr("shiftleft(1L, i % 64)")).otherwise(0))
    return bits.groupBy("root").agg(value(0).alias("c0"), value(1).alias("c1"))


def _stars(members: DataFrame, left: DataFrame) -> DataFrame:
    """Edges from one text of each cluster, the one closest to the centre of those in ``left``, to all that are alike; one pass over ``members``.

    members: root, node, keys, b0, b1, k (parts of the cluster), part. left: rows of them. The chosen set is sent to each part, so a task holds one set at a time.
    """
    spread = lambda one: one.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
    k = members.select("root", "k").distinct()
    away = F.bit_count(F.col("b0").bitwiseXOR(F.col("c0"))) + F.bit_count(F.col("b1").bitwiseXOR(F.col("c1")))
    far = left.join(spread(_centres(left).join(k, "root")).drop("k"), ["root", "part"]).select("root", "node", away.alias("far"))
    chosen = far.groupBy("root").agg(F.min_by("node", F.struct("far", F.xxhash64("node"), "node")).alias("node"))
    hub = spread(members.join(chosen, ["root", "node"], "left_semi").dropDuplicates(["root"]).select("root", "node", "keys", "k")).drop("k")

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, name, own = None, 0, np.zeros(0, np.uint64)
        for b in batches:
            found = []
            for root, part, other, node, v in zip(*(c if pa.types.is_binary(c.type) else c.to_pylist() for c in b.columns), strict=True):
                keys = np.frombuffer(v.as_buffer(), np.uint64)
                if not other:
                    here, name, own = (root, part), node, keys.copy()
                elif here == (root, part) and node != name and 5 * min(len(own), len(keys)) >= 4 * max(len(own), len(keys)):
                    both = int((own[np.minimum(np.searchsorted(own, keys), len(own) - 1)] == keys).sum()) if len(own) else 0
                    if both and 9 * both >= 4 * (len(own) + len(keys)):
                        found.append((name, node))
            yield pa.RecordBatch.from_arrays([pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int64())], ["a", "b"])

    rows = members.select("root", "part", F.lit(1).alias("other"), "node", "keys").unionByName(hub.withColumn("other", F.lit(0)))
    n = shuffle_partitions(members.sparkSession)
    return rows.repartition(n, "root", "part").sortWithinPartitions("root", "part", "other").mapInArrow(check, "a long, b long")


def _rest(members: DataFrame, linked: DataFrame) -> DataFrame:
    """Edges between a large cluster's texts that ``linked`` (node, root) leaves apart: those outside its largest group meet all others, block by block."""

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, node, group, out, sets in _runs(batches):
            pairs = []
            for own in _by_key([key]):
                names, first = np.unique(node[own], return_index=True)
                near, label, loose = alike([np.frombuffer(sets[own][i], np.uint64) for i in first]), group[own][first], np.flatnonzero(np.isin(names, node[own][out[own] == 1]))
                for i in loose.tolist():
                    other = np.flatnonzero(label != label[i])
                    hit = other[near(i, other)] if len(other) else other
                    if len(hit):
                        pairs.append((np.full(len(hit), names[i]), names[hit]))
                        label = np.where(np.isin(label, label[hit]), label[i], label)
            yield from _edges(pairs)

    blocks = lambda size: F.greatest(F.lit(1), F.ceil(size / F.lit(8.0 * REST_KEYS))).cast("int")
    named = members.join(linked.withColumnRenamed("root", "grp"), "node", "left").withColumn("grp", F.coalesce("grp", "node"))
    groups = named.groupBy("root", "grp").agg(F.count("*").alias("n"), F.sum(F.length("keys")).alias("bytes"))
    most = groups.groupBy("root").agg(F.max_by("grp", F.struct("n", "grp")).alias("main"), F.count("*").alias("groups"), F.sum("bytes").alias("all"), F.max_by("bytes", F.struct("n", "grp")).alias("held"))
    most = most.where("groups > 1").select("root", "main", blocks(F.col("all") - F.col("held")).alias("j"), blocks(F.col("all")).alias("k"))
    named = named.drop("k").join(most, "root").withColumn("part", F.pmod(F.xxhash64("node"), "k").cast("int")).withColumn("out", (F.col("grp") != F.col("main")).cast("int"))
    named = named.withColumn("block", F.pmod(F.xxhash64("node", F.lit(1)), F.col("j")).cast("int"))
    row = ["root", "node", "grp", "keys"]
    every = named.select(*row, F.lit(0).alias("out"), F.col("part").alias("x"), F.explode(F.sequence(F.lit(0), F.col("j") - 1)).alias("y"))
    loose = named.where("out = 1").select(*row, "out", F.explode(F.sequence(F.lit(0), F.col("k") - 1)).alias("x"), F.col("block").alias("y"))
    n = shuffle_partitions(members.sparkSession)
    dealt = every.unionByName(loose).select(F.xxhash64("root", "x", "y").alias("task"), "node", "grp", "out", "keys")
    return dealt.repartition(n, "task").sortWithinPartitions("task").mapInArrow(check, "a long, b long")


def verified_edges(members: DataFrame, block: int = BLOCK_KEYS, stars: int = STARS) -> DataFrame:
    """Edges among nodes of one cluster (root, node, keys) whose sets have the least similarity; they connect what all such pairs connect.

    A cluster of up to ``block`` shingles is one task's work. A larger one is dealt into parts. In each of ``stars`` passes one text, the closest to the centre of what
    is not linked yet, is compared with every part; copies of one text mostly end there. What is still apart from the largest group meets all others, block by block.
    """

    def bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, len(b), 500):
                some = b.slice(lo, 500)
                sets = [np.frombuffer(v.as_buffer(), np.uint64) for v in some.column(2)]
                two = sketch_bits(sketches(np.concatenate(sets), np.array([len(v) for v in sets]))).view(np.int64)
                yield pa.RecordBatch.from_arrays([*some.columns, pa.array(two[:, 0].copy()), pa.array(two[:, 1].copy())], [*some.schema.names, "b0", "b1"])

    members = cut(members.select("root", "node", "keys"))
    parts = cut(members.groupBy("root").agg(F.ceil(F.sum(F.length("keys")) / F.lit(8.0 * block)).cast("int").alias("k")))
    large = parts.where("k > 1")
    found = _small_clusters(members.join(large, "root", "left_anti"))
    if large.isEmpty():
        return found
    rows = members.join(large, "root").select("root", "node", "keys", "k", F.pmod(F.xxhash64("node"), "k").cast("int").alias("part"))
    rows = cut(rows.mapInArrow(bits, "root long, node long, keys binary, k int, part int, b0 long, b1 long"))
    known, left = None, rows
    for _ in range(stars):
        edges = _stars(rows, left.select("root", "node", "part", "b0", "b1"))
        known = cut(edges if known is None else known.unionByName(edges))
        linked = components(known)
        left = rows.join(linked, "node", "left_anti")
    return found.unionByName(known).unionByName(_rest(rows, linked))


def near_copies(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, component_id, the smallest id among the documents reachable through links, text_hash (XXH64 of the text) and
    stays: whether the row has its component's smallest id and, among texts of that id, the smallest hash.

    Null and white-space-only texts are alike. Repeated rows give a row each, and so do different texts under one id; an empty table gives none; other columns are ignored.
    Rows without an id are linked like all others. A null id comes after all ids: it is a component's, and stays, only where no row of the component has one.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")

    def names(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from (b.select([0, 1, 2, 5]) for b in _sign(batches))

    found = cut(docs.withColumn("text_hash", F.xxhash64("text")).mapInArrow(names, "doc_id long, sig long, fp long, text_hash long"))
    own = F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "text_hash")
    label = cut(found.groupBy(F.col("sig").alias("node")).agg(F.min(own).alias("first"), F.first("fp").alias("fp")))
    sure = cut(fingerprint_edges(label.select("node", "fp")))
    clusters = components(sure.unionByName(shingle_edges(docs)))
    chosen = cut(clusters.join(label.select("node", "first.*"), "node"))  # sets are read again from the texts: they are larger than the texts, so never kept
    again = docs.where("doc_id is not null").join(chosen.select("doc_id").distinct(), "doc_id", "left_semi")
    nameless = docs.where("doc_id is null").withColumn("text_hash", F.xxhash64("text")).join(chosen.where("nameless").select("text_hash").distinct(), "text_hash", "left_semi")
    again = again.unionByName(nameless.groupBy("text_hash").agg(F.first("text").alias("text")).select(F.lit(None).cast("long").alias("doc_id"), "text"))
    again = signatures(again).select(F.col("sig").alias("node"), F.col("doc_id").alias("low"), "keys")
    chosen = chosen.select(F.col("node").alias("name"), "doc_id", "root")
    members = again.join(chosen, (F.col("node") == F.col("name")) & F.col("low").eqNullSafe(F.col("doc_id"))).select("root", "node", "keys")
    tree = components(sure.unionByName(verified_edges(members)))
    label = label.select("node", "first").join(tree, "node", "left").withColumn("root", F.coalesce("root", "node"))
    lowest = label.groupBy("root").agg(F.min("first").alias("lowest"))
    of = label.join(lowest, "root").select(F.col("node").alias("sig"), "lowest")
    stays = own.eqNullSafe(F.col("lowest"))
    return found.select("doc_id", "text_hash", "sig").join(of, "sig").select("doc_id", F.col("lowest.doc_id").alias("component_id"), "text_hash", stays.alias("stays"))
