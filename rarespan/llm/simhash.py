"""Near-duplicates by SimHash, found through a covering code.

A text's fingerprint is the bit-wise majority over the hashes of its word shingles.
Two fingerprints link if they differ in at most ``RADIUS`` = 3 of 64 bits. One of their two
halves then differs in at most one bit, and each half lies within one bit of exactly
one anchor: a codeword of the perfect Hamming code on 31 bits, extended by a free bit.
So each half is *at home* at one anchor and is replicated to every anchor within two
bits (covering radius 1 plus the half's threshold 1: at most 17); linked fingerprints meet at
the anchor of either. Equal fingerprints are first folded into one, so that copies never meet.

At an anchor a breadth-first sweep emits a spanning forest of the links rather than all
pairs: a group of n near copies gives at most n - 1 edges per anchor.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rarespan.llm import textkit as T
from rarespan.llm.components import components
from rarespan.runtime import cut, shuffle_partitions

RADIUS = 3
_HALF = 31
_LOW31 = np.uint64((1 << _HALF) - 1)


def shingle_fingerprints(raw: np.ndarray, offsets: np.ndarray, shingle: int) -> np.ndarray:
    """uint64 SimHash of each text; fewer words than a shingle: of the whole sequence; none: zero."""
    out = np.zeros(len(offsets) - 1, np.uint64)
    for lo, hi in T.blocks(offsets):
        at = offsets[lo : hi + 1]
        w = T.words(raw[at[0] : at[-1]], at - at[0])
        n = np.where(w.per_doc == 0, 0, np.maximum(1, w.per_doc - shingle + 1))
        total = int(n.sum())
        if not total:
            continue
        doc = np.repeat(np.arange(hi - lo), n)
        head = w.first[doc] + np.arange(total) - np.repeat(np.concatenate(([0], np.cumsum(n)[:-1])), n)
        tail = head + np.minimum(shingle, w.per_doc[doc]) - 1
        hashes = T.xxh64_spans(w.buf, w.start[head], w.end[tail])
        bits = T.bit_counts(hashes, n) * 2 > n[:, None]
        out[lo:hi] = (bits.astype(np.uint64) << np.arange(64, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)
    return out


def fingerprints(docs: DataFrame, shingle: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp): the 64-bit fingerprint of each whole text as a signed long. Null texts count as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, offsets = T.text_buffers(b.column(1))
            fp = shingle_fingerprints(raw, offsets, shingle)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp.view(np.int64))], ["doc_id", "fp"])

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, "doc_id long, fp long")


def _syndrome(x: np.ndarray) -> np.ndarray:
    s = np.zeros(len(x), np.uint64)
    for j in range(_HALF):
        s ^= ((x >> np.uint64(j)) & np.uint64(1)) * np.uint64(j + 1)
    return s


def _flip(x: np.ndarray, place: np.ndarray) -> np.ndarray:
    """x with the bit of each 1-based place flipped; place 0 flips none."""
    return x ^ np.where(place == 0, np.uint64(0), np.uint64(1) << (np.maximum(place, np.uint64(1)) - np.uint64(1)))


def anchors(fp: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, anchor, at_home) for both halves of each fingerprint, home first."""
    rows, keys, home = [], [], []
    everyone = np.arange(len(fp))
    for half in range(2):
        part = (fp >> np.uint64(32 * half)) & np.uint64(0xFFFFFFFF)
        x, free = part & _LOW31, part >> np.uint64(31)
        s = _syndrome(x)
        tag = np.uint64(half << 32)

        def add(which, code, bit, is_home, tag=tag):
            rows.append(which)
            keys.append(tag | (bit << np.uint64(31)) | code)
            home.append(np.full(len(which), is_home))

        own = _flip(x, s)
        add(everyone, own, free, True)
        add(everyone, own, free ^ np.uint64(1), False)
        off = np.flatnonzero(s)
        for a in range(1, _HALF + 1):
            b = s[off] ^ np.uint64(a)
            pick = off[b > a]
            if len(pick):
                add(pick, _flip(_flip(x[pick], np.full(len(pick), a, np.uint64)), s[pick] ^ np.uint64(a)), free[pick], False)
    return np.concatenate(rows), np.concatenate(keys), np.concatenate(home)


def forest(values: np.ndarray, radius: int = RADIUS) -> list[tuple[int, int]]:
    """Spanning edges of the links among distinct fingerprints, by a sweep that never compares what is already reached."""
    edges: list[tuple[int, int]] = []
    rest = values
    while len(rest) > 1:
        front, rest = [rest[0]], rest[1:]
        while front and len(rest):
            x = front.pop()
            near = T.popcount(rest ^ x) <= radius
            if near.any():
                hit = rest[near]
                edges += [(int(x), int(y)) for y in hit]
                front += list(hit)
                rest = rest[~near]
    return edges


def _links(batches: Iterator[pa.RecordBatch], radius: int, small: int = 8) -> Iterator[pa.RecordBatch]:
    """Edges among rows (anchor, fp, home) sorted by anchor; a group may run over several batches."""
    held_key, held_fp = np.zeros(0, np.int64), np.zeros(0, np.uint64)

    def solve(key, fp):
        if len(key) < 2:
            return None
        starts = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
        sizes = np.diff(np.append(starts, len(key)))
        left, right = [], []
        limit = np.repeat(starts + sizes, sizes)
        tiny = np.repeat(sizes <= small, sizes)
        for d in range(1, small):
            i = np.flatnonzero((np.arange(len(key)) + d < limit) & tiny)
            if not len(i):
                break
            near = i[T.popcount(fp[i] ^ fp[i + d]) <= radius]
            left.append(fp[near])
            right.append(fp[near + d])
        for k in np.flatnonzero(sizes > small):
            found = forest(np.unique(fp[starts[k] : starts[k] + sizes[k]]), radius)
            if found:
                pair = np.array(found, np.uint64)
                left.append(pair[:, 0])
                right.append(pair[:, 1])
        if not left:
            return None
        a, b = np.concatenate(left).view(np.int64), np.concatenate(right).view(np.int64)
        return pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"]) if len(a) else None

    for b in batches:
        key = np.concatenate([held_key, b.column(0).to_numpy(zero_copy_only=False)])
        fp = np.concatenate([held_fp, b.column(1).to_numpy(zero_copy_only=False).view(np.uint64)])
        if not len(key):
            continue
        last = int(np.searchsorted(key, key[-1], "left"))
        held_key, held_fp = key[last:], fp[last:]
        out = solve(key[:last], fp[:last])
        if out is not None:
            yield out
    out = solve(held_key, held_fp)
    if out is not None:
        yield out


def near_edges(distinct: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Edges (a, b) that connect exactly the fingerprints which links at ``radius`` bits connect.

    ``distinct`` has one row per fingerprint (column fp). ``radius`` may be at most 3, what the anchors guarantee.
    """
    if not 0 <= radius <= RADIUS:
        raise ValueError("the anchors cover radii from 0 to 3")

    def replicate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = b.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            for lo in range(0, len(fp), 50_000):
                part = fp[lo : lo + 50_000]
                row, key, _ = anchors(part)
                yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(part[row].view(np.int64))], ["anchor", "fp"])

    spread = distinct.select("fp").mapInArrow(replicate, "anchor long, fp long")
    n = shuffle_partitions(distinct.sparkSession)
    return spread.repartition(n, "anchor").sortWithinPartitions("anchor").mapInArrow(lambda x: _links(x, radius), "a long, b long")


def near_duplicates(
    docs: DataFrame, shingle: int = 3, radius: int = RADIUS, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """One row per document: doc_id, fp (signed long), component_id (smallest doc_id reachable through links).

    Null and white-space-only texts have fingerprint zero and link like any other. Repeated rows and ids
    give a row each. An empty table gives an empty result. Extra columns are ignored. A null id is kept, and is never the smallest unless alone.
    """
    prints = cut(fingerprints(docs, shingle, id_col, text_col))
    distinct = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("low")))
    tree = components(near_edges(distinct, radius))
    member = distinct.join(tree.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    lowest = member.groupBy("root").agg(F.min("low").alias("component_id"))
    label = member.select("fp", "root").join(lowest, "root").select("fp", "component_id")
    return prints.join(label, "fp").select("doc_id", "fp", "component_id")
