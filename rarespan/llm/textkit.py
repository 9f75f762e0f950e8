"""Vectorised kernels over Arrow text batches, shared by the operators of this folder.

Everything works on the UTF-8 bytes of a batch. A word is a maximal run of bytes
other than 0x20 and 0x09-0x0D; upper-case A-Z are lowered on request, nothing else
is. Batches are cut into blocks of about ``BLOCK`` bytes, so that the working set
does not follow the batch size; one longer text makes a block of its own.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BLOCK = 1 << 20
_U = np.uint64

# White space of the word pattern, and the constants of XXH64.
_SPACE = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)
_P1, _P2, _P3, _P4, _P5 = (
    _U(11400714785074694791),
    _U(14029467366897019727),
    _U(1609587929392839161),
    _U(9650029242287828579),
    _U(2870177450012600261),
)

_KEEP_CASE = np.arange(256, dtype=np.uint8)
_KEEP_CASE[list(_SPACE)] = 0x20
_LOWER = _KEEP_CASE.copy()
_LOWER[ord("A") : ord("Z") + 1] += 32

_rng = np.random.default_rng(20_240_229)
_BYTE = _rng.integers(0, 2**63, 256, dtype=np.uint64) * _U(2) + _U(1)
_TILE = _BYTE.copy()
_BYTE[0x20] = 0
_PLACE = _rng.integers(0, 2**63, 1021, dtype=np.uint64) * _U(2) + _U(1)


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and int64 offsets of a string column; nulls become empty texts."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    kind = np.int64 if pa.types.is_large_string(column.type) else np.int32
    _, offsets, data = column.buffers()
    if len(column) == 0 or offsets is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    at = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def blocks(offsets: np.ndarray, limit: int = BLOCK) -> Iterator[tuple[int, int]]:
    """Row ranges [lo, hi) whose texts take about ``limit`` bytes together."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1
        hi = min(max(hi, lo + 1), n)
        yield lo, hi
        lo = hi


@dataclass
class Words:
    """Words of some texts: ``buf`` has single spaces inside a text, word i is buf[start[i]:end[i]]."""

    buf: np.ndarray
    start: np.ndarray
    end: np.ndarray
    doc: np.ndarray
    per_doc: np.ndarray
    offsets: np.ndarray

    @property
    def first(self) -> np.ndarray:
        """Index of each text's first word."""
        return np.concatenate(([0], np.cumsum(self.per_doc)))[:-1]


def words(raw: np.ndarray, offsets: np.ndarray, lower: bool = True) -> Words:
    """Split texts into words, with each run of white space squeezed to one space."""
    n_docs = len(offsets) - 1
    if len(raw) == 0:
        none = np.zeros(0, np.int64)
        return Words(raw, none, none, none, np.zeros(n_docs, np.int64), offsets)
    buf = (_LOWER if lower else _KEEP_CASE)[raw]
    blank = buf == 0x20
    before = np.empty_like(blank)
    before[1:] = blank[:-1]
    heads = offsets[:-1][offsets[:-1] < offsets[1:]]
    before[heads] = True
    keep = ~(blank & before)
    if not keep.all():
        moved = np.concatenate(([0], np.cumsum(keep)))
        offsets = moved[offsets]
        buf, blank = buf[keep], blank[keep]
        before = np.empty_like(blank)
        before[1:] = blank[:-1]
        heads = offsets[:-1][offsets[:-1] < offsets[1:]]
        before[heads] = True
    if len(buf) == 0:
        none = np.zeros(0, np.int64)
        return Words(buf, none, none, none, np.zeros(n_docs, np.int64), offsets)
    after = np.empty_like(blank)
    after[:-1] = blank[1:]
    after[heads[1:] - 1] = True
    after[-1] = True
    start = np.flatnonzero(~blank & before)
    end = np.flatnonzero(~blank & after) + 1
    cuts = np.searchsorted(start, offsets)
    per_doc = np.diff(cuts)
    return Words(buf, start, end, np.repeat(np.arange(n_docs), per_doc), per_doc, offsets)


def mix64(h: np.ndarray) -> np.ndarray:
    """A full avalanche of 64-bit values."""
    h = h ^ (h >> _U(30))
    h = h * _U(0xBF58476D1CE4E5B9)
    h = h ^ (h >> _U(27))
    h = h * _U(0x94D049BB133111EB)
    return h ^ (h >> _U(31))


def tile_hashes(buf: np.ndarray, start: np.ndarray) -> np.ndarray:
    """64-bit hashes of the spans that begin at ``start`` and together cover ``buf``; equal for equal bytes."""
    if len(start) == 0:
        return np.zeros(0, np.uint64)
    size = np.diff(np.append(start, len(buf)))
    place = np.arange(len(buf), dtype=np.int32) - np.repeat(start.astype(np.int32), size)
    if size.max() >= 1021:
        place %= 1021
    value = _TILE[buf]
    value *= _PLACE[place]
    return mix64(np.add.reduceat(value, start) + size.astype(np.uint64) * _P3)


def word_hashes(w: Words) -> np.ndarray:
    """64-bit hash of every word; the same word has the same hash in every batch and process."""
    if len(w.start) == 0:
        return np.zeros(0, np.uint64)
    size = np.diff(np.append(w.start, len(w.buf)))
    place = np.arange(w.start[0], len(w.buf), dtype=np.int32) - np.repeat(w.start.astype(np.int32), size)
    if size.max() >= 1021:
        place %= 1021
    value = np.zeros(len(w.buf), np.uint64)
    np.multiply(_BYTE[w.buf[w.start[0] :]], _PLACE[place], out=value[w.start[0] :])
    return mix64(np.add.reduceat(value, w.start) + (w.end - w.start).astype(np.uint64) * _P3)


def pair_hashes(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    return mix64(left * _P1 + (right ^ _P2) * _P4)


def _rot(x: np.ndarray, r: int) -> np.ndarray:
    return (x << _U(r)) | (x >> _U(64 - r))


def _lane(acc, value):
    return _rot(acc + value * _P2, 31) * _P1


def xxh64_spans(buf: np.ndarray, start: np.ndarray, end: np.ndarray, seed: int = 42) -> np.ndarray:
    """XXH64 of many spans at once; spans of one length go through the rounds together."""
    out = np.empty(len(start), np.uint64)
    if len(start) == 0:
        return out
    padded = np.concatenate([buf, np.zeros(8, np.uint8)])
    by8 = np.ndarray((len(buf) + 1,), "<u8", padded, 0, (1,))
    by4 = np.ndarray((len(buf) + 1,), "<u4", padded, 0, (1,))
    size = end - start
    order = np.argsort(size.astype(np.uint16) if size.max() < 65536 else size, kind="stable")
    lengths, at = np.unique(size[order], return_index=True)
    at = np.append(at, len(order))
    zero = _U(seed)
    with np.errstate(over="ignore"):
        for k, length in enumerate(lengths.tolist()):
            rows = order[at[k] : at[k + 1]]
            s = start[rows]
            done = 0
            if length >= 32:
                a, b, c, d = (np.full(len(s), v, np.uint64) for v in (zero + _P1 + _P2, zero + _P2, zero, zero - _P1))
                while length - done >= 32:
                    a, b, c, d = (_lane(x, by8[s + (done + 8 * i)]) for i, x in enumerate((a, b, c, d)))
                    done += 32
                h = _rot(a, 1) + _rot(b, 7) + _rot(c, 12) + _rot(d, 18)
                for x in (a, b, c, d):
                    h = (h ^ _lane(_U(0), x)) * _P1 + _P4
            else:
                h = np.full(len(s), zero + _P5, np.uint64)
            h = h + _U(length)
            while length - done >= 8:
                h = _rot(h ^ _lane(_U(0), by8[s + done]), 27) * _P1 + _P4
                done += 8
            if length - done >= 4:
                h = _rot(h ^ (by4[s + done].astype(np.uint64) * _P1), 23) * _P2 + _P3
                done += 4
            while done < length:
                h = _rot(h ^ (buf[s + done].astype(np.uint64) * _P5), 11) * _P1
                done += 1
            h ^= h >> _U(33)
            h *= _P2
            h ^= h >> _U(29)
            h *= _P3
            out[rows] = h ^ (h >> _U(32))
    return out


def bit_counts(values: np.ndarray, per_doc: np.ndarray, most: int = 60_000) -> np.ndarray:
    """How often each of 64 bits is set among each text's values: an int64 matrix of texts x 64."""
    out = np.zeros((len(per_doc), 64), np.int64)
    full = np.flatnonzero(per_doc)
    if len(full) == 0:
        return out
    pieces = -(-per_doc[full] // most)
    first = np.concatenate(([0], np.cumsum(per_doc[full])[:-1]))
    head = np.concatenate(([0], np.cumsum(pieces)[:-1]))
    cut = np.repeat(first, pieces) + (np.arange(pieces.sum()) - np.repeat(head, pieces)) * most
    lanes = _U(0x0001000100010001)
    for j in range(16):
        sums = np.add.reduceat((values >> _U(j)) & lanes, cut)
        for k in range(4):
            part = ((sums >> _U(16 * k)) & _U(0xFFFF)).astype(np.int64)
            out[full, j + 16 * k] = np.add.reduceat(part, head)
    return out


def popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x)


class HashTable:
    """Long-lived map from 64-bit hashes to small integers, probed for whole arrays at once. Zero hashes are never found."""

    def __init__(self, bits: int):
        self.mask = (1 << bits) - 1
        self.keys = np.zeros(self.mask + 1, np.uint64)
        self.values = np.zeros(self.mask + 1, np.int32)
        self.count = 0

    def find(self, key: np.ndarray) -> np.ndarray:
        """Value of each key, -1 where there is none."""
        out = np.full(len(key), -1, np.int32)
        slot = (key & _U(self.mask)).astype(np.int64)
        held = self.keys[slot]
        hit = held == key
        out[hit] = self.values[slot[hit]]
        rest = np.flatnonzero(~hit & (held != 0))
        while len(rest):
            slot[rest] = (slot[rest] + 1) & self.mask
            held = self.keys[slot[rest]]
            hit = held == key[rest]
            out[rest[hit]] = self.values[slot[rest[hit]]]
            rest = rest[~hit & (held != 0)]
        return out

    def put(self, key: np.ndarray, value: np.ndarray):
        """Add distinct keys that are not there yet."""
        slot = (key & _U(self.mask)).astype(np.int64)
        rest = np.arange(len(key))
        while len(rest):
            free = rest[self.keys[slot[rest]] == 0]
            self.keys[slot[free]] = key[free]
            won = free[self.keys[slot[free]] == key[free]]
            self.values[slot[won]] = value[won]
            settled = np.zeros(len(key), bool)
            settled[won] = True
            rest = rest[~settled[rest]]
            slot[rest] = (slot[rest] + 1) & self.mask
        self.count += len(key)
