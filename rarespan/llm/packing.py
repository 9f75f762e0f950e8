"""Packing token sequences into fixed windows: bounded-space, online, best fit.

Each partition keeps ``open_windows`` windows open. A piece goes into the open window that
it fills best. When none has room, the fullest one is filled up with the head of the piece and
emitted, and the rest of the piece is placed again; so what a partition emits is full. At its
end a partition merges its open windows; at most one stays unfilled. These last windows of up to
``MERGE`` partitions are merged by one small task, and the final one of each such task is
cut into sequences whose lengths are powers of two, which need no padding.

Token ids never leave the worker that makes them, save those of the unfilled windows (or on request).
"""

from __future__ import annotations

import json
import string
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rarespan.llm import textkit as T
from rarespan.runtime import cut

WINDOW = 2048
OPEN_WINDOWS = 16
END_ID = 1
MERGE = 256
_SHIFT = 31
_PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, part long, ids binary"
_COLUMNS = [c.split()[0] for c in _PIECE.split(", ")]


# The pre-tokenizer's pattern of byte-level vocabularies (a fixed value).
_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def _visible_bytes() -> dict[int, str]:
    """Each byte's character in byte-level vocabularies: itself if printable, else one from 256 upwards in turn."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    moved = [b for b in range(256) if b not in plain]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(moved)}


class UnitEncoder:
    """Token ids of whole texts, with each distinct unit encoded once.

    A unit starts at a white-space byte that follows a visible character. The pre-tokenizer of
    byte-level vocabularies always cuts there, so the ids of a text are those of its units, joined.
    A unit that holds an added token of the vocabulary goes through the whole tokenizer.
    Units of up to ``longest`` bytes are remembered by a 64-bit hash; the memory is cleared at half of 2**bits units.
    """

    def __init__(self, tokenizer_json: str, bits: int = 21, longest: int = 64):
        import regex
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_str(tokenizer_json)
        added = json.loads(tokenizer_json).get("added_tokens") or []
        self.special = [t["content"] for t in added]
        if any(t["lstrip"] or t["rstrip"] or t["single_word"] or set(t["content"]) & set(string.whitespace) for t in added):
            raise ValueError("added tokens that reach over white space can't be told unit by unit")
        self.model, self.pieces, self.visible = self.tokenizer.model, regex.compile(_PATTERN).findall, _visible_bytes()
        self.bits, self.longest = bits, longest
        self._clear()

    def _clear(self, needed: int = 0):
        """Forget everything; the new table has room for at least the units of the block at hand."""
        self.table = T.HashTable(max(self.bits, (4 * needed).bit_length()))
        self.first = np.zeros(1 << 16, np.int64)
        self.size = np.zeros(1 << 16, np.int32)
        self.pool = np.zeros(1 << 18, np.int32)
        self.used = 0

    def _remember(self, keys: np.ndarray, encoded: list[list[int]]) -> np.ndarray:
        n, sizes = self.table.count, np.fromiter(map(len, encoded), np.int32, len(encoded))
        total = int(sizes.sum())
        while n + len(keys) > len(self.first):
            self.first, self.size = np.resize(self.first, 2 * len(self.first)), np.resize(self.size, 2 * len(self.size))
        while self.used + total > len(self.pool):
            self.pool = np.resize(self.pool, 2 * len(self.pool))
        self.first[n : n + len(keys)] = self.used + np.concatenate(([0], np.cumsum(sizes)[:-1]))
        self.size[n : n + len(keys)] = sizes
        self.pool[self.used : self.used + total] = np.fromiter((x for ids in encoded for x in ids), np.int32, total)
        self.used += total
        at = np.arange(n, n + len(keys), dtype=np.int32)
        self.table.put(keys, at)
        return at

    def _whole(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def _encode(self, texts: list[str]) -> list[list[int]]:
        """Latin units go piece by piece straight to the merge model; the others through the whole tokenizer."""
        seen: dict[str, list[int]] = {}
        model, visible, pieces = self.model.tokenize, self.visible, self.pieces
        out = []
        for text in texts:
            if not text.isascii() and max(text) >= "\u0250" or any(t in text for t in self.special):
                out.append(self._whole(text))
                continue
            ids: list[int] = []
            for piece in pieces(text):
                known = seen.get(piece)
                if known is None:
                    known = [t.id for t in model(piece.encode().decode("latin-1").translate(visible))]
                    seen[piece] = known
                ids += known
            out.append(ids)
        return out

    @staticmethod
    def unit_starts(buf: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        cut = np.zeros(len(buf), bool)
        space = (buf == 0x20) | ((buf >= 9) & (buf <= 13))
        cut[1:] = space[1:] & (buf[:-1] > 0x20)
        wide = np.flatnonzero(cut[3:] & (buf[2:-1] >= 0x80)) + 3
        if len(wide):
            a, b, c = buf[wide - 3], buf[wide - 2], buf[wide - 1]
            blank = (b == 0xC2) & ((c == 0x85) | (c == 0xA0))
            blank |= (a == 0xE1) & (b == 0x9A) & (c == 0x80)
            blank |= (a == 0xE2) & (b == 0x80) & ((c <= 0x8A) | (c == 0xA8) | (c == 0xA9) | (c == 0xAF))
            blank |= (a == 0xE2) & (b == 0x81) & (c == 0x9F)
            blank |= (a == 0xE3) & (b == 0x80) & (c == 0x80)
            cut[wide[blank]] = False
        cut[: min(3, len(cut))] &= buf[: min(3, len(cut))] < 0x80
        if len(buf) > 2 and buf[0] == 0xC2:
            cut[2] = False
        cut[offsets[:-1][offsets[:-1] < offsets[1:]]] = True
        return np.flatnonzero(cut)

    def __call__(self, raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, ids per text) of one block of texts."""
        if len(raw) == 0:
            return np.zeros(0, np.int32), np.zeros(len(offsets) - 1, np.int64)
        start = self.unit_starts(raw, offsets)
        end = np.append(start[1:], len(raw))
        key = T.tile_hashes(raw, start)
        key[key == 0] = 1
        where = self.table.find(key)
        miss = np.flatnonzero(where < 0)
        long_units: dict[int, np.ndarray] = {}
        if len(miss):
            unique, sample, back = np.unique(key[miss], return_index=True, return_inverse=True)
            if self.table.count + len(unique) > self.table.mask // 2:
                self._clear(len(unique))
                where[:] = -1
                miss = np.arange(len(key))
                unique, sample, back = np.unique(key, return_index=True, return_inverse=True)
            s, e = start[miss[sample]], end[miss[sample]]
            short = np.flatnonzero(e - s <= self.longest)
            data = raw.tobytes()
            texts = [data[i:j].decode("utf-8", "replace") for i, j in zip(s[short].tolist(), e[short].tolist(), strict=True)]
            place = np.full(len(unique), -1, np.int32)
            if texts:
                place[short] = self._remember(unique[short], self._encode(texts))
            where[miss] = place[back]
            for i in np.flatnonzero(where < 0).tolist():
                long_units[i] = np.array(self._whole(data[start[i] : end[i]].decode("utf-8", "replace")), np.int32)
        per_unit = self.size[where].astype(np.int64)
        for i, ids in long_units.items():
            per_unit[i] = len(ids)
        first = np.concatenate(([0], np.cumsum(per_unit)))
        source = np.repeat(self.first[where] - first[:-1], per_unit) + np.arange(first[-1])
        for i in long_units:
            source[first[i] : first[i + 1]] = 0
        ids = self.pool[source]
        for i, own in long_units.items():
            ids[first[i] : first[i + 1]] = own
        return ids, np.diff(first[np.searchsorted(start, offsets)])


class Packer:
    """Bounded-space best fit. ``emit`` gets (sequence number, pieces) of each closed window; a piece is (doc, start, ids, doc tokens)."""

    def __init__(self, window: int, slots: int, emit):
        self.window, self.slots, self.emit = window, slots, emit
        self.open: list[list] = []
        self.room: list[int] = []
        self.n = 0

    def close(self, pieces: list):
        self.emit(self.n, pieces)
        self.n += 1

    def add(self, doc, start: int, ids: np.ndarray, total: int):
        while len(ids) >= self.window:
            self.close([(doc, start, ids[: self.window], total)])
            start, ids = start + self.window, ids[self.window :]
        while len(ids):
            best = min((r, i) for i, r in enumerate(self.room) if r >= len(ids)) if any(r >= len(ids) for r in self.room) else None
            if best is not None:
                i = best[1]
                self.open[i].append((doc, start, ids, total))
                self.room[i] -= len(ids)
                if not self.room[i]:
                    self.close(self.open.pop(i))
                    self.room.pop(i)
                return
            if len(self.open) < self.slots:
                self.open.append([(doc, start, ids, total)])
                self.room.append(self.window - len(ids))
                return
            i = min(range(len(self.room)), key=self.room.__getitem__)
            gap, pieces = self.room.pop(i), self.open.pop(i)
            pieces.append((doc, start, ids[:gap], total))
            self.close(pieces)
            start, ids = start + gap, ids[gap:]

    def finish(self) -> list:
        """Merge the open windows, closing full ones; the pieces of the one that stays unfilled."""
        rest = sorted(zip(self.room, self.open, strict=True), key=lambda x: x[0])
        self.open, self.room, self.slots = [], [], 1
        for _, pieces in rest:
            for p in pieces:
                self.add(*p)
        return self.open.pop() if self.open else []


def _rows(pieces: list, sequence: int, part: int, keep_ids: bool) -> list[tuple]:
    out, at = [], 0
    for doc, start, ids, total in pieces:
        raw = np.ascontiguousarray(ids, dtype="<u4").tobytes()
        out.append((doc, start, len(ids), zlib.crc32(raw), total, sequence, at, part, raw if keep_ids else None))
        at += len(ids)
    return out


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    types = [pa.int64()] * 8 + [pa.binary()]
    columns = list(zip(*rows, strict=True)) if rows else [[]] * 9
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], _COLUMNS)


_ENCODERS: dict[int, UnitEncoder] = {}


def _encoder(tokenizer_json: str) -> UnitEncoder:
    """One encoder for each vocabulary and worker process."""
    key = hash(tokenizer_json)
    if key not in _ENCODERS:
        _ENCODERS.clear()
        _ENCODERS[key] = UnitEncoder(tokenizer_json)
    return _ENCODERS[key]


def pack(
    docs: DataFrame,
    tokenizer_path: str,
    window: int = WINDOW,
    open_windows: int = OPEN_WINDOWS,
    end_id: int | None = END_ID,
    keep_ids: bool = False,
    id_col: str = "doc_id",
    text_col: str = "text",
) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, and ids (little-endian uint32) if kept.

    Null and empty texts hold the end id alone (nothing without one). Texts longer than a window are cut; repeated rows are packed each
    for itself; an empty table gives no rows; other columns are ignored. Sequences have ``window`` ids, or a power of two.
    """
    with open(tokenizer_path, encoding="utf-8") as f:
        vocabulary = f.read()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part = _encoder(vocabulary), TaskContext.get().partitionId()
        rows: list[tuple] = []
        packer = Packer(window, open_windows, lambda n, pieces: rows.extend(_rows(pieces, (part << _SHIFT) | n, -1, keep_ids)))
        for b in batches:
            raw, offsets = T.text_buffers(b.column(1))
            doc_ids = b.column(0).to_pylist()
            for lo, hi in T.blocks(offsets):
                at = offsets[lo : hi + 1]
                ids, counts = encode(raw[at[0] : at[-1]], at - at[0])
                begin = 0
                for d, n in zip(doc_ids[lo:hi], counts.tolist(), strict=True):
                    own = ids[begin : begin + n]
                    begin += n
                    if end_id is not None:
                        own = np.append(own, np.int32(end_id))
                    packer.add(d, 0, own, len(own))
            if rows:
                yield _batch(rows)
                rows.clear()
        left = packer.finish()
        rows.extend(_rows(left, -1, part, True))
        if rows:
            yield _batch(rows)

    packed = cut(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string")).mapInArrow(run, _PIECE))

    def merge(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        rows: list[tuple] = []
        base = (1 << 62) | (int(key[0]) << _SHIFT)
        packer = Packer(window, 1, lambda n, pieces: rows.extend(_rows(pieces, base | n, -1, keep_ids)))
        for r in group.sort_values(["part", "offset"]).itertuples():
            doc = None if r.doc_id is None or r.doc_id != r.doc_id else int(r.doc_id)
            packer.add(doc, int(r.start), np.frombuffer(r.ids, "<u4"), int(r.doc_tokens))
        left = packer.finish()
        size = sum(len(p[2]) for p in left)
        tail = Packer(1, 1, packer.emit)
        tail.n = packer.n
        while size:
            tail.window = 1 << (size.bit_length() - 1)
            pieces, need = [], tail.window
            while need:
                doc, start, ids, total = left.pop(0)
                pieces.append((doc, start, ids[:need], total))
                if len(ids) > need:
                    left.insert(0, (doc, start + need, ids[need:], total))
                need -= min(need, len(ids))
            tail.close(pieces)
            size -= tail.window
        return pd.DataFrame(rows, columns=_COLUMNS).astype({"doc_id": "Int64"})

    whole = packed.where("part < 0")
    merged = packed.where("part >= 0").groupBy(F.expr(f"part div {MERGE}").alias("g")).applyInPandas(merge, _PIECE)
    return whole.unionByName(merged).drop("part", *([] if keep_ids else ["ids"]))
