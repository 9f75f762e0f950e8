"""Toxicity: Levenshtein automata over a lexicon trie, with context windows.

The lexicon is learnt: from a bounded sample of labelled documents, near copies counted once, stems are kept that
begin the words of toxic documents far more often than those of others. The trie of the stems finds words that begin
with one; for stems that mostly stand as whole words, the trie is intersected with a Levenshtein automaton of one edit, so that
misspelt words are found as well. Both are compiled to one transition table and run over a batch's new words together.

Each hit weighs its stem's log odds, less if misspelt, and much less if its context window looks like a quotation or a
report. A logistic model over sums of the hits gives the document's score.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as St

from rarespan.llm import textkit as T
from rarespan.llm.logistic import fit_logistic
from rarespan.llm.sampling import bounded
from rarespan.runtime import cut

SAMPLE = 12_000  # at most so many labelled rows are learnt from
MOST_STEMS = 400
LEAST_LLR = 36.0
LEAST_ODDS = 10.0
STEM = (3, 12)
WINDOW = 6
EDITED = 0.7
_LONGEST = 32

# Marks stripped from words, quotation marks, and words that announce a quotation.
_STRIP = ".,;:!?\"'()[]{}<>*&$#%|«»“”„‘’…-_/\\=+~^`@"
_OPEN, _CLOSE = ('"', "“", "„", "«", "‘"), ('"', "”", "“", "»", "’")
_REPORT = {"said", "says", "wrote", "writes", "quote", "quoted", "quoting", "called", "dit", "écrit", "sagte", "schrieb", "dijo", "escribió"}


@dataclass
class Lexicon:
    """Stems with weights; ``whole`` marks those that take misspellings as whole words."""

    stems: list[str] = field(default_factory=list)
    weights: list[float] = field(default_factory=list)
    whole: list[bool] = field(default_factory=list)


@dataclass
class Automaton:
    symbols: np.ndarray
    table: np.ndarray
    prefix: np.ndarray
    final: np.ndarray
    step: int = _LONGEST


def compile_automaton(stems: list[str], whole: list[bool]) -> Automaton:
    """Subset construction over (stem, matched letters, edits).

    A state that has a whole stem without edits is absorbing: ``prefix`` names the stem + 1. ``final`` names the stem + 1 for
    states in which a word that ends there is one edit away from a whole-word stem of five letters or more.
    """
    letters = sorted({c for s in stems for c in s})
    code = {c: i + 1 for i, c in enumerate(letters)}
    symbols = np.zeros(0x3000, np.int32)
    for c, i in code.items():
        if ord(c) < len(symbols):
            symbols[ord(c)] = i
    fuzzy = [w and len(s) >= 5 for s, w in zip(stems, whole, strict=True)]
    rows = [[code[c] for c in s] for s in stems]

    def grown(items: set) -> frozenset:
        """With the deletions of stem letters that an edit may still pay for."""
        return frozenset(items | {(i, p + 1, 1) for i, p, e in items if e == 0 and fuzzy[i] and p < len(rows[i])})

    def follow(items: frozenset, x: int) -> frozenset:
        out = set()
        for i, p, e in items:
            if p < len(rows[i]) and rows[i][p] == x:
                out.add((i, p + 1, e))
            if e == 0 and fuzzy[i]:
                out.add((i, p, 1))
                if p < len(rows[i]):
                    out.add((i, p + 1, 1))
        return grown(out)

    start = grown({(i, 0, 0) for i in range(len(stems))})
    states, order, table = {start: 0, frozenset(): 1}, [start, frozenset()], []
    k = 0
    while k < len(order):
        here, row = order[k], []
        done = next((i for i, p, e in sorted(here) if e == 0 and p == len(rows[i])), None)
        for x in range(len(letters) + 1):
            if done is not None and k > 1:
                row.append(k)
                continue
            nxt = follow(here, x)
            if nxt not in states:
                states[nxt] = len(order)
                order.append(nxt)
            row.append(states[nxt])
        table.append(row)
        k += 1
    prefix, final = np.zeros(len(order), np.int32), np.zeros(len(order), np.int32)
    for k, here in enumerate(order):
        for i, p, e in sorted(here, reverse=True):
            if p == len(rows[i]):
                if e == 0:
                    prefix[k] = i + 1
                elif fuzzy[i]:
                    final[k] = i + 1
    return Automaton(symbols, np.array(table, np.int32).reshape(len(order), len(letters) + 1), prefix, final)


def look_up(automaton: Automaton, words: list[str]) -> np.ndarray:
    """0 for words without a stem, 1 + 2 x stem for an exact one, 2 + 2 x stem for a misspelt one."""
    if not words:
        return np.zeros(0, np.int32)
    long = np.fromiter((len(w) > _LONGEST for w in words), bool, len(words))
    grid = np.array(words, dtype=f"U{_LONGEST}")
    grid = np.ascontiguousarray(grid).view(np.uint32).reshape(len(words), _LONGEST)
    state = np.zeros(len(words), np.int32)
    n = np.zeros(len(words), np.int64)
    for j in range(_LONGEST):
        column = grid[:, j]
        live = column != 0
        if not live.any():
            break
        symbol = automaton.symbols[np.where(column < len(automaton.symbols), column, 0)]
        state = np.where(live, automaton.table[state, symbol], state)
        n += live
    exact, near = automaton.prefix[state], automaton.final[state]
    near = np.where(long | (n == 0), 0, near)
    exact = np.where(n == 0, 0, exact)
    return np.where(exact > 0, 2 * exact - 1, np.where(near > 0, 2 * near, 0)).astype(np.int32)


def _context(words: list[str], at: int) -> float:
    """1 for plain abuse, less where the window around word ``at`` quotes or reports."""
    left, right = words[max(0, at - WINDOW) : at + 1], words[at : at + WINDOW + 1]
    quoted = any(w.startswith(_OPEN) for w in left) and any(w.rstrip(".,;:!?").endswith(_CLOSE) for w in right)
    told = any(w.strip(_STRIP) in _REPORT for w in left)
    return (0.35 if quoted else 1.0) * (0.7 if told else 1.0)


FEATURES = ("any", "log_sum", "log_distinct", "density")


class Scanner:
    """Hits of a lexicon in blocks of texts; verdicts on words are remembered by their hashes."""

    def __init__(self, lexicon: Lexicon, bits: int = 20):
        self.lexicon, self.bits = lexicon, bits
        self.automaton = compile_automaton(lexicon.stems, lexicon.whole)
        self.known = T.HashTable(bits)

    def hits(self, w: T.Words) -> np.ndarray:
        key = T.word_hashes(w)
        key[key == 0] = 1
        found = self.known.find(key)
        miss = np.flatnonzero(found < 0)
        if len(miss):
            unique, sample, back = np.unique(key[miss], return_index=True, return_inverse=True)
            data = w.buf.tobytes()
            s, e = w.start[miss[sample]].tolist(), w.end[miss[sample]].tolist()
            texts = [data[i:j].decode("utf-8", "ignore").strip(_STRIP).lower() for i, j in zip(s, e, strict=True)]
            verdict = look_up(self.automaton, texts)
            if self.known.count + len(unique) > self.known.mask // 2:
                self.known = T.HashTable(max(self.bits, (4 * len(unique)).bit_length()))
            self.known.put(unique, verdict)
            found[miss] = verdict[back]
        return found

    def features(self, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        w = T.words(raw, offsets)
        out = np.zeros((len(offsets) - 1, len(FEATURES)))
        if not len(w.start) or not self.lexicon.stems:
            return out
        verdict = self.hits(w)
        at = np.flatnonzero(verdict)
        if not len(at):
            return out
        docs = w.doc[at]
        first = w.first
        for lo, hi in zip(np.flatnonzero(np.diff(docs, prepend=-1)), np.append(np.flatnonzero(np.diff(docs)) + 1, len(docs)), strict=True):
            d = int(docs[lo])
            total, seen = 0.0, set()
            for i in at[lo:hi].tolist():
                stem, edited = (int(verdict[i]) - 1) // 2, verdict[i] % 2 == 0
                a, b = max(int(first[d]), i - WINDOW), min(int(first[d] + w.per_doc[d]), i + WINDOW + 1)
                around = [w.buf[w.start[k] : w.end[k]].tobytes().decode("utf-8", "ignore") for k in range(a, b)]
                total += self.lexicon.weights[stem] * (EDITED if edited else 1.0) * _context(around, i - a)
                seen.add(stem)
            out[d] = (1.0, math.log1p(total), math.log1p(len(seen)), math.log1p(100.0 * total / w.per_doc[d]))
        return out


def _keys(raw: np.ndarray, offsets: np.ndarray, n: int = 3, shingle: int = 5) -> np.ndarray:
    """Smallest shingle hashes of each text under ``n`` orders; near copies mostly share each of them."""
    out = np.zeros((len(offsets) - 1, n), np.int64)
    w = T.words(raw, offsets)
    if not len(w.start):
        return out
    h = T.word_hashes(w)
    run = h.copy()
    for k in range(1, shingle):
        run[:-k] = T.pair_hashes(run[:-k], h[k:])
    full = np.flatnonzero(w.per_doc)
    for j in range(n):
        low = np.minimum.reduceat(T.mix64(run ^ np.uint64(0x9E3779B97F4A7C15 * (j + 1) & (2**64 - 1))), w.first[full])
        out[full, j] = low.view(np.int64)
    return out


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, folds: int, held_out: int, most: int) -> DataFrame:
    """At most ``most`` documents (doc_id, text, y) with a label, outside the held-out fold, chosen by a hash of their ids."""
    fold = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(folds))
    usable = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max(label).alias("y"))
    chosen = bounded(usable.where(fold != held_out), most)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where(F.col("text").isNotNull())
    return rows.join(F.broadcast(chosen), "doc_id").orderBy(F.xxhash64("doc_id"), "doc_id", F.xxhash64("text")).limit(most)


def learn_lexicon(sample: DataFrame) -> Lexicon:
    """Stems of the sample (doc_id, text, y), near copies counted once. Of the bounded sample, ids and three hashes a row reach the driver, and the best stems."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, offsets = T.text_buffers(b.column(0))
            keys = np.concatenate([_keys(raw[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]) for lo, hi in T.blocks(offsets)] or [np.zeros((0, 3), np.int64)])
            yield pa.RecordBatch.from_arrays([b.column(1), *(pa.array(keys[:, j].copy()) for j in range(3))], ["row", "k0", "k1", "k2"])

    named = sample.select("text", F.xxhash64("doc_id", "text").alias("row"), F.col("y").cast("int").alias("y"))
    rows = named.select("text", "row").mapInArrow(run, "row long, k0 long, k1 long, k2 long").toArrow()
    rows = np.column_stack([c.to_numpy() for c in rows.columns])
    rows = rows[np.argsort(rows[:, 0], kind="stable")]
    for j in (1, 2, 3):
        rows = rows[np.sort(np.unique(rows[:, j], return_index=True)[1])]
    alone = named.sparkSession.createDataFrame(pa.table({"row": rows[:, 0].copy()}))
    single = cut(named.join(F.broadcast(alone), "row", "left_semi").dropDuplicates(["row"]).select("text", "y"))
    strip = "[" + "".join("\\" + c for c in _STRIP) + "]"
    bare = F.transform(F.split(F.lower("text"), r"[\x20\x09-\x0D]+"), lambda w: F.regexp_replace(w, f"^{strip}+|{strip}+$", ""))
    word = F.explode(F.array_distinct(bare))
    words = cut(single.select(word.alias("word"), "y").groupBy("word").agg(F.sum("y").alias("t"), F.sum(1 - F.col("y")).alias("c")).where("char_length(word) >= 3"))
    n = single.groupBy("y").count().collect()
    n = {r["y"]: r["count"] for r in n}
    toxic, clean = n.get(1, 0), n.get(0, 0)
    if not toxic or not clean:
        return Lexicon()
    stem = F.explode(F.transform(F.sequence(F.lit(STEM[0]), F.greatest(F.lit(STEM[0]), F.least(F.lit(STEM[1]), F.char_length("word")))), lambda k: F.substring("word", F.lit(1), k)))
    stems = words.select(stem.alias("stem"), "word", "t", "c").where(f"char_length(stem) >= {STEM[0]}")
    stems = stems.groupBy("stem").agg(F.sum("t").alias("t"), F.sum("c").alias("c"), F.sum(F.when(F.col("word") == F.col("stem"), F.col("t")).otherwise(0)).alias("alone"))
    t, c = F.col("t").cast("double"), F.col("c").cast("double")
    share = F.lit(toxic / (toxic + clean))
    both = t + c
    llr = 2 * (F.when(t > 0, t * F.log(t / (both * share))).otherwise(0.0) + F.when(c > 0, c * F.log(c / (both * (1 - share)))).otherwise(0.0))
    odds = ((t + 0.5) / (toxic + 1)) / ((c + 0.5) / (clean + 1))
    best = (
        stems.where("t >= 4").withColumn("llr", llr).withColumn("odds", odds).where((F.col("llr") >= LEAST_LLR) & (F.col("odds") >= LEAST_ODDS))
        .orderBy(F.desc("llr"), F.desc(F.char_length("stem")), "stem").limit(8 * MOST_STEMS).collect()
    )
    chosen: list = []
    for r in best:
        if not any(r["stem"].startswith(x["stem"]) or x["stem"].startswith(r["stem"]) for x in chosen):
            chosen.append(r)
    chosen = chosen[:MOST_STEMS]
    return Lexicon([r["stem"] for r in chosen], [math.log(r["odds"]) for r in chosen], [r["alone"] >= 0.8 * r["t"] for r in chosen])


@dataclass
class Model:
    lexicon: Lexicon
    weights: list[float]

    def score(self, features: np.ndarray) -> np.ndarray:
        if not self.lexicon.stems:
            return np.zeros(len(features))
        z = features @ np.array(self.weights[1:]) + self.weights[0]
        return 1.0 / (1.0 + np.exp(-np.clip(z, -30, 30)))


def _feature_rows(sample: DataFrame, lexicon: Lexicon) -> tuple[np.ndarray, np.ndarray]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(lexicon)
        for b in batches:
            raw, offsets = T.text_buffers(b.column(0))
            x = np.concatenate([scanner.features(raw[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]) for lo, hi in T.blocks(offsets)] or [np.zeros((0, len(FEATURES)))])
            yield pa.RecordBatch.from_arrays([*(pa.array(x[:, j].copy()) for j in range(len(FEATURES))), b.column(1)], [*FEATURES, "y"])

    schema = ", ".join(f"`{f}` double" for f in FEATURES) + ", y int"
    got = sample.select("text", F.col("y").cast("int").alias("y")).mapInArrow(run, schema).toPandas()
    return got[list(FEATURES)].to_numpy(float), got["y"].to_numpy(float)


def drop_misleading(sample: DataFrame, lexicon: Lexicon) -> Lexicon:
    """Takes the misspellings from stems whose neighbours at one edit also occur in clean documents of the sample."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(lexicon)
        for b in batches:
            raw, offsets = T.text_buffers(b.column(0))
            rows = []
            for lo, hi in T.blocks(offsets):
                w = T.words(raw[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo])
                if len(w.start):
                    verdict = scanner.hits(w)
                    rows += [int(v) for v in verdict[(verdict > 0) & (verdict % 2 == 0)]]
            yield pa.RecordBatch.from_arrays([pa.array(rows, pa.int32())], ["v"])

    if not any(lexicon.whole):
        return lexicon
    clean = sample.where("y = 0").select("text").mapInArrow(run, "v int").groupBy("v").count().where("count >= 2").collect()
    bad = {(r["v"] - 1) // 2 for r in clean}
    return Lexicon(lexicon.stems, lexicon.weights, [w and i not in bad for i, w in enumerate(lexicon.whole)])


def train(docs: DataFrame, labels: DataFrame, folds: int = 5, held_out: int = 0, most: int = SAMPLE) -> Model:
    """Lexicon and model from at most ``most`` labelled rows outside the held-out fold; an empty model without both classes."""
    sample = cut(labelled_sample(docs, labels, "toxic", folds, held_out, most))
    lexicon = drop_misleading(sample, learn_lexicon(sample))
    if not lexicon.stems:
        return Model(Lexicon(), [])
    x, y = _feature_rows(sample, lexicon)
    return Model(lexicon, fit_logistic(x, y).tolist())


def score_documents(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """The documents with toxicity (0 to 1) added (a column of that name is replaced). Null and empty texts score as texts without hits."""
    docs = docs.drop("toxicity")
    place = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(model.lexicon)
        for b in batches:
            raw, offsets = T.text_buffers(b.column(place))
            x = np.concatenate([scanner.features(raw[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]) for lo, hi in T.blocks(offsets)] or [np.zeros((0, len(FEATURES)))])
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(model.score(x))], [*b.schema.names, "toxicity"])

    return docs.mapInArrow(run, St.StructType([*docs.schema.fields, St.StructField("toxicity", St.DoubleType())]))
