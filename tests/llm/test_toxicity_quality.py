import random

import numpy as np
import pytest

from rarespan.llm import quality, toxicity
from rarespan.llm.toxicity import Lexicon, Scanner, compile_automaton, look_up


def edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        row = _next(row, i, x, b)
    return row[-1]


def _next(row, i, x, b):
    out = [i]
    for j, y in enumerate(b, 1):
        out.append(min(out[-1] + 1, row[j] + 1, row[j - 1] + (x != y)))
    return out


def test_automaton_equals_edit_distance():
    rnd = random.Random(7)
    stems, whole = ["idiot", "moron", "réeux", "clowns", "ab"], [True, True, False, True, True]
    a = compile_automaton(stems, whole)
    words = ["", "x" * 40, "idiotic", "réeuxan", "réaux"]
    for s in stems:
        for _ in range(300):
            w = list(s)
            for _ in range(rnd.randrange(4)):
                k = rnd.randrange(len(w) + 1)
                w[k : k + rnd.randrange(2)] = rnd.choice([[], [rnd.choice("abimoé")]])
            words.append("".join(w))
    got = look_up(a, words)
    for w, v in zip(words, got.tolist(), strict=True):
        exact = any(w.startswith(s) for s in stems)
        near = any(f and len(s) >= 5 and edits(s, w) == 1 for s, f in zip(stems, whole, strict=True))
        assert (v % 2 == 1) == exact, w
        assert (v > 0 and v % 2 == 0) == (near and not exact), w


def test_context_separates_quotation():
    import pyarrow as pa

    from rarespan.llm import textkit as T

    s = Scanner(Lexicon(["idiot"], [5.0], [True]))
    raw, offsets = T.text_buffers(pa.array(["you are an idiot and a fool", 'he said "what an idiot he is" then', "you are an idoit, really no idot", "", "nothing here"]))
    x = s.features(raw, offsets)
    assert not s.features(*T.text_buffers(pa.array(["no hit in this block"]))).any()
    assert x[0, 1] > x[1, 1] > 0 and x[2, 0] == 1 and not x[3:].any()


@pytest.fixture(scope="module")
def corpus(spark):
    rnd = random.Random(5)
    vocab = ["".join(rnd.choice("abcdefgh") for _ in range(rnd.randrange(3, 9))) for _ in range(500)]
    rows, labels = [], []
    for i in range(2400):
        bad, low = i % 6 == 0, i % 5 == 0
        w = [rnd.choice(vocab) for _ in range(rnd.randrange(30, 90))]
        if bad:
            for _ in range(3):
                w[rnd.randrange(len(w))] = rnd.choice(["zuktar", "zuktars", "molgrim", "Molgrim!"])
        text = " ".join(x + "$$$" for x in w) if low else ". ".join(" ".join(w[k : k + 8]) for k in range(0, len(w), 8))
        rows.append((i, text, 0.5))
        labels.append((i, int(not low), int(bad)))
    rows += [(5000, None, None), (5001, "", 0.1), (3, rows[3][1], 0.2)]
    labels += [(4, None, None), (None, 1, 1), (6, 1, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, toxicity double")
    return docs, spark.createDataFrame(labels, "doc_id long, quality int, toxic int"), dict((a, (b, c)) for a, b, c in labels)


def test_toxicity_on_held_out(spark, corpus):
    docs, labels, truth = corpus
    model = toxicity.train(docs, labels)
    assert {s[:4] for s in model.lexicon.stems} >= {"zukt", "molg"}
    got = toxicity.score_documents(docs, model).collect()
    assert len(got) == docs.count() and all(0 <= r.toxicity <= 1 for r in got)
    right = [(r.toxicity >= 0.5) == bool(truth[r.doc_id][1]) for r in got if r.doc_id < 2400 and r.doc_id % 6]
    assert np.mean(right) > 0.97
    empty = toxicity.train(docs, labels.limit(0))
    assert {r.toxicity for r in toxicity.score_documents(docs, empty).collect()} == {0.0}
    assert toxicity.score_documents(docs.limit(0), model).collect() == []


def test_quality_on_held_out(spark, corpus):
    docs, labels, truth = corpus
    got = quality.score_documents(docs, labels).collect()
    assert len(got) == docs.count() and all(0 <= r.score <= 1 for r in got)
    held = [r.predicted == truth[r.doc_id][0] for r in got if r.held_out and r.doc_id < 2400]
    assert len(held) > 400 and np.mean(held) > 0.97
    assert {r.score for r in quality.score_documents(docs, labels.limit(0)).collect()} == {0.5}
    assert quality.score_documents(docs.limit(0), labels).collect() == []


def test_rules_compile_to_columns(spark, corpus):
    docs, labels, _ = corpus
    stats = quality.with_statistics(docs)
    model = quality.train(stats, labels)
    pdf = stats.select("*", model.column().alias("s")).toPandas()
    x = pdf[list(quality.STATISTICS)].to_numpy(float)
    z = model.intercept + sum(w * r.holds(x) for r, w in model.rules) + sum(w * np.clip(x[:, j], lo, hi) for j, lo, hi, w in model.linear)
    assert np.allclose(1 / (1 + np.exp(-z)), pdf["s"])
