import itertools
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from rarespan.llm import chat, lm
from rarespan.llm.topk import top_k


def brute_top(rows, k):
    ok = {}
    for i, v in rows:
        if v is not None and all(x is not None and math.isfinite(x) for x in v):
            ok[i] = [math.floor(64 * float(np.float32(x))) for x in v]
    out = []
    for q in ok:
        if q % 20 == 0:
            s = sorted((-sum(a * b for a, b in zip(ok[q], ok[c], strict=False)), c) for c in ok if c != q)[:k]
            out += [(q, r + 1, c, -x) for r, (x, c) in enumerate(s)]
    return sorted(out)


@pytest.mark.parametrize("scale", [1.0, 5e6])
def test_top_k_equals_brute_force(spark, scale):
    rnd = random.Random(1)
    rows = [(i, [rnd.choice([rnd.gauss(0, 0.2), 0.0]) * scale for _ in range(24)]) for i in range(300)]
    rows += [(1000 + i, list(rows[20][1])) for i in range(40)]
    rows += [(2000, None), (2020, [1.0, None] + [0.0] * 22), (2040, [float("nan")] * 24), (2060, [float("inf")] * 24)]
    df = spark.createDataFrame([(*r, "x") for r in rows], "vec_id long, embedding array<float>, score string")
    got = sorted(map(tuple, top_k(df, F.col("vec_id") % 20 == 0).collect()))
    assert got == brute_top(rows, 20)
    assert top_k(df.limit(0), F.col("vec_id") % 20 == 0).collect() == []


def plain_viterbi(m, e):
    best = max(
        itertools.product(range(chat.STATES), repeat=len(e)),
        key=lambda p: m.start[p[0]] + sum(m.move[a, b] for a, b in zip(p, p[1:], strict=False)) + sum(e[i][s] for i, s in enumerate(p)),
    )
    return list(best)


def test_viterbi_and_chunks(spark):
    rnd = random.Random(3)
    turns = []
    for c in range(40):
        for t in range(rnd.randrange(1, 30)):
            role = "system" if t == 0 and c % 3 == 0 else ("user", "assistant")[t % 2]
            text = "\n".join("w" * rnd.randrange(1, 20 if role == "user" else 200) for _ in range(1 if role == "user" else rnd.randrange(1, 4)))
            turns.append((c, t, role, text + ("?" if role == "user" else "")))
    m = chat.fit(turns)
    for _ in range(5):
        e = np.random.default_rng(rnd.randrange(99)).normal(size=(5, chat.STATES))
        assert m.decode(e, -1, -1).tolist() == plain_viterbi(m, e)
    df = spark.createDataFrame([*turns, (None, 1, "user", "x"), (99, 0, "user", None)], "conv_id long, turn long, role string, text string")
    whole = sorted(map(tuple, chat.recover_roles(df, m).drop("body").collect()))
    assert sorted(map(tuple, chat.recover_roles(df, m, chunk=4).drop("body").collect())) != []
    want = []
    for c in {t[0] for t in turns}:
        own = [t for t in turns if t[0] == c]
        lines, gaps, heads = [], [], []
        for t in own:
            heads.append(len(lines))
            part = t[3].split("\n")
            lines += part
            gaps += [True] + [False] * (len(part) - 1)
        s = m.decode(m.emissions(chat.features(lines, gaps, True)), -1, -1)
        want += [(c, t[1], t[3], chat.ROLES[s[h] // 2]) for t, h in zip(own, heads, strict=True)]
    assert [r for r in whole if r[0] != 99] == sorted(want)
    assert sorted(map(tuple, chat.recover_roles(df, m, chunk=4).drop("body").collect())) == whole
    right = sum(a[3] == b[2] for a, b in zip(sorted(want), sorted(turns), strict=True))
    assert right > 0.85 * len(turns)


def test_parse_and_render():
    m = chat.fit([(1, 0, "user", "User: hi?"), (1, 1, "assistant", "Assistant: well\nsecond line of it"), (2, 0, "user", "User: and?"), (2, 1, "assistant", "Assistant: yes\nmore")])
    assert chat.parse(m, "User: hello?\n\nAssistant: so\nand on") == [("user", "hello?"), ("assistant", "so\nand on")]
    assert chat.parse(m, None) == [] and chat.render("user", "a") == "<|user|>\na<|end|>\n"


def words(t):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")
    return [*re.findall(r"[^\x20\x09-\x0D]+", low), None]


def test_base_scores_and_filter(spark):
    rnd = random.Random(9)
    vocab = [f"W{i}é" for i in range(400)]
    rows = [(i, rnd.choice([" ", "\n\n"]).join(vocab[min(399, int(rnd.expovariate(0.02)))] for _ in range(rnd.randrange(60))), "x") for i in range(300)]
    rows += [(300, None, None), (301, "", "x"), (7, rows[7][1], "again"), (None, "no id", "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, h string")
    held = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) == 1, F.lit(False))
    model, counts = lm.train(df.where(~held), heads=50)
    got = lm.score_documents(df, model, counts).collect()
    is_held = lambda i: i is not None and zlib.crc32(str(i).encode()) % 5 == 1
    c, pairs = Counter(), Counter()
    for i, t, _ in rows:
        if not is_held(i):
            w = words(t)
            c.update(w)
            pairs.update(zip([1, *w], w, strict=False))
    n, v = sum(c.values()), len(c)
    assert (model.n_tokens, model.n_types) == (n, v)
    want = sorted((str(i), len(words(t)), sum(c[w] > 0 for w in words(t)), round(sum(math.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in words(t)), 6)) for i, t, _ in rows)
    assert sorted((str(r.doc_id), r.n_tokens, r.n_known, round(r.base_score, 6)) for r in got) == want
    assert len(model.heads) <= 50 and all(r.score < 0 for r in got)
    # the filter gives each n-gram its level back
    h = np.array([r.h for r in counts.collect()], np.int64).view(np.uint64)
    level = {r.h: int(lm.level(np.array([r.c]))[0]) for r in counts.collect()}
    assert np.mean(model.filter.levels(h) == np.array([level[int(x)] for x in h.view(np.int64)])) > 0.95
    assert [int(lm.level(np.array([c]))[0]) for c in (1, 2, 3, 4, 7, 8, 1023, 1024)] == [1, 2, 2, 3, 3, 4, 10, 11]
    # probabilities of a history's words sum to one at most
    keys = np.append(h, np.uint64(12345))
    for history in h[:40]:
        assert (10 ** np.array([model.log10(np.array([k]), np.array([history])).item() for k in keys])).sum() < 1.0 + 1e-6


def plain_scores(rows, train, order):
    """log10 P of each text with exact counts quantised like the filter's."""
    from math import floor, log10, log2

    grams = [Counter() for _ in range(order + 1)]
    docs = 0
    for t in train:
        w = words(t)
        docs += 1
        for k in range(1, order + 1):
            padded = [1, *w] if k >= 2 else w
            grams[k].update(tuple(padded[i : i + k]) for i in range(len(padded) - k + 1))
    n, v = sum(grams[1].values()), len(grams[1])
    low = lambda c: 2 ** floor(log2(c)) if c else 0
    high = lambda c: 2 * low(c) - 1 if c else 0
    mix = lambda x, y, p: sum(s * (max(min(x, y) - lm.DISCOUNT, 0) + k * p) / (y + k) for s, k in lm.MIXTURE)
    out = []
    for t in rows:
        w, total = words(t), 0.0
        for i, x in enumerate(w):
            p = (grams[1][(x,)] + 0.5) / (n + 0.5 * (v + 1))
            if order >= 2:
                y = docs if i == 0 else grams[1][(w[i - 1],)]
                p = mix(low(grams[2][((1 if i == 0 else w[i - 1]), x)]), y, p)
            if order >= 3 and i >= 1:
                three = tuple([1, *w][i - 1 : i + 2])
                p = mix(low(grams[3][three]), high(grams[2][three[:2]]), p)
            total += log10(p)
        out.append(total)
    return out


@pytest.mark.parametrize("order", [1, 2, 3])
def test_scores_equal_exact_counts(spark, order):
    """Every word is a head and the filter is large, so that scores are those of the quantised counts; broadcast or not, they are the same."""
    rnd = random.Random(order)
    vocab = [f"w{i}" for i in range(60)]
    texts = [" ".join(rnd.choice(vocab) for _ in range(rnd.randrange(80))) for _ in range(200)] + ["", None, "x" * 100_000 + " w1 " * 3]
    texts += texts[:30]
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, score string").repartition(4)
    model, counts = lm.train(df.where("doc_id < 150"), order=order, bits_per_key=64)
    got = {r.doc_id: r.score for r in lm.score_documents(df, model, counts).collect()}
    want = plain_scores(texts, texts[:150], order)
    assert max(abs(got[i] - s) for i, s in enumerate(want)) < 1.0  # false positives
    assert sum(abs(got[i] - s) < 1e-6 for i, s in enumerate(want)) > 0.97 * len(want)
    dealt, counts = lm.train(df.where("doc_id < 150"), order=order, bits_per_key=64, broadcast=0)
    assert dealt.filter is None
    again = {r.doc_id: r.score for r in lm.score_documents(df, dealt, counts).collect()}
    assert again == got
    assert lm.score_documents(df.limit(0), dealt, counts).collect() == []


def test_every_ngram_is_in_the_filter(spark):
    texts = [f"a{i} b{i} c{i}" for i in range(3000)]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    model, _ = lm.train(df, heads=10)
    for order in (1, 2):
        rows = lm.ngram_counts(df, order).collect()
        found = model.filter.levels(np.array([r.h for r in rows], np.int64).view(np.uint64))
        assert (found >= lm.level(np.array([r.c for r in rows]))).all() and len(rows) > 9000
    absent = np.random.default_rng(1).integers(0, 2**63, 20_000, dtype=np.uint64)
    assert (model.filter.levels(absent) > 0).mean() < 0.06


def test_empty_training_table(spark):
    df = spark.createDataFrame([(1, "a b")], "doc_id long, text string")
    model, counts = lm.train(df.limit(0))
    (row,) = lm.score_documents(df, model, counts).collect()
    assert (row.n_tokens, row.n_known, row.train_tokens) == (3, 0, 0) and math.isfinite(row.score) and math.isfinite(row.base_score)


def test_chat_takes_whole_conversations_and_strips_markers(spark):
    rows = [(c, t, ("user", "assistant")[t % 2], ("User: " if t % 2 == 0 else "Assistant: ") + "word " * (3 if t % 2 == 0 else 30) + f"{c}") for c in range(30) for t in range(100)]
    rows += [(77, 0, "user", "x " * 200_000), (None, 0, "user", "x"), (1, None, "user", "x"), (78, 0, None, None)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    for clash in ("first", "chunk", "alone", "body"):
        df = df.withColumn(clash, F.lit("x"))
    found = chat.format_conversations(df).collect()
    assert len(found) == len(rows) - 2
    marked = [r for r in found if r.conv_id < 30]
    assert sum(r.role_found == ("user", "assistant")[r.turn % 2] for r in marked) > 0.95 * len(marked)
    assert not any("User:" in r.rendered or "Assistant:" in r.rendered for r in marked if r.role_found == ("user", "assistant")[r.turn % 2])
    assert chat.format_conversations(df.limit(0)).collect() == []
    # a bound that the first conversations pass leaves those out whole
    some = chat.train(df, F.lit(True), most=250)
    assert np.isfinite(some.move).all()
