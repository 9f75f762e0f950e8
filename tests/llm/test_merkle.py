import hashlib
import random
import re

import xxhash
from pyspark.sql import functions as F

from rarespan.llm.merkle import LEAF, NODES, differing_branches, edit_comparison, fingerprints, tree, with_next

SCHEMA = "doc_id long, text string, root string"


def all_nodes(text):
    """(root, set of the hashes of all nodes) in plain Python."""
    md5 = lambda x: hashlib.md5(x.encode()).hexdigest()
    h64 = lambda x: xxhash.xxh64(x.encode(), seed=42).intdigest()
    signed = lambda x: str(x - (1 << 64) if x >> 63 else x)
    marks = ".,!?;:|&%$#*…。"
    cut = rf"[^{marks}]{{0,{LEAF}}}[{marks}]+|[^{marks}]{{1,{LEAF}}}"
    leaves = [[[h64(x) for x in re.findall(cut, p)] for p in s.split("\n")] for s in re.split(r"\n[ \t]*\n", text)]
    paragraphs = [[md5(",".join(map(signed, p))) for p in s] for s in leaves]
    sections = [md5(",".join(s)) for s in paragraphs]
    top = md5(",".join([",".join(sections), str(len(text)), signed(h64(text))]))
    inner = [h64(x) for x in [*(p for s in paragraphs for p in s), *sections, top]]
    return top, {h & 0xFFFFFFFF for h in [*(h for s in leaves for p in s for h in p), *inner]}


def near(a, b):
    return 2 * len(a & b) / (len(a) + len(b))


def test_likeness_equals_brute_force_on_whole_trees(spark):
    rnd = random.Random(11)
    part = ["one two. ", "three, ", "\n", "\n \t\n", "𝟘é; ", "x" * 450, "four"]
    texts = ["".join(rnd.choice(part) for _ in range(rnd.randrange(40))) for _ in range(120)] + ["", "a. b.", "b. a."]
    df = spark.createDataFrame([(i, t, "") for i, t in enumerate(texts)], SCHEMA)
    got = {r.doc_id: r for r in edit_comparison(df).collect()}
    for i, t in enumerate(texts):
        nxt = texts[i - 1]
        half = len(t) // 2
        (top, own), (_, other), (changed, after) = all_nodes(t), all_nodes(nxt), all_nodes(t[: len(t) - half] + nxt[:half])
        assert len(own) < NODES
        assert got[i].fingerprint == top + ":" + "".join(f"{h:08x}" for h in sorted(own))
        assert got[i].edited_fingerprint.startswith(changed)
        assert abs(got[i].near_edited - near(own, after)) < 1e-12 and abs(got[i].near_next - near(own, other)) < 1e-12
    assert got[len(texts) - 1].near_next < 1  # the same phrases in another order


def test_long_texts_have_bounded_fingerprints_and_close_likeness(spark):
    rnd = random.Random(12)
    words = [f"w{i}" for i in range(3000)]
    rows = []
    for i in range(12):
        rows.append((i, "\n".join(" ".join(rnd.choices(words, k=9)) + "." for _ in range(800 if i % 3 else 60)), ""))
    got = {r.doc_id: r for r in edit_comparison(spark.createDataFrame(rows, SCHEMA)).collect()}
    for i, t, _ in rows:
        nxt = rows[i - 1][1]
        half = len(t) // 2
        (_, own), (_, after) = all_nodes(t), all_nodes(t[: len(t) - half] + nxt[:half])
        assert len(got[i].fingerprint) <= 33 + 8 * NODES
        assert abs(got[i].near_edited - near(own, after)) < 0.2 and got[i].near_edited > got[i].near_next


def test_edits_equal_brute_force(spark):
    rnd = random.Random(4)
    words = ["a", "bc.", "é,", "\n", "\n\n", "𝟘", "long" * 80, "$$$"]
    rows = [(i * 3, " ".join(rnd.choice(words) for _ in range(rnd.randrange(30))), "x") for i in range(300)]
    rows += [(5000, None, "x"), (5001, "", None), (5002, "x", "y"), (9, "again, one", "z"), (None, "no id. at all", None)]
    order = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0), r[1] or ""))
    want = []
    for k, r in enumerate(order):
        t, nxt = r[1] or "", order[(k + 1) % len(order)][1] or ""
        h = len(t) // 2
        want.append((r[0], len(t), hashlib.sha256((t[: len(t) - h] + nxt[:h]).encode()).hexdigest()))
    df = spark.createDataFrame(rows, SCHEMA).repartition(7)
    got = edit_comparison(df).collect()
    assert sorted(((r.doc_id, r.n_chars, r.edited_sha256) for r in got), key=str) == sorted(want, key=str)
    by_text = {}
    for r in got:
        assert 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
        if r.fingerprint == r.edited_fingerprint:
            assert r.near_edited == 1
    for r in fingerprints(df).collect():
        by_text.setdefault(r.text or "", set()).add(r.fingerprint)
    assert all(len(v) == 1 for v in by_text.values())
    assert len(set().union(*by_text.values())) == len(by_text)


def test_many_ranges_and_one_row(spark):
    df = spark.createDataFrame([(i, f"t{i}", "") for i in range(100)], SCHEMA)
    got = {r.doc_id: r.n for r in with_next(df, {"n": "text"}, buckets=37).collect()}
    assert got == {i: f"t{(i - 1) % 100}" for i in range(100)}
    assert [r.near_next for r in edit_comparison(df.where("doc_id = 4")).collect()] == [1.0]
    assert edit_comparison(df.limit(0)).collect() == []
    assert len(edit_comparison(spark.createDataFrame([(None, "a", ""), (None, "b", "")], SCHEMA)).collect()) == 2


def test_branches_locate_edits(spark):
    a = "one. two\nthree\n\nfour"
    df = spark.createDataFrame([(a, a), (a, "one. two\nthree!\n\nfour"), (a, "one. two\nthree\n\nfour\nfive")], "a string, b string")
    got = [[tuple(x) for x in r[0]] for r in df.select(differing_branches(tree(F.col("a")), tree(F.col("b")))).collect()]
    assert got == [[], [(0, 1)], [(1, 1)]]
