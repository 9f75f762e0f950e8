import random

import numpy as np
from pyspark.sql import functions as F

from rarespan.llm.components import components
from rarespan.llm.near_copies import near_copies, shingle_edges, signatures, verified_edges
from rarespan.runtime import cut
from tests.llm.test_simhash import SCHEMA, fingerprint


def shingles(text, k=5):
    w = (text or "").split()
    return {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()


def components_of(spark, rows):
    return {r.doc_id: r.component_id for r in near_copies(spark.createDataFrame(rows, SCHEMA)).collect()}


def test_copies_meet_and_others_stay_apart(spark):
    rnd = random.Random(11)
    vocab = [f"w{i}" for i in range(3000)]
    rows, groups, i = [], [], 0
    for g in range(60):
        base = [rnd.choice(vocab) for _ in range(rnd.choice([60, 200, 500]))]
        for c in range(rnd.choice([1, 1, 2, 3, 30 if g == 0 else 2])):
            copy = list(base)
            for _ in range(int(len(copy) * 0.015) if c else 0):
                copy[rnd.randrange(len(copy))] = rnd.choice(vocab)
            rows.append((i, " ".join(copy), "x"))
            groups.append(g)
            i += 1
    rows += [(i, None, "x"), (i + 1, " \n", "x"), (i + 2, "one two", "x"), (i + 3, "one two", "x"), (i + 4, "two one", "x")]
    groups += [-1, -1, -2, -2, -3]
    got = components_of(spark, rows)
    pairs = alike = met = 0
    for a in range(len(rows)):
        for b in range(a):
            same = got[rows[a][0]] == got[rows[b][0]]
            if groups[a] != groups[b]:
                assert not same, (rows[a], rows[b])
            elif groups[a] < 0:
                assert same
            else:
                x, y = shingles(rows[a][1]), shingles(rows[b][1])
                pairs += 1
                if len(x & y) / len(x | y) >= 0.8:
                    alike += 1
                    met += same
                if bin(fingerprint(rows[a][1]) ^ fingerprint(rows[b][1])).count("1") <= 3:
                    assert same
    assert alike > 40 and met / alike >= 0.9, (alike, met)
    assert near_copies(spark.createDataFrame([], SCHEMA)).collect() == []


def edited(rnd, groups):
    """Texts with a copy cut short, extended or beheaded, one line in all of them; and the pairs of true similarity 0.8 or more."""
    vocab = [f"w{i}" for i in range(3000)]
    line = " ".join(rnd.choice(vocab) for _ in range(40))
    rows, pairs = [], []
    for g in range(groups):
        base = [rnd.choice(vocab) for _ in range(rnd.randrange(100, 900))] + line.split()
        n = len(base)
        edits = [base[: int(n * 0.85)], base + [rnd.choice(vocab) for _ in range(int(n * 0.2))], base[int(n * 0.15) :]]
        for copy in (base, edits[g % 3]):
            rows.append((len(rows), " ".join(copy), "x"))
        x, y = shingles(rows[-2][1]), shingles(rows[-1][1])
        if len(x & y) / len(x | y) >= 0.8:
            pairs.append((len(rows) - 2, len(rows) - 1))
    return rows, pairs


def test_extended_and_cut_copies_are_candidates(spark):
    rows, pairs = edited(random.Random(5), 150)
    got = near_copies(spark.createDataFrame(rows, SCHEMA))
    assert got.count() == 300 and len(pairs) > 120
    own = cut(signatures(spark.createDataFrame(rows, SCHEMA)))
    node = dict(own.select("doc_id", "sig").collect())
    root = dict(components(shingle_edges(own.select(F.col("sig").alias("node"), "sketch", "keys"))).collect())
    assert all(root.get(node[a], -1) == root.get(node[b], -2) for a, b in pairs)
    got = {r.doc_id: r.component_id for r in got.collect()}
    assert sum(got[a] == got[b] for a, b in pairs) / len(pairs) > 0.9
    assert len(set(got.values())) >= 150


def test_links_are_exactly_those_of_the_least_similarity(spark):
    rnd = random.Random(3)
    rows, want = [], []
    for g in range(120):  # sets of 4x and 5x, or one shingle less in common: 0.8 and just below it
        x = rnd.randrange(40, 120)
        n = 5 * x + 4
        base = [f"g{g}w{i}" for i in range(n)]
        rows += [(2 * g, " ".join(base), "x"), (2 * g + 1, " ".join(base[: 4 * x + 4 - g % 2]), "x")]
        want.append(g % 2 == 0)
    got = components_of(spark, rows)
    assert [got[2 * g] == got[2 * g + 1] for g in range(120)] == want


def test_blocks_of_a_large_cluster_link_as_one(spark):
    rnd = random.Random(8)
    sets = []
    for i in range(90):
        own = set(range(100)) - set(rnd.sample(range(100), rnd.randrange(30)))
        sets.append((7, i, np.array(sorted(own), np.uint64).tobytes()))
    rows = spark.createDataFrame(sets, "root long, node long, keys binary")
    whole, dealt = (dict(components(verified_edges(rows, b)).collect()) for b in (1 << 19, 700))
    assert whole == dealt and len(whole) > 60


def linked(root, pairs):
    return all(root.get(a, -1) == root.get(b, -2) for a, b in pairs)


def test_large_clusters_link_what_pairs_link(spark):
    """Copies of one centre that are not alike among themselves, a second group, a chain, and loose sets: the links are those of all pairs."""
    rnd = random.Random(4)
    centre, other = list(range(400)), list(range(1000, 1400))
    sets = [set(centre), set(other)]
    sets += [set(c) - set(rnd.sample(c, 40)) | set(range(10**6 + 1000 * i, 10**6 + 1000 * i + 30)) for i in range(120) for c in (centre, other)]
    chain = [set(range(5000 + 8 * i, 5100 + 8 * i)) for i in range(30)]
    sets += chain + [set(rnd.sample(range(9000, 9900), 80)) for _ in range(40)]
    rows = [(1, i, np.array(sorted(s), np.uint64).tobytes()) for i, s in enumerate(sets)]
    pairs = [(a, b) for a in range(len(sets)) for b in range(a) if 9 * len(sets[a] & sets[b]) >= 4 * (len(sets[a]) + len(sets[b]))]
    want = dict(components(spark.createDataFrame(pairs, "a long, b long")).collect())
    df = spark.createDataFrame(rows, "root long, node long, keys binary")
    for stars in (1, 2):
        assert dict(components(verified_edges(df, 3000, stars)).collect()) == want


def test_repeated_ids_and_rows(spark):
    text = " ".join(f"w{i}" for i in range(50))
    rows = [(1, text, "x"), (1, "another text altogether here now", "x"), (1, text, "x"), (2, text, "x"), (None, text, "x"), (3, None, "x"), (4, "", "x")]
    got = near_copies(spark.createDataFrame(rows, SCHEMA)).collect()
    assert sorted((str(r.doc_id), r.component_id) for r in got) == [("1", 1), ("1", 1), ("1", 1), ("2", 1), ("3", 3), ("4", 3), ("None", 1)]
    kept = {(r.doc_id, r.text_hash) for r in got if r.stays}
    assert len(kept) == 3 and {i for i, _ in kept} == {1, 3}


def test_rows_without_an_id_are_compared_like_others(spark):
    """Copies cut short, too far apart for the fingerprint, without an id on both sides or on one; and the same text twice without one."""
    import corpus_pipeline

    rnd = random.Random(9)
    vocab = [f"w{i}" for i in range(3000)]
    rows, want, far = [], [], 0
    for g in range(12):
        base = [rnd.choice(vocab) for _ in range(200)]
        long, short = " ".join(base), " ".join(base[:166])
        far += bin(fingerprint(long) ^ fingerprint(short)).count("1") > 3
        rows += [(g if g % 3 == 1 else None, long, "x"), (g if g % 3 == 2 else None, short, "x")]
        want.append((g if g % 3 else None, long, short))
    same = " ".join(rnd.choice(vocab) for _ in range(50))
    rows += [(None, same, "x"), (None, same, "x"), (None, None, "x"), (None, " ", "x"), (100, "alone here", "x")]
    docs = spark.createDataFrame(rows, SCHEMA)
    assert far > 6
    found = near_copies(docs).collect()
    assert len(found) == len(rows) and {r.component_id for r in found} == {None, 100} | {i for i, _, _ in want}
    kept = [(r.doc_id, r.text) for r in corpus_pipeline.drop_near_duplicates(spark, docs, "").collect()]
    assert len(kept) == 12 + 3
    for i, long, short in want:
        of = [(k, t) for k, t in kept if t in (long, short)]
        assert len(of) == 1 and of[0][0] == i
    assert sum(t == same for _, t in kept) == 1 and sum(not (t or "").strip() for _, t in kept) == 1
