import random
import re

from rarespan.llm.mixing import mixture, resample


def brute_targets(per):
    order = sorted((s for s in per if s is not None)) + ([None] if None in per else [])
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    total, target, free = 1.5 * sum(per.values()), {}, set(order)
    while free:
        left = total - sum(target.values())
        w = sum(weight[s] for s in free)
        over = [s for s in free if left * weight[s] / w > 2 * per[s]]
        if not over:
            target |= {s: left * weight[s] / w for s in free}
            break
        for s in over:
            target[s] = 2.0 * per[s]
            free.discard(s)
    return target


def rows(seed, n):
    rnd = random.Random(seed)
    out = []
    for i in range(n):
        s = rnd.choice(["hot", "hot", "hot", "b", "c", "é", None, "tiny"]) if i % 97 else "rare"
        out.append((i, None if i % 50 == 0 else " \n".join("w" for _ in range(rnd.choice([0, 1, 3, 10, 80]))), "en", s, 0))
    return [*out, (3, out[3][1], "en", out[3][3], 0), (3, "other text", "fr", "b", 0)]


SCHEMA = "doc_id long, text string, lang string, source string, size long"


def test_targets_and_taken(spark):
    data = rows(1, 3000)
    df = spark.createDataFrame(data, SCHEMA)
    got = mixture(df).collect()
    size = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    assert sorted((r.doc_id, r.size) for r in got) == sorted((d[0], size(d[1])) for d in data)
    per = {}
    for d in data:
        per[d[3]] = per.get(d[3], 0) + size(d[1])
    want = brute_targets(per)
    taken = dict.fromkeys(per, 0)
    for r in got:
        assert r.source_size == per[r.source] and abs(r.target - want[r.source]) < 1e-6
        assert 0 <= r.taken <= 2 * r.size and (r.size == 0 or r.taken % r.size == 0)
        taken[r.source] += r.taken
    assert all(abs(taken[s] - want[s]) <= 2 * 80 for s in per)
    assert sorted(map(tuple, mixture(df.repartition(3)).collect()), key=str) == sorted(map(tuple, got), key=str)


def test_chances_are_kept(spark):
    df = spark.createDataFrame([(i, "w " * (1 + i % 7), "en", "ab"[i % 2], 0) for i in range(400)], SCHEMA)
    mean = {}
    for seed in range(6):
        for r in mixture(df, seed).collect():
            mean.setdefault(r.source, []).append((r.taken, r.target / r.source_size * r.size))
    for pairs in mean.values():
        assert abs(sum(a - b for a, b in pairs)) < 60


def test_edges(spark):
    df = spark.createDataFrame([], SCHEMA)
    assert mixture(df).collect() == [] and resample(df).collect() == []
    one = spark.createDataFrame([(1, None, None, None, 7)], SCHEMA)
    assert [(r.size, r.taken, r.target) for r in mixture(one).collect()] == [(0, 0, 0.0)]


def test_resample_follows_copies(spark):
    df = spark.createDataFrame(rows(2, 500), SCHEMA)
    want = {}
    for r in mixture(df).collect():
        want[r.doc_id] = want.get(r.doc_id, 0) + (r.copies if r.size else 1)
    got = {}
    for r in resample(df).collect():
        got[r.doc_id] = got.get(r.doc_id, 0) + 1
    assert got == {k: v for k, v in want.items() if v}
