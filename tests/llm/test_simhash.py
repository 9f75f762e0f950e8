import random
import re

import xxhash
from pyspark.sql import types as T

from rarespan.llm.simhash import near_duplicates

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("fp", T.StringType())])


def fingerprint(text, k=3):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", low)
    grams = [" ".join(w[i : i + k]) for i in range(max(1, len(w) - k + 1))] if w else []
    if not grams:
        return 0
    h = [xxhash.xxh64_intdigest(g.encode(), seed=42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute(rows):
    fps = [fingerprint(r[1]) for r in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if bin(fps[i] ^ fps[j]).count("1") <= 3:
                root[find(i)] = find(j)
    low = {}
    for i, r in enumerate(rows):
        low[find(i)] = min(low.get(find(i), r[0]), r[0])
    return sorted((r[0], fps[i], low[find(i)]) for i, r in enumerate(rows))


def got(df):
    return sorted((r.doc_id, r.fp & (2**64 - 1), r.component_id) for r in df.collect())


def test_equals_brute_force(spark):
    rnd = random.Random(5)
    vocab = [f"w{i}é" for i in range(300)]
    rows, i = [], 0
    for _ in range(40):
        base = [rnd.choice(vocab) for _ in range(rnd.choice([1, 2, 3, 40, 400]))]
        for _ in range(rnd.choice([1, 1, 2, 9, 25])):
            copy = list(base)
            for _ in range(rnd.choice([0, 1, 2])):
                copy[rnd.randrange(len(copy))] = rnd.choice(vocab)
            rows.append((i, rnd.choice([" ", "\n", "  "]).join(copy).upper(), "x"))
            i += 1
    rows += [(i, "", "x"), (i + 1, None, "x"), (i + 2, " \t\n", None), (5, rows[5][1], "again")]
    assert got(near_duplicates(spark.createDataFrame(rows, SCHEMA))) == brute(rows)


def test_empty_table(spark):
    assert near_duplicates(spark.createDataFrame([], SCHEMA)).collect() == []
