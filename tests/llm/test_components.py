import random

import pytest

from rarespan.llm.components import ONE_TASK, components


def roots_by_hand(edges):
    root = {x: x for e in edges for x in e}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    return {x: find(x) for x in root}


def shapes():
    r = random.Random(5)
    chain = [(i, i + 1) for i in range(300)]
    star = [(-7, 1000 + i) for i in range(200)] + [(5000, 2000 + i) for i in range(50)]
    loose = [(r.randrange(10_000, 10_400), r.randrange(10_000, 10_400)) for _ in range(220)]
    edges = chain + star + loose + [(-(2**63), 2**63 - 1), (42_000, 42_000), (1, 0), (1, 0)]
    r.shuffle(edges)
    return edges


@pytest.mark.parametrize("one_task", [ONE_TASK, 150, 0])
def test_roots_whether_the_rounds_or_one_task_ends_the_work(spark, one_task):
    edges = shapes()
    df = spark.createDataFrame([*edges, (None, 3), (3, None)], "a long, b long").repartition(5)
    rows = components(df, one_task=one_task).collect()
    got = {r["node"]: r["root"] for r in rows}
    assert len(rows) == len(got)
    assert got == roots_by_hand(edges)


@pytest.mark.parametrize("one_task", [ONE_TASK, 0])
def test_no_edges(spark, one_task):
    got = components(spark.createDataFrame([], "a long, b long"), one_task=one_task)
    assert got.columns == ["node", "root"]
    assert got.count() == 0
