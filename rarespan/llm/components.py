"""Connected components of an edge table, by contraction.

Each round points every node at the neighbour of smallest hash, follows the pointers three
times, renames the ends of the edges and drops what became a loop. A round costs a few shuffles of the
remaining edges. The hash is another one each round, so about a third of a chain's nodes are left after a round, whatever their order:
rounds grow with the logarithm of the longest path. Hubs are harmless: minima are aggregated on the
map side before any shuffle, and the joins meet one row per node.

Once at most ``ONE_TASK`` edges are left, whatever the input's size, one task ends the work with the same result: a round's
shuffles would cost far more than so few edges do. Nothing is sent to the driver.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rarespan.runtime import cut_in_loop, shuffle_partitions

ROWS = 100_000  # of a partition of what is left; later rounds are small and need not as many tasks and files as the first
ONE_TASK = 1 << 20  # edges that one task joins: about 150 MB there


def _join_all(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, root) for all edges (u, v) of the batches together: larger roots hang on the smallest root they meet, until no edge joins two."""
    ends = [(b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_numpy(zero_copy_only=False)) for b in batches]
    if not sum(len(u) for u, _ in ends):
        return
    u, v = (np.concatenate([e[i] for e in ends]) for i in range(2))
    names, at = np.unique(np.concatenate((u, v)), return_inverse=True)
    root, (x, y) = np.arange(len(names)), np.split(at, 2)
    while len(x):
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while (root[root] != root).any():
            root = root[root]
        x, y = root[x], root[y]
        x, y = x[x != y], y[x != y]
    for lo in range(0, len(names), 100_000):
        yield pa.RecordBatch.from_arrays([pa.array(names[lo : lo + 100_000]), pa.array(names[root[lo : lo + 100_000]])], ["node", "root"])


def _by_smallest(known: DataFrame) -> DataFrame:
    lowest = known.groupBy("root").agg(F.min("node").alias("low"))
    return known.join(lowest, "root").select("node", F.col("low").alias("root"))


def components(edges: DataFrame, max_rounds: int = 60, one_task: int = ONE_TASK) -> DataFrame:
    """Rows (node, root) for every node of ``edges`` (columns a, b); root is the component's smallest node.

    No edges give no rows. Loops and repeated edges are allowed; nulls are dropped. ``one_task`` steers the cost alone.
    """
    edges = cut_in_loop(
        edges.where("a is not null and b is not null")
        .select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
        .distinct()
    )
    known: DataFrame | None = None
    left, room = edges.count(), shuffle_partitions(edges.sparkSession)
    tasks = lambda n: max(1, min(room, -(-n // ROWS)))
    wide = tasks(2 * left)
    for r in range(max_rounds):
        if left <= one_task:
            ends = cut_in_loop(edges.select(F.col("u").cast("long"), F.col("v").cast("long")).coalesce(1).mapInArrow(_join_all, "node long, root long"))
            if known is None:
                return ends
            known = known.join(ends.select(F.col("node").alias("root"), F.col("root").alias("to")), "root", "left").select("node", F.coalesce("to", "root").alias("root"))
            return _by_smallest(known)
        few = tasks(2 * left)
        order = F.struct(F.xxhash64("to", F.lit(r)), "to")
        lowest = (
            edges.select(F.col("u").alias("node"), F.col("v").alias("to"))
            .unionAll(edges.select("v", "u"))
            .unionAll(edges.select("u", "u"))
            .unionAll(edges.select("v", "v"))
            .groupBy("node")
            .agg(F.min_by("to", order).alias("to"))
        )
        lowest = cut_in_loop(lowest.coalesce(few))
        jump = lowest
        for _ in range(2):
            far = jump.select(F.col("node").alias("to"), F.col("to").alias("far"))
            jump = jump.join(far, "to", "left").select("node", F.coalesce("far", "to").alias("to"))
        jump = cut_in_loop(jump.coalesce(few))
        if known is None:
            known = jump.select("node", F.col("to").alias("root"))
        else:
            moved = jump.select(F.col("node").alias("root"), "to")
            known = known.join(moved, "root", "left").select("node", F.coalesce("to", "root").alias("root"))
        left = jump.select(F.col("node").alias("u"), F.col("to").alias("x"))
        right = jump.select(F.col("node").alias("v"), F.col("to").alias("y"))
        edges = cut_in_loop(
            edges.join(left, "u")
            .join(right, "v")
            .where("x <> y")
            .select(F.greatest("x", "y").alias("u"), F.least("x", "y").alias("v"))
            .distinct()
            .coalesce(few)
        )
        known = cut_in_loop(known.coalesce(wide))
        left = edges.count()
        if not left:
            return _by_smallest(known)
    raise RuntimeError(f"components are not settled after {max_rounds} rounds")
