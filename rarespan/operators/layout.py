"""Cutting long series into chunks with a halo, and numbering rows in order, without a task for the whole table."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rarespan.runtime import shuffle_partitions

CORE = 1 << 18


def with_chunks(df: DataFrame, n: int, core: int = CORE) -> DataFrame:
    """Adds chunk (from 0): positions c*core+1 .. (c+1)*core, and for windows of n values also the n - 1 that follow.

    Each row is sent to its own chunk and to those before it that reach over to it; no second shuffle is needed.
    """
    own = F.expr(f"(pos - 1) div {core}")
    back = F.greatest(F.lit(0), F.expr(f"(pos - {n}) div {core}")) if n > 1 else own
    lowest = F.when(F.col("pos") - n < 0, F.lit(0)).otherwise(back)
    return df.withColumn("chunk", F.explode(F.sequence(F.least(lowest, own), own)))


def bucket_of(value: Column, bounds: list) -> Column:
    """How many of the ascending bounds lie below the value, by a search in two levels."""
    if not bounds:
        return F.lit(0)
    width = math.isqrt(len(bounds)) + 1
    rows = [bounds[i : i + width] for i in range(0, len(bounds), width)]
    below = lambda values: F.size(F.filter(values, lambda b: b < value))
    array = lambda values: F.array(*map(F.lit, values))
    head = below(array([r[-1] for r in rows]))
    inner = F.element_at(F.array(*map(array, [*rows, rows[-1]])), head + 1)
    return F.when(head == len(rows), F.lit(len(bounds))).otherwise(head * width + below(inner))


def number_rows(df: DataFrame, order: list[str], by: str | None = None, name: str = "pos") -> DataFrame:
    """Adds dense numbers from 1 in the given order, within ``by`` if named, else over the whole table.

    The first order column (numeric) is cut into ranges at approximate quantiles; rows are numbered within their range, and the ranges' sizes, one
    row each, give the offsets.
    """
    if by is not None:
        return df.withColumn(name, F.row_number().over(Window.partitionBy(by).orderBy(*order)).cast("long"))
    n = min(1024, 4 * shuffle_partitions(df.sparkSession))
    lead = F.col(order[0]).cast("double")
    found = df.agg(F.percentile_approx(lead, [i / n for i in range(1, n)], 10 * n)).first()[0]
    bounds = sorted(set(found or []))
    ranged = df.withColumn("_range", bucket_of(lead, bounds))
    sizes = {r["_range"]: r["count"] for r in ranged.groupBy("_range").count().collect()}
    offsets, total = [0] * (len(bounds) + 1), 0
    for k in range(len(bounds) + 1):
        offsets[k] = total
        total += sizes.get(k, 0)
    at = F.element_at(F.array(*map(F.lit, offsets)).cast("array<bigint>"), F.col("_range") + 1)
    inside = F.row_number().over(Window.partitionBy("_range").orderBy(*order))
    return ranged.withColumn(name, at + inside).drop("_range")


def codes(column: pa.Array) -> np.ndarray:
    """A number for each value, equal where values are; nulls are one value."""
    return column.dictionary_encode(null_encoding="encode").indices.to_numpy(zero_copy_only=False)


def group_starts(batch: pa.RecordBatch | pa.Table, keys: list[str]) -> list[int]:
    """Where each stretch of rows with the same keys begins, and the number of rows."""
    edge = np.zeros(batch.num_rows, bool)
    edge[:1] = True
    for k in keys:
        c = codes(batch.column(k))
        edge[1:] |= c[1:] != c[:-1]
    return [*np.flatnonzero(edge).tolist(), batch.num_rows]


def whole_groups(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[tuple[pa.RecordBatch, list[int]]]:
    """(rows, where each group begins and the last ends) of rows that come group by group: no group is cut, and many short ones come together."""
    held: list[pa.RecordBatch] = []

    def joined() -> tuple[pa.RecordBatch, list[int]]:
        one = held[0] if len(held) == 1 else pa.Table.from_batches(held).combine_chunks().to_batches()[0]
        return one, group_starts(one, keys)

    for batch in batches:
        if not batch.num_rows:
            continue
        last = group_starts(batch, keys)[-2]
        if held and (last or any(held[-1].column(k)[-1] != batch.column(k)[0] for k in keys)):
            first = group_starts(batch, keys)[1] if all(held[-1].column(k)[-1] == batch.column(k)[0] for k in keys) else 0
            if first:
                held.append(batch.slice(0, first))
            yield joined()
            held, batch, last = [], batch.slice(first), last - first
        if last > 0:
            held = [batch.slice(0, last)]
            yield joined()
            held, batch = [], batch.slice(last)
        if batch.num_rows:
            held.append(batch)
    if held:
        yield joined()


def dealt_by(df: DataFrame, keys: list[str], order: list[str]) -> DataFrame:
    """Rows of a group together and in order, the groups dealt to all tasks; small in bytes, long in work, so not to be coalesced."""
    return df.repartition(shuffle_partitions(df.sparkSession), *keys).sortWithinPartitions(*keys, *order)
