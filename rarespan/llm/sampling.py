"""Bounded samples of labelled rows, chosen by a hash of their ids."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def bounded(rows: DataFrame, most: int, id_col: str = "doc_id") -> DataFrame:
    """The ``most`` rows of smallest id hash (all, if fewer); ids are distinct.

    Where there are more, a cut-off on the hash leaves about twice as many as needed before they are ordered, so what tasks send on does not grow with their number.
    """
    key, n = F.xxhash64(F.col(id_col)), rows.count()
    if n > 2 * most:
        span = 2.0**64
        rows = rows.where(key.cast("double") < F.lit(-(2.0**63) + span * (2.0 * most + 1000.0) / n))
    return rows.orderBy(key, id_col).limit(most)
