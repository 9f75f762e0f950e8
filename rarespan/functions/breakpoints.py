"""Equi-probable Gaussian cuts, their union over alphabets, and the letters of each interval.

Cuts are keyed by the reduced fraction k/a, so equal cuts of different alphabets are one
cut. Regions are closed on the left: a value's letter is the number of cuts at or below it.
"""

from __future__ import annotations

from fractions import Fraction
from functools import lru_cache
from statistics import NormalDist

from pyspark.sql import Column
from pyspark.sql import functions as F

LETTERS = "abcdefghijklmnopqrstuvwxyz"


@lru_cache(None)
def _value(share: Fraction) -> float:
    if share == Fraction(1, 2):
        return 0.0
    if share > Fraction(1, 2):
        return -_value(1 - share)
    return NormalDist().inv_cdf(float(share))


@lru_cache(None)
def cuts(a: int) -> tuple[float, ...]:
    """The a - 1 cuts of an alphabet of size a."""
    if not 2 <= a <= len(LETTERS):
        raise ValueError(f"alphabet size must be from 2 to {len(LETTERS)}")
    return tuple(_value(Fraction(k, a)) for k in range(1, a))


@lru_cache(None)
def summary_breaks(a_max: int) -> tuple[float, ...]:
    """Distinct cuts of all alphabets from 2 to a_max, ascending."""
    shares = sorted({Fraction(k, a) for a in range(2, a_max + 1) for k in range(1, a)})
    return tuple(_value(s) for s in shares)


@lru_cache(None)
def symbol_matrix(a_max: int) -> tuple[tuple[int, ...], ...]:
    """For each interval between summary cuts, its letter index in alphabets 2, 3 .. a_max."""
    shares = sorted({Fraction(k, a) for a in range(2, a_max + 1) for k in range(1, a)})
    rows = []
    for i in range(len(shares) + 1):
        low = shares[i - 1] if i else None
        rows.append(tuple(0 if low is None else int(low * a) for a in range(2, a_max + 1)))
    return tuple(rows)


def count_at_or_below(value: Column, sorted_cuts: tuple[float, ...]) -> Column:
    """Number of cuts <= value, as a balanced tree of comparisons."""

    def node(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(value >= F.lit(sorted_cuts[mid]), node(mid + 1, hi)).otherwise(node(lo, mid))

    return node(0, len(sorted_cuts))


def to_symbol(value: Column, a: int) -> Column:
    """The letter of a coefficient in an alphabet of size a."""
    return F.substring(F.lit(LETTERS), count_at_or_below(value, cuts(a)) + 1, F.lit(1))
