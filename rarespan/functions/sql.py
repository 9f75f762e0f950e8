"""SQL surface: scalar functions over arrays, table functions over token tables, and their registration."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as St
from pyspark.sql.functions import pandas_udf, udtf

from rarespan.functions.breakpoints import LETTERS, count_at_or_below, cuts


def _row(**fields: St.DataType) -> St.StructType:
    """Types as objects: type strings could not be read before a session exists."""
    return St.StructType([St.StructField(k, t) for k, t in fields.items()])


def _let(value: Column, body) -> Column:
    """body(value) with the value computed once."""
    return F.transform(F.array(value), body)[0]


def znorm_array(xs: Column) -> Column:
    """z-normalised array (sample deviation); zeros for a flat one."""
    n = F.size(xs)
    total = F.aggregate(xs, F.lit(0.0), lambda s, x: s + x.cast("double"))

    def spread(mean: Column) -> Column:
        square = F.aggregate(xs, F.lit(0.0), lambda s, x: s + (x.cast("double") - mean) * (x.cast("double") - mean))
        return F.struct(mean.alias("mean"), F.sqrt(square / F.greatest(n - 1, F.lit(1))).alias("sd"))

    def scaled(m: Column) -> Column:
        return F.transform(xs, lambda x: F.when(m["sd"] > 0, (x - m["mean"]) / F.when(m["sd"] > 0, m["sd"])).otherwise(0.0))

    return _let(_let(total / n, spread), scaled)


def paa_array(xs: Column, w: int) -> Column:
    """Means of w equal segments; w must divide the array's length."""

    def means(v: Column) -> Column:
        step = (F.size(v) / w).cast("int")
        return F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda i: F.aggregate(F.slice(v, i * step + 1, step), F.lit(0.0), lambda s, x: s + x.cast("double")) / step)

    return _let(xs, means)


def word_array(xs: Column, w: int, a: int) -> Column:
    """The word of an array, in built-in functions only."""
    letter = lambda c: F.substring(F.lit(LETTERS), count_at_or_below(c, cuts(a)) + 1, F.lit(1))
    return F.concat_ws("", F.transform(paa_array(znorm_array(xs), w), letter))


@pandas_udf(St.StringType())
def symbolic_word(xs: pd.Series, w: pd.Series, a: pd.Series) -> pd.Series:
    """The word of an array with w and a as columns; any w up to the length."""
    import numpy as np

    out = []
    for x, k, m in zip(xs, w, a, strict=True):
        if x is None or len(x) < 2 or k > len(x):
            out.append(None)
            continue
        v = np.asarray(x, float)
        sd = v.std(ddof=1)
        z = (v - v.mean()) / sd if sd > 0 else np.zeros(len(v))
        coef = np.repeat(z, k).reshape(k, len(v)).mean(1)
        out.append("".join(LETTERS[i] for i in np.searchsorted(np.array(cuts(int(m))), coef, side="right")))
    return pd.Series(out, dtype=object)


@pandas_udf(St.LongType())
def grammar_size(words: pd.Series) -> int:
    """Symbols on all right sides of the grammar of a group's tokens, in the order given."""
    from rarespan.operators import kernel

    bodies, _ = kernel.grammar_rows(words)
    return sum(map(len, bodies.values()))


@udtf(returnType=_row(rule=St.IntegerType(), body=St.StringType(), uses=St.IntegerType(), series_id=St.StringType()))
class Induce:
    """induce(TABLE(t) PARTITION BY key ORDER BY pos): the rules of each partition, with its series_id if the table has one; the table has a column word."""

    def __init__(self):
        self.words: list[str] = []
        self.name = None

    def eval(self, row):
        self.words.append(row["word"])
        self.name = row["series_id"] if "series_id" in row else None

    def terminate(self):
        from collections import Counter

        from rarespan.operators import kernel

        bodies, names = kernel.grammar_rows(self.words)
        uses = Counter(v >> 1 for b in bodies.values() for v in b if v & 1)
        for r, body in bodies.items():
            yield r, " ".join(f"R{v >> 1}" if v & 1 else names[v >> 1] for v in body), uses[r], self.name


@udtf(returnType=_row(lo=St.LongType(), hi=St.LongType(), d=St.LongType()))
class RuleDensity:
    """rule_density(TABLE(t) PARTITION BY key ORDER BY pos, last): density runs of a partition's tokens; the table has pos and word."""

    def __init__(self):
        self.rows: list[tuple] = []
        self.last = 0

    def eval(self, row, last: int):
        self.rows.append((row["pos"], row["word"]))
        self.last = last

    def terminate(self):
        import numpy as np

        from rarespan.operators import kernel

        if self.rows:
            lo, hi, d = kernel.density_runs(np.array([r[0] for r in self.rows]), np.array([r[1] for r in self.rows], str), self.last)
            for row in zip(lo.tolist(), hi.tolist(), d.tolist(), strict=True):
                yield row


@udtf(returnType=_row(rank=St.IntegerType(), loc=St.LongType(), value=St.DoubleType()))
class Detect:
    """detect(TABLE(t) PARTITION BY series_id ORDER BY pos, n): committee candidates of a partition's series; the table has x."""

    def __init__(self):
        self.xs: list[int] = []
        self.n = 2

    def eval(self, row, n: int):
        self.xs.append(row["x"])
        self.n = n

    def terminate(self):
        import numpy as np

        from rarespan.operators import kernel
        from rarespan.operators.committee import draw_params

        for r, (i, v) in enumerate(kernel.committee_one(np.array(self.xs, np.int64), self.n, draw_params(50, w_cap=self.n), 0.4, 3)):
            yield r + 1, i + 1, v


def register_all(spark: SparkSession) -> None:
    """Makes symbolic_word, grammar_size, induce, rule_density and detect known to SQL."""
    spark.udf.register("symbolic_word", symbolic_word)
    spark.udf.register("grammar_size", grammar_size)
    spark.udtf.register("induce", Induce)
    spark.udtf.register("rule_density", RuleDensity)
    spark.udtf.register("detect", Detect)
