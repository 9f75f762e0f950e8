"""Sliding windows, segment means and words of integer series, in DataFrame form.

A series has positions 1..N and integer values (cents, whole units), so that prefix sums are exact and the same in any
engine and any chunking. With T1 and T2 the sums of x and x*x over a window of n values, V = n * T2 - T1 * T1 and S_i the
sum over segment i times the number of segments w, the z-normalised segment mean is (S_i - T1) / sqrt(V * n / (n - 1)).
If w does not divide n, a boundary value is shared between its two segments in proportion. A window without spread has
coefficients of zero. Squares and V are decimals of 38 digits; window sums, times w, must stay below 2**63.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rarespan.functions.breakpoints import LETTERS, count_at_or_below, cuts, summary_breaks, symbol_matrix

_KEEP = ("series_id", "pos")


def _order() -> Window:
    return Window.partitionBy("series_id").orderBy("pos")


def windows(df: DataFrame, n: int, stride: int = 1) -> DataFrame:
    """(series_id, pos, values): the window that starts at each position 1..N-n+1, every ``stride``-th one."""
    over = _order().rowsBetween(0, n - 1)
    got = df.select(*_KEEP, F.collect_list("x").over(over).alias("values"))
    return got.where((F.size("values") == n) & ((F.col("pos") - 1) % stride == 0))


def _wide(c: Column) -> Column:
    return c.cast("decimal(38,0)")


def _square(c: Column) -> Column:
    return _wide(c) * c.cast("decimal(19,0)")


def prefix_sums(df: DataFrame) -> DataFrame:
    """Adds p1, p2: inclusive running sums of x and of its square."""
    over = _order().rowsBetween(Window.unboundedPreceding, 0)
    return df.withColumn("p1", F.sum("x").over(over)).withColumn("p2", F.sum(_square(F.col("x"))).over(over))


def _spread(t1: Column, t2: Column, n: int) -> Column:
    """V, which passes 64 bits where values do not: n * t2 - t1 * t1."""
    return F.lit(n).cast("decimal(10,0)") * t2 - _square(t1)


def _moments(df: DataFrame, n: int) -> DataFrame:
    """Direct window sums t1, t2 and v of the windows that fit; they read the window's own rows."""
    over = _order().rowsBetween(0, n - 1)
    t = df.withColumn("t1", F.sum("x").over(over)).withColumn("t2", F.sum(_square(F.col("x"))).over(over)).withColumn("len", F.count("*").over(over))
    return t.withColumn("v", _spread(F.col("t1"), F.col("t2"), n))


def coefficient(s: Column, t1: Column, v: Column, n: int, ddof: int = 1, flat_eps: float = 0.0) -> Column:
    """z-normalised segment mean from integer sums; zero for flat windows. ddof 0 takes the population deviation."""
    spread = F.sqrt(v.cast("double") * F.lit(n / (n - 1)) if ddof else v.cast("double"))
    return F.when(v <= flat_eps, F.lit(0.0)).otherwise((s - t1).cast("double") / F.when(v > flat_eps, spread))


def znorm(df: DataFrame, n: int, ddof: int = 1, flat_eps: float = 0.0) -> DataFrame:
    """(series_id, pos, z): the z-normalised values of each window."""
    m = _moments(df, n).withColumn("values", F.collect_list("x").over(_order().rowsBetween(0, n - 1))).where(f"len = {n}")
    return m.select(*_KEEP, F.transform("values", lambda x: coefficient(n * x, F.col("t1"), F.col("v"), n, ddof, flat_eps)).alias("z"))


def _bounds(n: int, w: int, segments: str) -> list[tuple[int, int]]:
    """(offset, share) of each segment boundary: ``share`` of w parts of the value at ``offset`` lie before it."""
    if segments == "floor":
        return [(i * n // w, 0) for i in range(w + 1)]
    return [divmod(i * n, w) for i in range(w + 1)]


def paa_naive(df: DataFrame, n: int, w: int, segments: str = "fractional") -> DataFrame:
    """(series_id, pos, coef): segment means from raw values, each by its own frame. The yard-stick for cost."""
    m = _moments(df, n)
    bounds = _bounds(n, w, segments)
    for i, ((lo, a), (hi, b)) in enumerate(zip(bounds, bounds[1:], strict=False)):
        whole = F.coalesce(F.sum("x").over(_order().rowsBetween(lo, hi - 1)), F.lit(0)) if hi > lo else F.lit(0)
        at = lambda k: F.lead("x", k).over(_order()) if k else F.col("x")
        total = w * whole
        if a:
            total = total - a * at(lo)
        if b:
            total = total + b * at(hi)
        if segments == "floor":
            total = total * F.lit(n) / F.lit(w * (hi - lo)) if n % w else total
        m = m.withColumn(f"s{i}", total)
    m = m.where(f"len = {n}")
    return m.select(*_KEEP, F.array(*(coefficient(F.col(f"s{i}"), F.col("t1"), F.col("v"), n) for i in range(w))).alias("coef"))


def with_coefficients(df: DataFrame, n: int, ws: list[int]) -> DataFrame:
    """Adds t1, v and for each w an array column coef{w}, from prefix sums.

    All boundaries of all w are offsets into the same two running sums, so one exchange and one sort serve every resolution.
    """
    if max(ws) > n:
        raise ValueError("w must not exceed n")
    p = prefix_sums(df)
    spots = sorted({q for w in ws for q, _ in _bounds(n, w, "fractional")} | {n})
    shared = sorted({q for w in ws for q, r in _bounds(n, w, "fractional") if r})
    over = _order()
    ahead = {q: F.coalesce(F.lag("p1", 1).over(over), F.lit(0)) if q == 0 else (F.lead("p1", q - 1).over(over) if q > 1 else F.col("p1")) for q in spots}
    cols = [F.col(c) for c in df.columns] + [ahead[q].alias(f"_p{q}") for q in spots]
    cols += [(F.lead("x", q).over(over) if q else F.col("x")).alias(f"_x{q}") for q in shared]
    zero = F.lit(0).cast("decimal(38,0)")
    t2 = (F.lead("p2", n - 1).over(over) if n > 1 else F.col("p2")) - F.coalesce(F.lag("p2", 1).over(over), zero)
    q = p.select(*cols, t2.alias("_t2")).where(F.col(f"_p{n}").isNotNull())
    q = q.withColumn("t1", F.col(f"_p{n}") - F.col("_p0")).withColumn("v", _spread(F.col("t1"), F.col("_t2"), n))
    for w in ws:
        edge = [w * F.col(f"_p{o}") + (r * F.col(f"_x{o}") if r else F.lit(0)) for o, r in _bounds(n, w, "fractional")]
        coef = [coefficient(b - a, F.col("t1"), F.col("v"), n) for a, b in zip(edge, edge[1:], strict=False)]
        q = q.withColumn(f"coef{w}", F.array(*coef))
    return q.drop(*[c for c in q.columns if c.startswith("_")])


def paa_fast(df: DataFrame, n: int, w: int) -> DataFrame:
    """(series_id, pos, coef): segment means from prefix sums."""
    return with_coefficients(df, n, [w]).select(*_KEEP, F.col(f"coef{w}").alias("coef"))


def word_of(coef: Column, a: int) -> Column:
    """Letters of an array of coefficients in one alphabet, concatenated."""
    letter = lambda c: F.substring(F.lit(LETTERS), count_at_or_below(c, cuts(a)) + 1, F.lit(1))
    return F.concat_ws("", F.transform(coef, letter))


def words(df: DataFrame, n: int, w: int, a: int) -> DataFrame:
    """(series_id, pos, word): the word of every window."""
    return with_coefficients(df, n, [w]).select(*_KEEP, word_of(F.col(f"coef{w}"), a).alias("word"))


def summary_index(coef: Column, a_max: int) -> Column:
    """Interval numbers among the summary cuts of all alphabets, one search for each coefficient."""
    return F.transform(coef, lambda c: count_at_or_below(c, summary_breaks(a_max)))


def letters_of(index: Column, a: Column | int, a_max: int) -> Column:
    """Word of an interval vector in alphabet ``a`` (a number or a column)."""
    table = symbol_matrix(a_max)
    if isinstance(a, int):
        row = F.lit("".join(LETTERS[r[a - 2]] for r in table))
    else:
        row = F.element_at(F.array(*(F.lit("".join(LETTERS[r[k]] for r in table)) for k in range(a_max - 1))), a - 1)
    return F.concat_ws("", F.transform(index, lambda i: F.substring(row, i + 1, F.lit(1))))


def word_matrix(coef: Column, a_max: int) -> Column:
    """All words of one coefficient vector, alphabets 2 .. a_max in turn."""
    index = summary_index(coef, a_max)
    return F.array(*(letters_of(index, a, a_max) for a in range(2, a_max + 1)))


def multires_words(df: DataFrame, n: int, ws: list[int], alphabets: list[int]) -> DataFrame:
    """(series_id, w, a, pos, word) of every window at every resolution, collapsed before the alphabets fan out.

    Per w the interval vector is compared with that of the window before: where it does not change, no alphabet's word can.
    The result holds the windows with a change only; ``collapse_runs`` finishes the job per alphabet.
    """
    a_max = max(alphabets)
    q = with_coefficients(df, n, ws)
    index = F.array(*(F.struct(F.lit(w).alias("w"), summary_index(F.col(f"coef{w}"), a_max).alias("ix")) for w in ws))
    flat = q.select(*_KEEP, F.inline(index))
    change = Window.partitionBy("series_id", "w").orderBy("pos")
    flat = flat.withColumn("before", F.lag("ix").over(change)).where(~F.col("ix").eqNullSafe(F.col("before")))
    fan = flat.select("series_id", "w", F.explode(F.array(*map(F.lit, alphabets))).alias("a"), "pos", "ix")
    return fan.select("series_id", "w", "a", "pos", letters_of(F.col("ix"), F.col("a"), a_max).alias("word"))


def collapse_runs(tokens: DataFrame, keys: list[str] | None = None, last: DataFrame | None = None) -> DataFrame:
    """First token of every run of equal words, with tok_ix (from 0), and run_end if ``last`` (series_id, last_pos) is given."""
    keys = keys or [k for k in ("series_id", "w", "a") if k in tokens.columns]
    over = Window.partitionBy(*keys).orderBy("pos")
    kept = tokens.withColumn("_b", F.lag("word").over(over)).where(~F.col("word").eqNullSafe(F.col("_b"))).drop("_b")
    kept = kept.withColumn("tok_ix", (F.row_number().over(over) - 1).cast("long"))
    if last is not None:
        kept = kept.withColumn("_n", F.lead("pos").over(over)).join(last, "series_id")
        kept = kept.withColumn("run_end", F.coalesce(F.col("_n") - 1, F.col("last_pos"))).drop("_n", "last_pos")
    return kept


def expand_runs(collapsed: DataFrame) -> DataFrame:
    """The full token sequence again, from tokens with run_end."""
    keep = [c for c in collapsed.columns if c not in ("pos", "run_end", "tok_ix")]
    return collapsed.select(*keep, F.explode(F.sequence("pos", "run_end")).alias("pos"))
