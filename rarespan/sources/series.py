"""Integer series (series_id, pos, x) from the given tables. Money is in cents or whole units, so that sums are exact."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rarespan.operators.layout import dealt_by, number_rows
from rarespan.runtime import table


def cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("long")


def units(c: str) -> Column:
    return F.round(F.col(c)).cast("long")


def regularize(df: DataFrame, fill: str = "zero") -> DataFrame:
    """A dense series from (series_id, step, x) with gaps: zero, last (carried forward), linear (between neighbours, rounded down), or drop."""
    bounds = df.groupBy("series_id").agg(F.min("step").alias("a"), F.max("step").alias("b"))
    over = Window.partitionBy("series_id").orderBy("step")
    if fill == "drop":
        return df.where("x is not null").select("series_id", F.row_number().over(over).cast("long").alias("pos"), "x")
    grid = bounds.select("series_id", "a", F.explode(F.sequence("a", "b")).alias("step"))
    got = grid.join(df, ["series_id", "step"], "left")
    if fill == "zero":
        x = F.coalesce("x", F.lit(0))
    else:
        back, ahead = over.rowsBetween(Window.unboundedPreceding, 0), over.rowsBetween(0, Window.unboundedFollowing)
        last = F.last("x", ignorenulls=True).over(back)
        if fill == "last":
            x = F.coalesce(last, F.lit(0))
        else:
            at = F.when(F.col("x").isNotNull(), F.col("step"))
            s0, s1 = F.last(at, ignorenulls=True).over(back), F.first(at, ignorenulls=True).over(ahead)
            nxt = F.first("x", ignorenulls=True).over(ahead)
            x = F.when(s0 == s1, last).otherwise(F.floor(last + (nxt - last) * (F.col("step") - s0) / F.when(s1 > s0, s1 - s0)))
            x = F.coalesce(x, last, nxt)
    return got.select("series_id", (F.col("step") - F.col("a") + 1).cast("long").alias("pos"), x.cast("long").alias("x"))


def _epoch(c: str, step: int) -> Column:
    return F.floor(F.unix_micros(F.col(c).cast("timestamp")) / (step * 1_000_000)).cast("long")


def from_events(spark: SparkSession, d: str, grain: str | None = "hour", by: str | None = None) -> DataFrame:
    """Sums of cents an hour (gaps zero), or the raw sequence by (ts, event_id) with grain None; one series or one for each ``by``."""
    e = table(spark, d, "events").select("event_id", "ts", "user_id", "event_type", "value")
    sid = F.col(by).cast("string") if by else F.lit("all")
    if grain is None or by == "user_id":
        rows = e.select(sid.alias("series_id"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), "event_id", cents("value").alias("x"))
        return number_rows(rows, ["t", "event_id"], "series_id" if by else None).select("series_id", "pos", "x")
    step = {"hour": 3600, "day": 86400}[grain]
    sums = e.groupBy(sid.alias("series_id"), _epoch("ts", step).alias("step")).agg(F.sum(cents("value")).alias("x"))
    return regularize(sums)


def from_orders(spark: SparkSession, d: str, form: str = "day", limit: int | None = None) -> DataFrame:
    """Whole-unit totals a day, or form="walk": the running sum of steps around their mean, in key order."""
    o = table(spark, d, "orders").select("o_orderkey", "o_orderdate", "o_totalprice")
    if form == "day":
        return regularize(o.groupBy(F.lit("all").alias("series_id"), _epoch("o_orderdate", 86400).alias("step")).agg(F.sum(units("o_totalprice")).alias("x")))
    mean = o.agg(F.expr("cast(floor(avg(cast(round(o_totalprice * 100) as bigint))) as bigint)")).first()[0] or 0
    steps = number_rows(o.select(F.lit("walk").alias("series_id"), "o_orderkey", F.expr(f"(cast(round(o_totalprice * 100) as bigint) - {mean}) div 1000000").alias("s")), ["o_orderkey"])
    if limit:
        steps = steps.where(F.col("pos") <= limit)
    return running_sums(steps, "s")


def running_sums(steps: DataFrame, value: str, chunk: int = 1 << 16) -> DataFrame:
    """(series_id, pos, x): running sums in two levels, inside chunks of positions and over the chunks' sums, so a window holds ``chunk`` rows or one row a chunk."""
    steps = steps.withColumn("_c", F.expr(f"(pos - 1) div {chunk}"))
    before = Window.partitionBy("series_id").orderBy("_c").rowsBetween(Window.unboundedPreceding, -1)
    base = steps.groupBy("series_id", "_c").agg(F.sum(value).alias("_t")).select("series_id", "_c", F.coalesce(F.sum("_t").over(before), F.lit(0)).alias("_base"))
    inside = Window.partitionBy("series_id", "_c").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    return steps.join(base, ["series_id", "_c"]).select("series_id", "pos", (F.col("_base") + F.sum(value).over(inside)).alias("x"))


def from_lineitem(spark: SparkSession, d: str, grain: str | None = None, by: str | None = None, limit: int | None = None) -> DataFrame:
    """Whole-unit prices in key order as one series, or quantities a ship day for each ``by``."""
    keys = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate"]
    li = table(spark, d, "lineitem")
    if grain == "day":
        sid = F.col(by) if by else F.lit("all")
        return regularize(li.groupBy(sid.alias("series_id"), _epoch("l_shipdate", 86400).alias("step")).agg(F.sum(units("l_quantity")).alias("x")))
    rows = number_rows(li.select(F.lit("lineitem").alias("series_id"), *keys, units("l_extendedprice").alias("x")), keys)
    return (rows.where(F.col("pos") <= limit) if limit else rows).select("series_id", "pos", "x")


def from_nation(spark: SparkSession, d: str, of: str = "customer") -> DataFrame:
    """Order totals for each nation and month, by the customer's nation or (through line items) the supplier's."""
    nation = table(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    o = table(spark, d, "orders")
    month = (F.year("o_orderdate") * 12 + F.month("o_orderdate")).cast("long")
    if of == "customer":
        c = table(spark, d, "customer").select("c_custkey", "c_nationkey")
        rows = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
        x = units("o_totalprice")
    else:
        li = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey", "l_extendedprice")
        s = table(spark, d, "supplier").select("s_suppkey", "s_nationkey")
        rows = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
        rows = rows.join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey"))
        x = units("l_extendedprice")
    return regularize(rows.groupBy(F.concat_ws("/", "r_name", "n_name").alias("series_id"), month.alias("step")).agg(F.sum(x).alias("x")))


def from_part_cycle(spark: SparkSession, d: str, period: int = 40, reps: int = 30, odd: int = 17) -> DataFrame:
    """Exactly periodic series from part sizes, one for every 2 x ``period`` parts in a row: the first half is the cycle, the second replaces the ``odd``-th (from 0)."""
    p = table(spark, d, "part").select(F.expr(f"p_partkey div {2 * period}").alias("block"), "p_partkey", F.col("p_size").cast("long").alias("x"))
    per = Window.partitionBy("block")
    p = p.select("block", (F.row_number().over(per.orderBy("p_partkey")) - 1).alias("i"), "x", F.count("*").over(per).alias("n")).where(F.col("n") == 2 * period).drop("n")
    usual, other = p.where(F.col("i") < period), p.where(F.col("i") >= period).withColumn("i", F.col("i") - period)
    rep = F.explode(F.sequence(F.lit(0), F.lit(reps - 1)))
    rows = usual.withColumn("rep", rep).where(F.col("rep") != odd).unionByName(other.withColumn("rep", F.lit(odd)))
    return rows.select(F.concat(F.lit("cycle-"), F.col("block").cast("string")).alias("series_id"), (F.col("rep") * period + F.col("i") + 1).cast("long").alias("pos"), "x")


def from_documents(spark: SparkSession, d: str, by: str = "lang") -> DataFrame:
    """Text lengths in order of doc_id, one series for each language or source."""
    rows = table(spark, d, "documents").select(F.coalesce(F.col(by), F.lit("")).alias("series_id"), "doc_id", F.col("n_chars").cast("long").alias("x"))
    return number_rows(rows, ["doc_id"], "series_id").select("series_id", "pos", "x")


def doc_words(spark: SparkSession, d: str, together: bool = False) -> DataFrame:
    """(series_id, pos, word): the words of each document, as tokens. ``together``: those of a document come next to each other and in order, since whole texts are shuffled before."""
    docs = table(spark, d, "documents").select(F.col("doc_id").cast("string").alias("series_id"), "text")
    if together:
        docs = dealt_by(docs, ["series_id"], [])
    t = docs.select("series_id", F.posexplode(F.split(F.trim("text"), r"\s+")).alias("p", "word"))
    return t.select("series_id", (F.col("p") + 1).cast("long").alias("pos"), "word")


def page_tags(spark: SparkSession, d: str) -> DataFrame:
    """(series_id, pos, word): the tags of each page, in order."""
    t = table(spark, d, "pages").select(F.col("page_id").cast("string").alias("series_id"), F.posexplode(F.regexp_extract_all("html", F.lit(r"</?([a-zA-Z][a-zA-Z0-9]*)"), F.lit(0))).alias("p", "word"))
    return t.select("series_id", (F.col("p") + 1).cast("long").alias("pos"), F.lower("word").alias("word"))


def conversation_roles(spark: SparkSession, d: str) -> DataFrame:
    """(series_id, pos, word): the roles of each conversation's turns."""
    over = Window.partitionBy("conv_id").orderBy("turn")
    return table(spark, d, "conversations").select(F.col("conv_id").cast("string").alias("series_id"), F.row_number().over(over).cast("long").alias("pos"), F.col("role").alias("word"))


def event_types(spark: SparkSession, d: str) -> DataFrame:
    """(series_id, pos, word): the event types of each user, by (ts, event_id)."""
    rows = table(spark, d, "events").select(F.col("user_id").cast("string").alias("series_id"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), "event_id", F.col("event_type").alias("word"))
    return number_rows(rows, ["t", "event_id"], "series_id").select("series_id", "pos", "word")
