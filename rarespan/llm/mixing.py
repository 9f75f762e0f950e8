"""Mixing sources to target weights by pivotal dependent rounding, with DataFrame functions only.

A source with target t and size S gives each of its documents t / S copies on average. The whole part is
taken as it is; the fractional parts are rounded in pairs: some mass (words) moves from one document of the pair
to the other, in a random direction whose odds keep every expectation, until one of them is integral. The words taken by
the pair do not change. Documents are hashed into buckets of about ``FANOUT`` within their source; a bucket is
folded by such steps and hands one fractional document on. These are bucketed again, level by level, until each source
has a single one left, which is rounded by its own probability: a source misses its target by less than one document.
No group is larger than a bucket, however large its source.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rarespan.runtime import cut

FANOUT = 128
WEIGHTS = (5, 2, 1)
SHARE = 1.5
CAP = 2.0
WORD = r"[^\x20\x09-\x0D]+"
_TINY = 1e-12
_ITEM = "struct<doc_id:bigint,size:bigint,m:bigint,p:double>"
_STATE = f"struct<held:{_ITEM},done:array<struct<doc_id:bigint,size:bigint,up:int>>>"


def sizes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """(doc_id, source, size): words of each text, null texts zero."""
    size = F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long")
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).alias("source"), size.alias("size"))


def targets(sized: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, cap: float = CAP) -> DataFrame:
    """(source, source_size, n_items, target), one row per source.

    Sources in code-point order, null last, take the weights in turn. Together they get ``share`` of all words; none gets more
    than ``cap`` times its size, and what is cut off goes to the others by weight. Capped sources are those of smallest
    cap per weight, so a running sum in that order finds the common level. The windows run over one row per source.
    """
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_items"))
    turn = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*map(F.lit, map(float, weights))), (turn % len(weights)) + 1)
    every = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    order = Window.orderBy("ratio", F.col("source").asc_nulls_last())
    ranked = (
        per.withColumn("weight", weight)
        .withColumn("most", F.col("source_size") * F.lit(cap))
        .withColumn("ratio", F.col("most") / F.col("weight"))
        .withColumn("total", F.sum("source_size").over(every) * F.lit(share))
        .withColumn("before", F.coalesce(F.sum("most").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("open", F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("capped", F.col("ratio") * F.col("open") <= F.col("total") - F.col("before"))
        .withColumn("level", F.first(F.when(~F.col("capped"), (F.col("total") - F.col("before")) / F.col("open")), ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, 0)))
    )
    target = F.when(F.col("capped"), F.col("most")).otherwise(F.least(F.col("most"), F.col("level") * F.col("weight")))
    return ranked.select("source", "source_size", "n_items", target.alias("target"))


def _let(value: Column, body) -> Column:
    return F.element_at(F.transform(F.array(value), body), 1)


def _chance(*parts: Column) -> Column:
    """A uniform number in [0, 1) that depends on its arguments only."""
    return F.shiftrightunsigned(F.xxhash64(*parts), 11) / F.lit(float(1 << 53))


def _item(doc: Column, size: Column, m: Column, p: Column) -> Column:
    return F.struct(doc.alias("doc_id"), size.alias("size"), m.alias("m"), p.alias("p")).cast(_ITEM)


def _step(seed: int, level: int):
    """One transfer between the held document and the next one of the bucket."""

    def state(held: Column, done: Column) -> Column:
        return F.struct(held.alias("held"), done.alias("done")).cast(_STATE)

    def settled(done: Column, x: Column, up: int) -> Column:
        return F.concat(done, F.array(F.struct(x["doc_id"].alias("doc_id"), x["size"].alias("size"), F.lit(up).alias("up"))))

    def meet(acc: Column, y: Column) -> Column:
        x, done = acc["held"], acc["done"]
        sx, sy = (x["size"] * x["m"]).cast("double"), (y["size"] * y["m"]).cast("double")
        into_x = F.least((1 - x["p"]) * sx, y["p"] * sy)
        into_y = F.least((1 - y["p"]) * sy, x["p"] * sx)
        take = _chance(F.lit(seed), F.lit(level), x["doc_id"], x["size"], y["doc_id"], y["size"]) * (into_x + into_y) < into_y
        fills_x = (1 - x["p"]) * sx <= y["p"] * sy
        fills_y = (1 - y["p"]) * sy <= x["p"] * sx

        def moved(z: Column, p: Column) -> Column:
            return _item(z["doc_id"], z["size"], z["m"], F.greatest(F.lit(0.0), F.least(F.lit(1.0), p)))

        return (
            F.when(take & fills_x, state(moved(y, y["p"] - into_x / sy), settled(done, x, 1)))
            .when(take, state(moved(x, x["p"] + into_x / sx), settled(done, y, 0)))
            .when(fills_y, state(moved(x, x["p"] - into_y / sx), settled(done, y, 1)))
            .otherwise(state(moved(y, y["p"] + into_y / sy), settled(done, x, 0)))
        )

    return lambda acc, y: F.when(acc["held"].isNull(), state(_item(y["doc_id"], y["size"], y["m"], y["p"]), acc["done"])).otherwise(meet(acc, y))


def copies(sized: DataFrame, quota: DataFrame, seed: int = 17, fanout: int = FANOUT) -> DataFrame:
    """(source, doc_id, size, m, copies) for each distinct (source, doc_id, size); m rows of the input share it.

    ``quota`` has source, source_size and target; the same input and seed always give the same copies.
    """
    key = F.struct(F.col("source").isNull().alias("none"), F.coalesce(F.col("source"), F.lit("")).alias("name"))
    wanted = quota.withColumn("key", key).select("key", "source_size", "n_items", "target")
    items = sized.groupBy("source", "doc_id", "size").agg(F.count("*").alias("m")).withColumn("key", key).drop("source")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.when(F.col("source_size") > 0, F.col("source_size"))).otherwise(0.0)
    items = items.join(wanted, "key").withColumn("rate", rate)
    whole = F.floor(F.col("rate") + _TINY)
    items = items.withColumn("base", whole.cast("int")).withColumn("p", F.greatest(F.col("rate") - F.col("base"), F.lit(0.0)))
    items = cut(items.withColumn("nb", F.greatest(F.lit(1), F.ceil(F.col("n_items") / fanout))).select("key", "doc_id", "size", "m", "base", "p", "nb"))
    even = (F.col("p") <= _TINY) | (F.col("size") == 0)
    decided = [items.where(even).select("key", "doc_id", "size", F.lit(0).alias("up"))]
    rest = items.where(~even).select("key", "nb", "doc_id", "size", "m", "p")
    most = items.agg(F.max("nb")).first()[0] or 1
    level = 0
    while True:
        bucket = F.pmod(F.xxhash64(F.lit(seed), F.lit(level), "doc_id", "size"), F.col("nb"))
        order = F.xxhash64(F.lit(seed), F.lit(level), F.lit("order"), "doc_id", "size")
        row = F.struct(order.alias("o"), "doc_id", "size", "m", "p")
        zero = F.struct(F.lit(None).cast(_ITEM).alias("held"), F.array().cast("array<struct<doc_id:bigint,size:bigint,up:int>>").alias("done")).cast(_STATE)
        folded = cut(
            rest.groupBy("key", "nb", bucket.alias("bucket"))
            .agg(F.sort_array(F.collect_list(row)).alias("row"))
            .select("key", "nb", F.aggregate("row", zero, _step(seed, level)).alias("s"))
        )
        decided.append(folded.select("key", F.inline("s.done")))
        rest = folded.where("s.held is not null").select("key", F.ceil(F.col("nb") / fanout).alias("nb"), "s.held.*")
        if most == 1:
            break
        most = -(-most // fanout)
        level += 1
    last = F.when(_chance(F.lit(seed), F.lit(-1), F.col("doc_id"), F.col("size")) < F.col("p"), 1).otherwise(0)
    decided.append(rest.select("key", "doc_id", "size", last.alias("up")))
    ups = decided[0]
    for part in decided[1:]:
        ups = ups.unionByName(part)
    marked = items.select("key", "doc_id", "size", "m", "base", F.lit(0).alias("up")).unionByName(ups.select("key", "doc_id", "size", F.lit(0).alias("m"), F.lit(0).alias("base"), "up").where("up > 0"))
    out = marked.groupBy("key", "doc_id", "size").agg(F.sum("m").alias("m"), (F.sum("base") + F.sum("up")).alias("copies"))
    return out.select(F.when(~F.col("key.none"), F.col("key.name")).alias("source"), "doc_id", "size", "m", "copies")


def mixture(docs: DataFrame, seed: int = 17) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, copies, taken (= copies x size).

    Null texts have size zero; null sources form a source of their own, the last. Rows that share id, source and size get the same copies.
    Empty tables give no rows, and a source without words has target zero. Other columns are ignored.
    """
    sized = cut(sizes(docs))
    quota = cut(targets(sized))
    got = copies(sized, quota, seed).withColumn("row", F.explode(F.sequence(F.lit(1), F.col("m")))).drop("row", "m")
    name = quota.select(F.col("source").alias("s"), "source_size", "target")
    out = got.join(name, got["source"].eqNullSafe(name["s"]))
    return out.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).cast("long").alias("taken"))


def resample(docs: DataFrame, seed: int = 17) -> DataFrame:
    """The documents, each as often as its copies say; documents without words are kept once, whatever their source gets."""
    sized = cut(sizes(docs))
    got = copies(sized, cut(targets(sized)), seed).select(F.col("doc_id").alias("_id"), F.col("source").alias("_source"), F.col("size").alias("_size"), F.col("copies").alias("_copies"))
    size = F.coalesce(F.regexp_count(F.col("text"), F.lit(WORD)), F.lit(0)).cast("long")
    same = docs["doc_id"].eqNullSafe(got["_id"]) & docs["source"].eqNullSafe(got["_source"]) & (size == got["_size"])
    times = F.when(F.col("_size") == 0, 1).otherwise(F.col("_copies")).cast("int")
    return docs.join(got, same).withColumn("_times", F.explode(F.array_repeat(F.lit(1), times))).select(*docs.columns)
