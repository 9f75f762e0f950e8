"""Accuracy and cost measures. Evaluation rows have dataset, series_id, method and score."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def score(cands: DataFrame, truth: DataFrame) -> DataFrame:
    """Adds score = 1 - min(1, |loc - true loc| / true length) to candidates; truth has dataset, series_id, true_loc, true_len."""
    got = cands.join(truth, [c for c in ("dataset", "series_id") if c in cands.columns])
    return got.withColumn("score", 1.0 - F.least(F.lit(1.0), F.abs(F.col("loc") - F.col("true_loc")) / F.col("true_len")))


def best_of(scores: DataFrame, k: int = 3) -> DataFrame:
    """Best score among the first k candidates of each series and method."""
    return scores.where(F.col("rank") <= k).groupBy("dataset", "series_id", "method").agg(F.max("score").alias("score"))


def average_score(best: DataFrame, by: tuple[str, ...] = ("dataset", "method")) -> DataFrame:
    return best.groupBy(*by).agg(F.avg("score").alias("avg_score"))


def hit_rate(scores: DataFrame, per: str = "series") -> DataFrame:
    """Share of series (or of candidates) with a positive score."""
    rows = best_of(scores) if per == "series" else scores
    return rows.groupBy("dataset", "method").agg(F.avg((F.col("score") > 0).cast("double")).alias("hit_rate"))


def paired(best: DataFrame, ref: str = "committee") -> DataFrame:
    """(dataset, series_id, method, ref_score, score): the reference beside every other method."""
    own = best.where(F.col("method") == ref).select("dataset", "series_id", F.col("score").alias("ref_score"))
    return best.where(F.col("method") != ref).join(own, ["dataset", "series_id"]).select("dataset", "series_id", "method", "ref_score", "score")


def win_tie_loss(best: DataFrame, ref: str = "committee") -> DataFrame:
    p = paired(best, ref)
    return p.groupBy("dataset", "method").agg(
        F.count_if(F.col("ref_score") > F.col("score")).alias("wins"),
        F.count_if(F.col("ref_score") == F.col("score")).alias("ties"),
        F.count_if(F.col("ref_score") < F.col("score")).alias("losses"),
    )


def one_sided_misses(best: DataFrame, ref: str = "committee") -> DataFrame:
    """How often one side has score zero and the other does not."""
    p = paired(best, ref)
    return p.groupBy("dataset", "method").agg(
        F.count_if((F.col("score") == 0) & (F.col("ref_score") > 0)).alias("missed_by_method"),
        F.count_if((F.col("ref_score") == 0) & (F.col("score") > 0)).alias("missed_by_ref"),
    )


def best_single(best: DataFrame, by: str = "wins", ref: str = "committee", exclude: tuple[str, ...] = ("discord",)) -> DataFrame:
    """Per dataset the single-run opponent of highest mean score, or the one against which the reference wins least, then loses most."""
    if by == "score":
        mean = average_score(best.where(~F.col("method").isin(ref, *exclude)))
        return mean.groupBy("dataset").agg(F.min(F.struct(-F.col("avg_score"), "method"))["method"].alias("method"))
    wtl = win_tie_loss(best, ref).where(~F.col("method").isin(*exclude))
    return wtl.groupBy("dataset").agg(F.min(F.struct("wins", (-F.col("losses")).alias("l"), "method"))["method"].alias("method"))


def repeat_spread(best: DataFrame) -> DataFrame:
    """Mean and deviation, over repeats, of the average score; rows have a column repeat."""
    per = best.groupBy("dataset", "method", "repeat").agg(F.avg("score").alias("avg_score"))
    return per.groupBy("dataset", "method").agg(F.avg("avg_score").alias("mean"), F.stddev_samp("avg_score").alias("sd"))


def truths_found(cands: DataFrame, truth: DataFrame, k: int = 3) -> DataFrame:
    """(dataset, series_id, found): true places overlapped by at least one of the first k candidates."""
    keys = [c for c in ("dataset", "series_id") if c in cands.columns]
    near = cands.where(F.col("rank") <= k).select(*keys, "lo", "hi")
    hit = truth.join(near, keys, "left").withColumn("hit", (F.col("lo") < F.col("true_loc") + F.col("true_len")) & (F.col("true_loc") <= F.col("hi")))
    per = hit.groupBy(*keys, "true_loc").agg(F.max(F.coalesce("hit", F.lit(False))).alias("hit"))
    return per.groupBy(*keys).agg(F.count_if("hit").alias("found"))


def compression(tokens: DataFrame, rules: DataFrame, windows: DataFrame) -> DataFrame:
    """(series_id, w, a, tokens, windows, grammar_size): what collapsing and induction leave."""
    keys = ["series_id", "w", "a"]
    t = tokens.groupBy(*keys).agg(F.count("*").alias("tokens"))
    g = rules.groupBy(*keys).agg(F.count("*").alias("grammar_size"))
    return t.join(g, keys).join(windows, "series_id").select(*keys, "tokens", "windows", "grammar_size")


def word_cost(n: int, w_max: int, a_max: int) -> dict[str, int]:
    """Additions and comparisons a window for all resolutions: from raw values, and with shared sums and one search."""
    depth = (len(_breaks(a_max)) + 1 - 1).bit_length()
    ws = range(2, w_max + 1)
    return {
        "direct": n * (w_max - 1) * (a_max - 1) + sum(w * (a - 1) for w in ws for a in range(2, a_max + 1)),
        "shared": sum(ws) + sum(w * depth for w in ws),
    }


def _breaks(a_max: int) -> tuple[float, ...]:
    from rarespan.functions.breakpoints import summary_breaks

    return summary_breaks(a_max)


def timed(df: DataFrame) -> float:
    """Seconds that computing all rows of ``df`` takes; the rows go nowhere."""
    import time

    begin = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - begin


def growth(times: DataFrame) -> DataFrame:
    """(method, exponent): slope of log seconds over log points; rows have method, points, seconds."""
    return times.groupBy("method").agg(F.regr_slope(F.log("seconds"), F.log("points")).alias("exponent"))
