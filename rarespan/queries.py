"""Registered queries: each applies an operator, baseline, measure or workload to the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rarespan import oracles as o
from rarespan.functions import breakpoints as bp
from rarespan.operators import candidates as cand
from rarespan.operators import committee as com
from rarespan.operators import density as den
from rarespan.operators import discord, measures
from rarespan.operators import rounds as rnd
from rarespan.operators import windows as win
from rarespan.plans import detect
from rarespan.plans import workloads as wl
from rarespan.runtime import cut, cut_in_loop, table
from rarespan.sources import series as src

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}

N = 24
PAIRS = [(2, 3), (3, 3), (4, 4), (5, 7), (8, 6)]

SERIES: dict[str, Query] = {
    "events_hour": lambda s, d: src.from_events(s, d),
    "events_type_hour": lambda s, d: src.from_events(s, d, by="event_type"),
    "events_seq": lambda s, d: src.from_events(s, d, None),
    "events_user": lambda s, d: src.from_events(s, d, None, "user_id"),
    "orders_day": lambda s, d: src.from_orders(s, d),
    "orders_walk": lambda s, d: src.from_orders(s, d, "walk"),
    "lineitem_seq": lambda s, d: src.from_lineitem(s, d),
    "lineitem_day": lambda s, d: src.from_lineitem(s, d, "day", "l_returnflag"),
    "nation_month": lambda s, d: src.from_nation(s, d),
    "supplier_month": lambda s, d: src.from_nation(s, d, "supplier"),
    "part_cycle": lambda s, d: src.from_part_cycle(s, d),
    "doc_lengths": lambda s, d: src.from_documents(s, d),
}
TOKENS: dict[str, Query] = {"doc_words": src.doc_words, "page_tags": src.page_tags, "conv_roles": src.conversation_roles}


def add(name: str, query: Query, oracle: str | None = None):
    QUERIES[name] = query
    if oracle is not None:
        ORACLE_SQL[name] = oracle


for i, (_name, _q) in enumerate(SERIES.items(), 1):
    add(f"s{i:02d}_{_name}", _q, o.series(_name))
for _name, _q in TOKENS.items():
    add(f"s13_{_name}", _q, o.tokens(_name))


def _hour(s, d):
    return SERIES["events_hour"](s, d)


def _collapsed(df: DataFrame, n: int, w: int, a: int) -> DataFrame:
    t = win.words(df, n, w, a).select("series_id", F.lit(w).alias("w"), F.lit(a).alias("a"), "pos", "word")
    return win.collapse_runs(t, last=detect.series_ends(df))


def _coef_columns(df: DataFrame, w: int) -> DataFrame:
    return df.select("series_id", "pos", *(F.round(F.col("coef")[i], 9).alias(f"c{i}") for i in range(w)))


add("m01_windows", lambda s, d: win.windows(SERIES["orders_day"](s, d), 30).select("series_id", "pos", F.aggregate("values", F.lit(0).cast("long"), lambda a, x: a + x).alias("total")),
    f"with {o.SERIES['orders_day']}, z as (select series_id, pos, cast(sum(x) over (partition by series_id order by pos rows between current row and 29 following) as bigint) as total, count(*) over (partition by series_id order by pos rows between current row and 29 following) as len from s) select series_id, pos, total from z where len = 30")
add("m02_znorm", lambda s, d: win.znorm(_hour(s, d), N).select("series_id", "pos", F.round(F.col("z")[0], 9).alias("first"), F.round(F.array_max("z"), 9).alias("top")),
    f"with {o.SERIES['events_hour']}, z as (select series_id, pos, x, avg(x) over w as mu, stddev_samp(x) over w as sd, max(x) over w as mx, count(*) over w as len from s window w as (partition by series_id order by pos rows between current row and 23 following)) select series_id, pos, round((x - mu) / sd, 9) as first, round((mx - mu) / sd, 9) as top from z where len = 24")
add("m03_paa_naive", lambda s, d: _coef_columns(win.paa_naive(SERIES["events_type_hour"](s, d), N, 4), 4), o.paa("events_type_hour", N, 4))
add("m03b_paa_shared_edges", lambda s, d: _coef_columns(win.paa_naive(SERIES["orders_day"](s, d), 30, 7), 7), o.paa("orders_day", 30, 7))
add("m05_words", lambda s, d: win.words(_hour(s, d), N, 4, 4), o.words("events_hour", N, 4, 4))
add("m06_words_many_series", lambda s, d: win.words(SERIES["events_user"](s, d), 10, 3, 4), o.words("events_user", 10, 3, 4))
add("m07_collapse", lambda s, d: _collapsed(SERIES["lineitem_day"](s, d), 30, 3, 3), o.collapsed("lineitem_day", 30, 3, 3))
add("m07b_expand", lambda s, d: win.expand_runs(_collapsed(_hour(s, d), N, 2, 3)).select("series_id", "pos", "word"), o.expanded("events_hour", N, 2, 3))
add("m09_paa_fast", lambda s, d: _coef_columns(win.paa_fast(SERIES["nation_month"](s, d), 12, 5), 5), o.paa("nation_month", 12, 5))
add("m10_summary_breaks", lambda s, d: s.createDataFrame([(i + 1, round(x, 12)) for i, x in enumerate(bp.summary_breaks(10))], "ix int, cut double"), o.summary_breaks_sql(10))
add("m11_symbol_matrix", lambda s, d: s.createDataFrame([(i, a + 2, bp.LETTERS[x]) for i, r in enumerate(bp.symbol_matrix(10)) for a, x in enumerate(r)], "ix int, a int, letter string"), o.symbol_matrix_sql(10))


def _multires(s: SparkSession, d: str) -> DataFrame:
    words = win.multires_words(_hour(s, d), N, [w for w, _ in PAIRS], sorted({a for _, a in PAIRS}))
    some = words.where(F.struct("w", "a").isin(*[F.struct(F.lit(w), F.lit(a)) for w, a in PAIRS]))
    return win.collapse_runs(some).select("series_id", "w", "a", "tok_ix", "word")


def _kernel_words(s: SparkSession, d: str, name: str, n: int, core: int) -> DataFrame:
    t = detect.tokens_by_kernel(SERIES[name](s, d), n, PAIRS, core)
    return win.collapse_runs(t).select("series_id", "w", "a", "tok_ix", "word")


add("m12_multires", _multires, o.tokens_of("events_hour", N, PAIRS))
add("m12b_word_matrix", lambda s, d: s.createDataFrame([([-1.0, -0.2, 0.8],)], "c array<double>").select(F.posexplode(win.word_matrix(F.col("c"), 4)).alias("p", "word")).select((F.col("p") + 2).cast("int").alias("a"), "word"),
    "select cast(a as int) as a, word from (values (2, 'aab'), (3, 'abc'), (4, 'abd')) v(a, word)")
add("m13_kernel_words", lambda s, d: _kernel_words(s, d, "events_type_hour", N, 100), o.tokens_of("events_type_hour", N, PAIRS))

_TOY = "aa bb cc xx aa bb cc".split()
_EXAMPLE = list(zip("ab bc aa cc ca ab bc aa".split(), (1, 8, 15, 21, 25, 29, 34, 40), strict=True))


def _literal(s: SparkSession, rows: list[tuple[str, int]]) -> DataFrame:
    return s.createDataFrame([("s", 2, 3, p, w) for w, p in rows], "series_id string, w int, a int, pos long, word string")


def _ends(s: SparkSession, last: int) -> DataFrame:
    return s.createDataFrame([("s", last)], "series_id string, last_pos long")


def _bodies(rules: DataFrame) -> DataFrame:
    return rules.groupBy("rule").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ix", "sym"))), lambda x: x["sym"]), " ").alias("body"))


add("m14_toy_grammar", lambda s, d: _bodies(den.grammars(_literal(s, [(w, i + 1) for i, w in enumerate(_TOY)]))), "select cast(r as int) as rule, b as body from (values (0, 'R1 xx R1'), (1, 'aa bb cc')) v(r, b)")
add("m14_example_grammar", lambda s, d: _bodies(den.grammars(_literal(s, _EXAMPLE))), "select cast(r as int) as rule, b as body from (values (0, 'R1 cc ca R1'), (1, 'ab bc aa')) v(r, b)")
add("m18_uncovered", lambda s, d: den.uncovered(den.density(_literal(s, _EXAMPLE), _ends(s, 60))).select("lo", "hi"), "select cast(21 as bigint) as lo, cast(28 as bigint) as hi")
add("m19_spans", lambda s, d: den.rule_spans(win.collapse_runs(_literal(s, _EXAMPLE), last=_ends(s, 60))).select("rule", "lo", "hi"), "select cast(r as int) as rule, cast(a as bigint) as lo, cast(b as bigint) as hi from (values (1, 1, 20), (1, 29, 60)) v(r, a, b)")
add("m20_density_example", lambda s, d: den.density(_literal(s, _EXAMPLE), _ends(s, 60)).select("lo", "hi", "d"), "select cast(a as bigint) as lo, cast(b as bigint) as hi, cast(c as bigint) as d from (values (1, 20, 1), (21, 28, 0), (29, 60, 1)) v(a, b, c)")


def _tokens(s, d, pairs=((3, 3), (4, 4))):
    return win.collapse_runs(detect.tokens_by_kernel(_hour(s, d), N, list(pairs)))


add("m14a_digram_violations", lambda s, d: den.digram_violations(den.grammars(_tokens(s, d))), "select '' as series_id, 0 as w, 0 as a, '' as sym, '' as nxt, cast(0 as bigint) as times where false")
add("m14b_utility_violations", lambda s, d: den.utility_violations(den.grammars(_tokens(s, d))), "select '' as series_id, 0 as w, 0 as a, '' as sym, cast(0 as bigint) as count where false")
add("m15_roundtrip", lambda s, d: den.expand_grammar(den.grammars(_tokens(s, d))), o.tokens_of("events_hour", N, [(3, 3), (4, 4)]))


def _roundtrip(tokens: DataFrame, together: bool = False) -> DataFrame:
    rules = den.grammars(tokens.withColumn("w", F.lit(0)).withColumn("a", F.lit(0)), together)
    return den.expand_grammar(rules, together).select("series_id", (F.col("tok_ix") + 1).alias("pos"), "word")


add("m15_roundtrip_doc_words", lambda s, d: _roundtrip(src.doc_words(s, d, together=True), together=True), o.tokens("doc_words"))
for _name in ("page_tags", "conv_roles"):
    add(f"m15_roundtrip_{_name}", lambda s, d, q=TOKENS[_name]: _roundtrip(q(s, d)), o.tokens(_name))


def _span_density(s: SparkSession, d: str) -> DataFrame:
    """Where the swept spans and the token depths disagree, and the points covered a member."""
    df = _hour(s, d)
    t, ends = win.collapse_runs(detect.tokens_by_kernel(df, N, [(2, 3), (3, 3), (4, 4)]), last=detect.series_ends(df)), detect.series_ends(df)
    one, two = den.density(t, ends), den.density_from_spans(den.rule_spans(t), ends)
    off = one.where("d > 0").exceptAll(two.where("d > 0").select(*one.columns)).groupBy("series_id", "w", "a").agg(F.count("*").alias("off"))
    pts = one.groupBy("series_id", "w", "a").agg(F.sum(F.col("hi") - F.col("lo") + 1).alias("points"))
    return pts.join(off, ["series_id", "w", "a"], "left").select("series_id", "w", "a", "points", F.coalesce("off", F.lit(0)).cast("long").alias("off"))


add("m20_density", _span_density, f"with {o.SERIES['events_hour']} select 'all' as series_id, w, a, (select count(*) from s) as points, cast(0 as bigint) as off from (values (2, 3), (3, 3), (4, 4)) v(w, a)")
_ROUNDS = 10
add("m16_rounds", lambda s, d: rnd.induce_rounds(_collapsed(_hour(s, d), N, 3, 3), _ROUNDS)[0], o.rounds_sequence("events_hour", N, 3, 3, _ROUNDS))
add("m16_rounds_density", lambda s, d: rnd.density_by_rounds(_collapsed(_hour(s, d), N, 3, 3), _ROUNDS).groupBy("series_id", "d").agg(F.sum(F.col("hi") - F.col("lo") + 1).alias("points")), o.rounds_density("events_hour", N, 3, 3, _ROUNDS))
add("m23_single_rounds", lambda s, d: cand.top_windows(cand.window_values(rnd.density_by_rounds(_collapsed(SERIES["events_type_hour"](s, d), N, 3, 3), _ROUNDS).select("series_id", "lo", "hi", F.col("d").cast("double").alias("de")), N), N), o.rounds_single("events_type_hour", N, 3, 3, _ROUNDS))
add("m20_density_windows", lambda s, d: den.density(_tokens(s, d), detect.series_ends(_hour(s, d)), "window_span", N))
add("m20b_rules_once", lambda s, d: den.density_from_spans(den.rule_spans(win.collapse_runs(_literal(s, _EXAMPLE), last=_ends(s, 60)), "window_span", 16), _ends(s, 60), "rules").select("lo", "hi", "d"), "select cast(a as bigint) as lo, cast(b as bigint) as hi, cast(c as bigint) as d from (values (1, 55, 1), (56, 60, 0)) v(a, b, c)")
add("m21_single_plateaus", lambda s, d: cand.plateaus(den.density(_tokens(s, d, [(3, 3)]), detect.series_ends(_hour(s, d))).withColumn("de", F.col("d").cast("double")), 10))
add("m23_single", lambda s, d: detect.detect_single(SERIES["part_cycle"](s, d), 40, 4, 4))
add("m17_chunked", lambda s, d: detect.detect_single(SERIES["orders_walk"](s, d), 100, 4, 4, part=4096))
add("m24_params", lambda s, d: s.createDataFrame([(i + 1, w, a) for i, (w, a) in enumerate(com.draw_params(50))], "rank int, w int, a int"),
    "select cast(row_number() over (order by md5('42:' || w || ':' || a)) as int) as rank, cast(w as int) as w, cast(a as int) as a from (select unnest(generate_series(2, 10)) as w), (select unnest(generate_series(2, 10)) as a) qualify rank <= 50")


def _frequencies(s: SparkSession, d: str) -> DataFrame:
    """Curves that SQL can state: how many windows of the series share each window's word."""
    df = win.with_coefficients(_hour(s, d), N, sorted({w for w, _ in PAIRS}))
    each = [df.select("series_id", F.lit(w).alias("w"), F.lit(a).alias("a"), "pos", win.word_of(F.col(f"coef{w}"), a).alias("word")) for w, a in PAIRS]
    flat = wl._union(each).withColumn("d", F.count("*").over(Window.partitionBy("series_id", "w", "a", "word")))
    return cut(flat.select("series_id", "w", "a", F.col("pos").alias("lo"), F.col("pos").alias("hi"), "d"))


def _kept_curves(s, d, norm="max"):
    runs = _frequencies(s, d)
    return com.scaled(runs, com.keep_by_spread(com.curve_stats(runs), 0.6), norm)


def _combined(s, d, how="median"):
    return com.combine(_kept_curves(s, d), how, segment=100)


def _points(runs: DataFrame) -> DataFrame:
    return runs.select("series_id", F.explode(F.sequence("lo", "hi")).alias("pos"), F.round("de", 9).alias("de"))


add("c10_curve_spread", lambda s, d: com.deviation(com.curve_stats(_frequencies(s, d))).withColumn("spread", F.col("spread").cast("double")).select("series_id", "w", "a", "len", "total", "top", "spread", F.round("sd", 9).alias("sd"), F.round("level", 9).alias("level")), o.curve_stats("events_hour", N, PAIRS))
add("m25_keep", lambda s, d: com.keep_by_spread(com.curve_stats(_frequencies(s, d)), 0.6).select("series_id", "w", "a", F.col("spread").cast("double").alias("spread"), "rank"), o.keep("events_hour", N, PAIRS, 0.6))
for _norm, _key in (("max", "m26_scale"), ("minmax", "m26b_minmax"), ("none", "m26c_unscaled")):
    add(_key, lambda s, d, n=_norm: _kept_curves(s, d, n).select("series_id", "w", "a", F.col("lo").alias("pos"), F.round("v", 9).alias("v")), o.scale("events_hour", N, PAIRS, 0.6, _norm))
for _how, _key in (("median", "m27_median"), ("mean", "m27b_mean"), ("min", "m27b_min"), ("max", "m27b_max")):
    add(_key, lambda s, d, h=_how: _points(_combined(s, d, h)), o.combine("events_hour", N, PAIRS, 0.6, _how))
add("m21_plateaus", lambda s, d: cand.plateaus(_combined(s, d).withColumn("de", F.round("de", 9))), o.plateaus("events_hour", N, PAIRS, 0.6))
add("m22_topk", lambda s, d: cand.top_windows(cand.window_values(_points(_combined(s, d)).select("series_id", F.col("pos").alias("lo"), F.col("pos").alias("hi"), F.round("de", 6).alias("de")), N).withColumn("value", F.round("value", 6)), N), o.top_windows("events_hour", N, PAIRS, 0.6))
add("m28_committee", lambda s, d: detect.detect_committee(SERIES["part_cycle"](s, d), 40))


_TRIO = [(2, 3), (3, 3), (4, 3)]


def _committee_by_rounds(s: SparkSession, d: str) -> DataFrame:
    df = SERIES["part_cycle"](s, d)
    t = win.collapse_runs(detect.tokens_by_kernel(df, 40, _TRIO), last=detect.series_ends(df))
    runs = cut_in_loop(rnd.density_by_rounds(t, 8))
    curve = com.combine(com.scaled(runs, com.keep_by_spread(com.curve_stats(runs), 0.6)))
    # one kernel call a series: point by point, each candidate's plan would hold those of all before it, twice
    return cand.window_candidates(curve.withColumn("de", F.round("de", 6)), 40).withColumn("value", F.round("value", 6))


add("m28_committee_rounds", _committee_by_rounds, o.committee_by_rounds("part_cycle", 40, _TRIO, 8, 0.6))
add("m28_recommended", lambda s, d: detect.detect_committee(SERIES["events_hour"](s, d), N, detect.RECOMMENDED.n_members, tau=detect.RECOMMENDED.tau))
add("m28_chunked", lambda s, d: detect.detect_committee(SERIES["events_seq"](s, d), 64, 10, core=2048, part=8192))
add("m29_incompressible", lambda s, d: den.uncovered(den.density(_tokens(s, d), detect.series_ends(_hour(s, d)))))

_WALK = 300
add("b1_random", lambda s, d: detect.baseline_random(SERIES["nation_month"](s, d), 12))
add("b2_fixed", lambda s, d: detect.baseline_fixed(SERIES["nation_month"](s, d), 12))
add("b3_selected_mdl", lambda s, d: detect.baseline_selected(SERIES["part_cycle"](s, d), 40))
add("b3_selected_reconstruction", lambda s, d: detect.baseline_selected(SERIES["part_cycle"](s, d), 40, objective="reconstruction"))


def _profile(df: DataFrame) -> DataFrame:
    return df.select("series_id", "pos", F.round("distance", 6).alias("distance"))


add("b4_discord_bruteforce", lambda s, d: _profile(discord.bruteforce_profile(SERIES["nation_month"](s, d), 12)), o.discord("nation_month", 12))
add("b5_discord_profile", lambda s, d: _profile(discord.profile(SERIES["nation_month"](s, d), 12, tiles=8)), o.discord("nation_month", 12))
add("b5_discord_top", lambda s, d: discord.discord_profile(SERIES["events_type_hour"](s, d), N))
add("b6_discord_ordered", lambda s, d: discord.discord_ordered(SERIES["events_hour"](s, d), N))
add("b7_words_recomputed", lambda s, d: wl._union([_collapsed(_hour(s, d), N, w, a).select("series_id", "w", "a", "tok_ix", "word") for w, a in PAIRS]), o.tokens_of("events_hour", N, PAIRS))

_REF, _LAST = "1-URGENT", "5-LOW"


def _scored(s: SparkSession, d: str) -> DataFrame:
    """How near each customer's orders, in turn within every priority, come to the day of the dearest one; 256 days away or more score zero."""
    orders = table(s, d, "orders").select(
        (F.col("o_custkey") % 6).cast("int").alias("dataset"), F.col("o_custkey").cast("string").alias("series_id"), F.col("o_orderpriority").alias("method"),
        "o_orderkey", "o_totalprice", F.floor(F.unix_micros(F.col("o_orderdate").cast("timestamp")) / 86_400_000_000).cast("long").alias("loc"), "o_orderdate",
    )
    turn = F.row_number().over(Window.partitionBy("dataset", "series_id", "method").orderBy("o_orderdate", "o_orderkey")).cast("int")
    dearest = orders.groupBy("dataset", "series_id").agg(F.min(F.struct(-F.col("o_totalprice"), "o_orderkey", "loc"))["loc"].alias("true_loc"))
    return measures.score(orders.select("dataset", "series_id", "method", turn.alias("rank"), "loc"), dearest.withColumn("true_len", F.lit(256)))


_SC = f"""o as (select cast(o_custkey % 6 as int) as dataset, cast(o_custkey as varchar) as series_id, o_orderpriority as method, o_orderkey, o_totalprice, cast(epoch_us(o_orderdate) // 86400000000 as bigint) as loc,
cast(row_number() over (partition by o_custkey, o_orderpriority order by o_orderdate, o_orderkey) as int) as rank from orders),
tr as (select series_id, loc as l from o qualify row_number() over (partition by series_id order by o_totalprice desc, o_orderkey) = 1),
sc as (select dataset, series_id, method, rank, loc, 1 - least(1.0e0, abs(loc - l) / 256.0e0) as score from o join tr using (series_id)),
bs as (select dataset, series_id, method, max(score) as score from sc where rank <= 3 group by 1, 2, 3),
pr as (select b.dataset, b.series_id, b.method, c.score as ref_score, b.score from bs b join bs c on b.series_id = c.series_id and c.method = '{_REF}' where b.method <> '{_REF}')"""
add("c01_score", lambda s, d: _scored(s, d).select("dataset", "series_id", "method", "rank", "loc", "score"), f"with {_SC} select dataset, series_id, method, rank, loc, score from sc")
add("c02_best_of", lambda s, d: measures.best_of(_scored(s, d)), f"with {_SC} select dataset, series_id, method, score from bs")
add("c03_average", lambda s, d: measures.average_score(measures.best_of(_scored(s, d))), f"with {_SC} select dataset, method, avg(score) as avg_score from bs group by 1, 2")
add("c04_hit_rate", lambda s, d: measures.hit_rate(_scored(s, d)), f"with {_SC} select dataset, method, avg(case when score > 0 then 1.0e0 else 0 end) as hit_rate from bs group by 1, 2")
add("c04_hit_rate_candidates", lambda s, d: measures.hit_rate(_scored(s, d), "candidate"), f"with {_SC} select dataset, method, avg(case when score > 0 then 1.0e0 else 0 end) as hit_rate from sc group by 1, 2")
add("c05_win_tie_loss", lambda s, d: measures.win_tie_loss(measures.best_of(_scored(s, d)), _REF), f"with {_SC} select dataset, method, count(*) filter (where ref_score > score) as wins, count(*) filter (where ref_score = score) as ties, count(*) filter (where ref_score < score) as losses from pr group by 1, 2")
add("c05b_paired", lambda s, d: measures.paired(measures.best_of(_scored(s, d)), _REF), f"with {_SC} select dataset, series_id, method, ref_score, score from pr")
add("c05c_misses", lambda s, d: measures.one_sided_misses(measures.best_of(_scored(s, d)), _REF), f"with {_SC} select dataset, method, count(*) filter (where score = 0 and ref_score > 0) as missed_by_method, count(*) filter (where ref_score = 0 and score > 0) as missed_by_ref from pr group by 1, 2")
add("b8_best_single", lambda s, d: measures.best_single(measures.best_of(_scored(s, d)), ref=_REF, exclude=(_LAST,)), f"with {_SC}, w as (select dataset, method, count(*) filter (where ref_score > score) as wins, count(*) filter (where ref_score < score) as losses from pr where method <> '{_LAST}' group by 1, 2) select dataset, arg_min(method, row(wins, -losses, method)) as method from w group by 1")
_COSTS = ((100, 10, 10), (900, 10, 10), (1024, 20, 20))


def _word_costs(s: SparkSession, d: str) -> DataFrame:
    """Additions and comparisons for all windows of the daily orders."""
    each = s.createDataFrame([(n, w, a, *measures.word_cost(n, w, a).values()) for n, w, a in _COSTS], "n int, w_max int, a_max int, direct long, shared long")
    own = detect.series_ends(SERIES["orders_day"](s, d)).crossJoin(F.broadcast(each)).withColumn("windows", F.greatest(F.col("last_pos") - F.col("n") + 1, F.lit(0)))
    return own.select("n", "w_max", "a_max", "windows", (F.col("windows") * F.col("direct")).alias("direct"), (F.col("windows") * F.col("shared")).alias("shared"))


add("c06_word_cost", _word_costs,
    f"with {o.SERIES['orders_day']}, e as (select count(*) as len from s) select cast(n as int) as n, cast(m as int) as w_max, cast(m as int) as a_max, cast(greatest(len - n + 1, 0) as bigint) as windows, cast(greatest(len - n + 1, 0) * (n * (m - 1) * (m - 1) + (m * (m + 1) // 2 - 1) * ((m - 1) * m // 2)) as bigint) as direct, cast(greatest(len - n + 1, 0) * (m * (m + 1) // 2 - 1) * (1 + dep) as bigint) as shared from e, (values (100, 10, 5), (900, 10, 5), (1024, 20, 7)) v(n, m, dep)")
add("c12_compression", lambda s, d: measures.compression(_tokens(s, d), den.grammars(_tokens(s, d)), detect.series_ends(_hour(s, d)).select("series_id", (F.col("last_pos") - N + 1).alias("windows"))))
add("c13_landscape", lambda s, d: wl.landscape(SERIES["part_cycle"](s, d), 17 * 40 + 1, 40, 6, 6))


def _spending(s: SparkSession, d: str) -> DataFrame:
    """How a customer's spending grows with the number of orders, priority by priority; thousands of units stand for seconds."""
    per = table(s, d, "orders").groupBy(F.col("o_orderpriority").alias("method"), "o_custkey")
    return measures.growth(per.agg(F.count("*").alias("points"), (F.sum(src.units("o_totalprice")) / 1000.0).alias("seconds")))


add("c14_growth", lambda s, d: _spending(s, d).select("method", F.round("exponent", 6).alias("exponent")),
    "with p as (select o_orderpriority as method, o_custkey, count(*) as points, cast(sum(cast(round(o_totalprice) as bigint)) as bigint) / 1000.0e0 as seconds from orders group by 1, 2) select method, round(regr_slope(ln(seconds), ln(points)), 6) as exponent from p group by 1")

add("w01_plant", lambda s, d: wl.data(s, d)[0])
add("w01_truth", lambda s, d: wl.data(s, d)[1], o.planted_truth(6, 25))
add("w02_w03_accuracy", lambda s, d: wl.accuracy(s, d))
add("w04_duels", lambda s, d: wl.duels(s, d))
add("w04b_scatter", lambda s, d: wl.scatter(s, d))
add("w05_ranges", lambda s, d: wl.ranges(s, d, ((5, 5), (10, 10), (15, 15), (20, 20))))
add("w06_w_ranges", lambda s, d: wl.ranges(s, d, ((5, 10), (10, 10), (15, 10), (20, 10))))
add("w07_a_ranges", lambda s, d: wl.ranges(s, d, ((10, 5), (10, 10), (10, 15), (10, 20))))
add("w08_sizes", lambda s, d: wl.sizes(s, d))
add("w09_selectivity", lambda s, d: wl.selectivity(s, d))
add("w10_lengths", lambda s, d: wl.lengths(s, d))
add("w11_c07_run_times", lambda s, d: wl.run_times(s, d))
add("w13_two_anomalies", lambda s, d: wl.two_anomalies(s, d))
add("w12_long_series", lambda s, d: detect.detect_committee(SERIES["lineitem_seq"](s, d), 900, 50, k=2, core=8192))
add("w14_sensitivity", lambda s, d: wl.landscape(SERIES["part_cycle"](s, d), 17 * 40 + 1, 40))
add("w15_extreme_curves", lambda s, d: wl.extreme_curves(SERIES["part_cycle"](s, d), 40))
add("w17_minimum_at_anomaly", lambda s, d: detect.detect_committee(SERIES["part_cycle"](s, d), 40, 20, k=1).select("series_id", (F.abs(F.col("loc") - 681) < 40).alias("inside")))
add("w18_cost", lambda s, d: s.createDataFrame([(n, measures.word_cost(n, 10, 10)["direct"] / measures.word_cost(n, 10, 10)["shared"]) for n in (50, 100, 900)], "n int, ratio double").select("n", F.round("ratio", 6).alias("ratio")),
    "select cast(n as int) as n, round((n * 81.0e0 + 54 * 45) / (54 * 6.0e0), 6) as ratio from (values (50), (100), (900)) v(n)")
add("w19_many_series", lambda s, d: detect.detect_committee(SERIES["events_user"](s, d), 8))
add("w20_text", lambda s, d: wl.incompressible_share(src.doc_words(s, d)))


def _agreement(s: SparkSession, d: str, name: str, n: int, params: list[tuple[int, int]], tau: float = 0.4) -> DataFrame:
    """What must hold of the on-line committee on a whole series table, counted where it does not.

    tokens: points that expanding each member's grammar does not give back. twins, idle: broken constraints of the grammars. kept: series without ceil(tau x members) curves.
    scaled: kept curves whose greatest value is not 1 (or 0 where all are). median: places where the curve is not the point-wise median taken by SQL. first: series whose first
    candidate is not the leftmost window of least sum.
    """
    df = cut(SERIES[name](s, d))
    ends = cut(detect.series_ends(df))
    # of what a kernel or a grammar makes, the planner knows the input's file alone and would broadcast it as if it were as small
    t = cut_in_loop(win.collapse_runs(detect.tokens_by_kernel(df, n, params), last=ends))
    rules = cut_in_loop(den.grammars(t))
    back = den.expand_grammar(rules)
    given = t.select(*back.columns)
    runs = cut_in_loop(den.density(t, ends))
    kept = cut_in_loop(com.keep_by_spread(com.curve_stats(runs), tau))
    scaled = cut_in_loop(com.scaled(runs, kept))
    curve = cut_in_loop(com.combine(scaled))
    points = scaled.select("series_id", F.explode(F.sequence("lo", "hi")).alias("pos"), "v").groupBy("series_id", "pos").agg(F.round(F.expr("percentile(v, 0.5)"), 9).alias("m"))
    wrong = points.join(_points(curve), ["series_id", "pos"], "full").where("m is null or de is null or abs(m - de) > 1e-9")
    sums = cand.window_values(curve.select("series_id", "lo", "hi", "de"), n).withColumn("value", F.round("value", 6))
    first = sums.groupBy("series_id").agg(F.min(F.struct("value", "pos"))["pos"].alias("least"))
    short = detect.detect_committee(df, n, len(params), w_max=max(w for w, _ in params), a_max=max(a for _, a in params), tau=tau, k=1)
    off = first.join(short.select("series_id", "loc"), "series_id", "left").where("loc is null or loc <> least")
    most = F.lit(com.kept_count(tau, len(params)))
    count = lambda name, bad: bad.agg(F.count("*").alias("off")).select(F.lit(name).alias("rule"), "off")
    tops = scaled.groupBy("series_id", "w", "a").agg(F.max("v").alias("v")).where("v <> 1 and v <> 0")
    return wl._union(
        [
            count("tokens", given.exceptAll(back).unionByName(back.exceptAll(given))), count("twins", den.digram_violations(rules)), count("idle", den.utility_violations(rules)),
            count("kept", kept.groupBy("series_id").count().where(F.col("count") != most)), count("scaled", tops), count("median", wrong), count("first", off),
        ]
    )


_HOLDS = "select rule, cast(0 as bigint) as off from (values ('tokens'), ('twins'), ('idle'), ('kept'), ('scaled'), ('median'), ('first')) v(rule)"
for _name, _n in (("events_type_hour", 24), ("part_cycle", 40), ("nation_month", 12)):
    add(f"m28_holds_{_name}", lambda s, d, x=_name, n=_n: _agreement(s, d, x, n, com.draw_params(50, w_cap=n)), _HOLDS)


def _rounds_settled(s: SparkSession, d: str) -> DataFrame:
    """What a finished rounds grammar must not leave: pairs that still repeat, and top-level symbols whose lengths do not add up to the tokens."""
    t = _collapsed(_hour(s, d), N, 3, 3)
    seq, _, _ = rnd.induce_rounds(t)
    lost = t.groupBy("series_id").count().join(seq.groupBy("series_id").agg(F.sum("len").alias("len")), "series_id").where("count <> len")
    return rnd.repeating_pairs(seq).agg(F.count("*").alias("pairs")).join(lost.agg(F.count("*").alias("lost")), F.lit(True))


add("m16_rounds_settled", _rounds_settled, "select cast(0 as bigint) as pairs, cast(0 as bigint) as lost")


def _chosen_agree(s: SparkSession, d: str, name: str, n: int) -> DataFrame:
    """Candidates of the random baseline beside those of the fixed pair's runs it drew, series by series: rows that only one of them has."""
    df = cut(SERIES[name](s, d))
    drawn = detect.random_choice(df)
    each = wl.grid(df, n, [([(w, a) for w in range(2, 11) for a in range(2, 11)], 1.0)], singles=True).where("run = -1")
    one = each.join(drawn, ["series_id", "w", "a"]).select("series_id", "rank", "lo", "hi", "loc", F.round("value", 6).alias("value"))
    two = detect.baseline_random(df, n).select(*one.columns[:-1], F.round("value", 6).alias("value"))
    return one.exceptAll(two).unionByName(two.exceptAll(one)).agg(F.count("*").alias("off"))


add("b1_holds", lambda s, d: _chosen_agree(s, d, "nation_month", 12), "select cast(0 as bigint) as off")
add("b1_random_choice", lambda s, d: detect.random_choice(SERIES["nation_month"](s, d)),
    f"with {o.SERIES['nation_month']}, c as (select distinct series_id, cast('0x' || substr(md5('42:' || series_id), 1, 8) as bigint) % 81 as i from s) select series_id, cast(i // 9 + 2 as int) as w, cast(i % 9 + 2 as int) as a from c")
