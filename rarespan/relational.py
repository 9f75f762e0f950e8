"""Queries of the relational kind around the series: predicates, joins, aggregates, windows, sets and streams' batch twins, each with its SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from rarespan import oracles as o
from rarespan.functions import sql as fs
from rarespan.operators import windows as win
from rarespan.operators.candidates import long_window_candidates
from rarespan.operators.density import expand_grammar
from rarespan.operators.inducer import induce_trace
from rarespan.operators.joins import as_of, interval_points
from rarespan.queries import N, SERIES, _collapsed, _literal, add
from rarespan.runtime import table
from rarespan.sources.series import event_types
from rarespan.streaming import joins, resample

_HOUR = o.SERIES["events_hour"]
_TYPES = o.SERIES["events_type_hour"]


def _hour(s, d):
    return SERIES["events_hour"](s, d)


def _types(s, d):
    return SERIES["events_type_hour"](s, d)


# predicates
add("p02_range_filter", lambda s, d: table(s, d, "events").where("ts >= timestamp_ntz '1995-01-01' and value between 10 and 50").select("event_id", "event_type"), "select event_id, event_type from events where ts >= timestamp '1995-01-01' and value between 10 and 50")
add("p04_case_in", lambda s, d: table(s, d, "orders").select("o_orderkey", F.when(F.col("o_orderstatus").isin("F", "O"), F.lit("known")).otherwise("other").alias("kind")), "select o_orderkey, case when o_orderstatus in ('F', 'O') then 'known' else 'other' end as kind from orders")
add("p06_having", lambda s, d: table(s, d, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("n")).where("n >= 6"), "select l_orderkey, count(*) as n from lineitem group by 1 having count(*) >= 6")

# joins
add("j01_broadcast", lambda s, d: table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")), "select n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey group by 1")
add("j02_merge", lambda s, d: table(s, d, "orders").hint("merge").join(table(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum(F.round(F.col("l_extendedprice") * 100).cast("long")).alias("cents")), "select o_orderstatus, count(*) as n, cast(sum(cast(round(l_extendedprice * 100) as bigint)) as bigint) as cents from orders join lineitem on o_orderkey = l_orderkey group by 1")
add("j03_shuffled_hash", lambda s, d: table(s, d, "part").hint("shuffle_hash").join(table(s, d, "lineitem"), F.col("p_partkey") == F.col("l_partkey")).groupBy("p_size").agg(F.count("*").alias("n")), "select p_size, count(*) as n from part join lineitem on p_partkey = l_partkey group by 1")
add("j04_semi", lambda s, d: table(s, d, "documents").join(table(s, d, "labels").where("toxic = 1"), "doc_id", "left_semi").select("doc_id", "lang"), "select doc_id, lang from documents where doc_id in (select doc_id from labels where toxic = 1)")
add("j05_anti", lambda s, d: table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left_anti").select("doc_id"), "select doc_id from documents where doc_id not in (select doc_id from labels)")
add("j06_grid", lambda s, d: _types(s, d).select("series_id").distinct().crossJoin(F.broadcast(s.range(2, 5).withColumnRenamed("id", "w"))), f"with {_TYPES} select distinct series_id, unnest(generate_series(2, 4)) as w from s")
add("j08_range_by_bins", lambda s, d: _range_join(s, d), f"with {_HOUR}, iv as (select unnest(generate_series(0, 9)) as k) select k, count(*) as n, cast(sum(x) as bigint) as total from iv join s on pos between k * 70 + 5 and k * 70 + 40 group by 1")
add("j09_as_of", lambda s, d: _as_of(s, d), f"with {_HOUR}, z as (select event_id, {o._epoch('ts', 3600)} - (select min({o._epoch('ts', 3600)}) from events) + 1 as spot from events where event_type = 'purchase') select event_id, (select max(pos) from s where pos <= z.spot and x % 2 = 0) as pos from z")
add("j10_calendar", lambda s, d: _hour(s, d).groupBy().agg(F.count("*").alias("hours"), F.count_if(F.col("x") == 0).alias("gaps")), f"with {_HOUR} select count(*) as hours, count(*) filter (where x = 0) as gaps from s")
add("j11_full_outer", lambda s, d: _full(s, d), f"with {_TYPES}, fa as (select pos, x from s where series_id = 'click' and x % 3 = 0), fb as (select pos, x as y from s where series_id = 'view' and x % 2 = 0) select coalesce(fa.pos, fb.pos) as pos, x, y from fa full join fb on fa.pos = fb.pos")


def _range_join(s, d):
    """Interval - point join by bins."""
    iv = s.range(10).select(F.col("id").alias("k"), (F.col("id") * 70 + 5).alias("lo"), (F.col("id") * 70 + 40).alias("hi"))
    return interval_points(iv, _hour(s, d), "pos", width=32).groupBy("k").agg(F.count("*").alias("n"), F.sum("x").alias("total"))


def _as_of(s, d):
    """Latest even-valued hour at or before each purchase."""
    e = table(s, d, "events").withColumn("at", F.expr("unix_micros(cast(ts as timestamp)) div 3600000000"))
    base = e.agg(F.min("at")).first()[0] or 0
    asks = e.where("event_type = 'purchase'").select("event_id", (F.col("at") - base + 1).alias("at"))
    marks = _hour(s, d).where("x % 2 = 0").select(F.col("pos").alias("at"), "pos")
    return as_of(asks, marks, "at", "pos", width=64).select("event_id", "pos")


def _full(s, d):
    t = _types(s, d)
    a = t.where("series_id = 'click' and x % 3 = 0").select("pos", "x")
    b = t.where("series_id = 'view' and x % 2 = 0").select("pos", F.col("x").alias("y"))
    return a.join(b, "pos", "full").select("pos", "x", "y")


# aggregates
add("g02_deviation", lambda s, d: _types(s, d).groupBy("series_id").agg(F.round(F.stddev_pop("x"), 6).alias("sd"), F.round(F.var_samp("x"), 4).alias("var")), f"with {_TYPES} select series_id, round(stddev_pop(x), 6) as sd, round(var_samp(x), 4) as var from s group by 1")
add("g03_median", lambda s, d: _types(s, d).groupBy("series_id").agg(F.median("x").alias("med"), F.expr("percentile(x, 0.9)").alias("p90")), f"with {_TYPES} select series_id, median(x) as med, quantile_cont(x, 0.9) as p90 from s group by 1")
add("g04_vocabulary", lambda s, d: win.words(_hour(s, d), N, 4, 4).agg(F.count_distinct("word").alias("words")), f"with {_HOUR}, {o.words_cte(N, 4, 4)} select count(distinct word) as words from t")
add("g05_rollup", lambda s, d: table(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")), "select l_returnflag, l_linestatus, count(*) as n from lineitem group by rollup (l_returnflag, l_linestatus)")
add("g05_cube", lambda s, d: table(s, d, "documents").cube("lang", "source").agg(F.count("*").alias("n")), "select lang, source, count(*) as n from documents group by cube (lang, source)")
add("g06_pivot", lambda s, d: table(s, d, "labels").groupBy("quality").pivot("toxic", [0, 1]).agg(F.count("doc_id")).select("quality", F.coalesce("0", F.lit(0)).alias("clean"), F.coalesce("1", F.lit(0)).alias("toxic")), "select quality, count(*) filter (where toxic = 0) as clean, count(*) filter (where toxic = 1) as toxic from labels group by 1")
add("g07_min_by", lambda s, d: _types(s, d).groupBy("series_id").agg(F.min(F.struct("x", "pos"))["pos"].alias("pos")), f"with {_TYPES} select series_id, arg_min(pos, row(x, pos)) as pos from s group by 1")
add("g08_collect", lambda s, d: table(s, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ",").alias("roles")), "select conv_id, string_agg(role, ',' order by turn) as roles from conversations group by 1")
add("g10_slope", lambda s, d: _types(s, d).groupBy("series_id").agg(F.round(F.regr_slope("x", "pos"), 6).alias("slope"), F.round(F.corr("x", "pos"), 6).alias("corr")), f"with {_TYPES} select series_id, round(regr_slope(x, pos), 6) as slope, round(corr(x, pos), 6) as corr from s group by 1")

# windows
_ROLL = "partition by series_id order by pos"
add("n01_cumulative", lambda s, d: win.prefix_sums(_types(s, d)).select("series_id", "pos", "p1", F.col("p2").cast("double").alias("p2")), f"with {_TYPES} select series_id, pos, cast(sum(x) over ({_ROLL}) as bigint) as p1, cast(sum(x * x) over ({_ROLL}) as double) as p2 from s")
add("n02_lead_lag", lambda s, d: _types(s, d).select("series_id", "pos", (F.lead("x", 3).over(win._order()) - F.lag("x", 2).over(win._order())).alias("gap")), f"with {_TYPES} select series_id, pos, lead(x, 3) over ({_ROLL}) - lag(x, 2) over ({_ROLL}) as gap from s")
add("n04_ranks", lambda s, d: _ranks(s, d), f"with {_TYPES} select series_id, pos, rank() over (partition by series_id order by x) as r, dense_rank() over (partition by series_id order by x) as dr, ntile(4) over (partition by series_id order by x, pos) as q from s")
add("n06_islands", lambda s, d: _islands(s, d), f"with {_TYPES}, m as (select series_id, median(x) as med from s group by 1), ia as (select series_id, pos, x > med as up from s join m using (series_id)), ib as (select *, pos - row_number() over (partition by series_id, up order by pos) as g from ia) select series_id, min(pos) as lo, max(pos) as hi from ib where up group by series_id, g having count(*) >= 3")
add("n07_time_range", lambda s, d: _smooth(s, d), "select event_id, count(*) over (order by epoch_us(ts) // 1000000 range between 1800 preceding and current row) as n from events where event_type = 'error'")


def _ranks(s, d):
    by = Window.partitionBy("series_id").orderBy("x")
    q = Window.partitionBy("series_id").orderBy("x", "pos")
    return _types(s, d).select("series_id", "pos", F.rank().over(by).cast("long").alias("r"), F.dense_rank().over(by).cast("long").alias("dr"), F.ntile(4).over(q).cast("long").alias("q"))


def _islands(s, d):
    """Runs of at least three hours above the series' median."""
    t = _types(s, d)
    t = t.join(t.groupBy("series_id").agg(F.median("x").alias("med")), "series_id").withColumn("up", F.col("x") > F.col("med"))
    g = F.col("pos") - F.row_number().over(Window.partitionBy("series_id", "up").orderBy("pos"))
    return t.withColumn("g", g).where("up").groupBy("series_id", "g").agg(F.min("pos").alias("lo"), F.max("pos").alias("hi"), F.count("*").alias("n")).where("n >= 3").select("series_id", "lo", "hi")


def _smooth(s, d):
    e = table(s, d, "events").where("event_type = 'error'").withColumn("t", F.expr("unix_micros(cast(ts as timestamp)) div 1000000"))
    return e.select("event_id", F.count("*").over(Window.partitionBy("event_type").orderBy("t").rangeBetween(-1800, 0)).alias("n"))


add("n05_first_last", lambda s, d: _types(s, d).select("series_id", "pos", F.nth_value("x", 2).over(_whole()).alias("second"), F.last("x").over(_whole()).alias("final")), f"with {_TYPES} select series_id, pos, nth_value(x, 2) over ({_ROLL} rows between unbounded preceding and unbounded following) as second, last_value(x) over ({_ROLL} rows between unbounded preceding and unbounded following) as final from s")
add("g09_conditional", lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("high"), F.count("*").alias("n")), "select event_type, count(*) filter (where value > 50) as high, count(*) as n from events group by 1")
add("j12_lateral", lambda s, d: _lateral(s, d), "select n_name, o_orderkey from (select n_name, o_orderkey, row_number() over (partition by n_name order by o_totalprice desc, o_orderkey) as r from nation join customer on n_nationkey = c_nationkey join orders on o_custkey = c_custkey) z where r <= 2")


def _whole():
    return Window.partitionBy("series_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)


def _lateral(s, d):
    """The two largest orders of each nation."""
    o_ = table(s, d, "orders").select("o_orderkey", "o_custkey", "o_totalprice").join(table(s, d, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    n = table(s, d, "nation").select("n_nationkey", "n_name")
    rank = F.row_number().over(Window.partitionBy("c_nationkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))
    return o_.withColumn("r", rank).where("r <= 2").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select("n_name", "o_orderkey")


# sorting and sets
add("k01_report", lambda s, d: _hour(s, d).orderBy(F.desc("x"), "pos").limit(10).select("pos", "x"), f"with {_HOUR} select pos, x from s order by x desc, pos limit 10")
add("u02_equal_forms", lambda s, d: _collapsed(_hour(s, d), N, 4, 4).select("pos", "word").exceptAll(win.collapse_runs(win.multires_words(_hour(s, d), N, [4], [4])).select("pos", "word")), "select cast(0 as bigint) as pos, '' as word where false")
add("u03_distinct", lambda s, d: table(s, d, "events").select("user_id", "event_type").distinct(), "select distinct user_id, event_type from events")
add("u04_recursive_expansion", lambda s, d: _recursive(s), "select cast(ix as int) as ix, sym from (values (1, 'ab'), (2, 'bc'), (3, 'aa'), (4, 'cc'), (5, 'ca'), (6, 'ab'), (7, 'bc'), (8, 'aa')) v(ix, sym)")


def _recursive(s):
    """The example's tokens from its grammar, by a recursive query; places are spelt as sortable paths."""
    s.sql("select * from (values ('S', 1, 'R', true), ('S', 2, 'cc', false), ('S', 3, 'ca', false), ('S', 4, 'R', true), ('R', 1, 'ab', false), ('R', 2, 'bc', false), ('R', 3, 'aa', false)) g(rule, ix, sym, is_rule)").createOrReplaceTempView("rarespan_example_grammar")
    return s.sql(
        """with recursive x(path, sym, is_rule) as (
             select cast(ix as string), sym, is_rule from rarespan_example_grammar where rule = 'S'
             union all select concat(x.path, '.', g.ix), g.sym, g.is_rule from x join rarespan_example_grammar g on x.is_rule and g.rule = x.sym)
           select cast(row_number() over (order by path) as int) as ix, sym from x where not is_rule"""
    )


# functions
add("f01_word_udf", lambda s, d: _arrays(s, d).select("series_id", "pos", fs.symbolic_word("xs", F.lit(4), F.lit(4)).alias("word"), (fs.symbolic_word("xs", F.lit(4), F.lit(4)) == fs.word_array(F.col("xs"), 4, 4)).alias("same")))
add("f02_paa_arrays", lambda s, d: _arrays(s, d).select("series_id", "pos", F.round(fs.paa_array(F.col("xs"), 4)[1], 6).alias("second")), f"with {o.SERIES['nation_month']} select series_id, pos, round(m, 6) as second from (select series_id, pos, avg(x) over ({_ROLL} rows between 3 following and 5 following) as m, count(*) over ({_ROLL} rows between current row and 11 following) as len from s) z where len = 12")
add("f03_induce_table", lambda s, d: _induce(s, d), "select cast(user_id as varchar) as series_id, count(*) as tokens, string_agg(event_type, ' ' order by ts, event_id) as words from events group by 1")
add("f04_density_table", lambda s, d: _density(s), "select cast(a as bigint) as lo, cast(b as bigint) as hi, cast(c as bigint) as d from (values (1, 20, 1), (21, 28, 0), (29, 60, 1)) v(a, b, c)")
add("f05_grammar_size", lambda s, d: _sized(s), "select cast(7 as bigint) as size")
add("f08_detect_table", lambda s, d: _detect(s, d))

_EX = list(zip("ab bc aa cc ca ab bc aa".split(), (1, 8, 15, 21, 25, 29, 34, 40), strict=True))


def _arrays(s, d):
    return win.windows(SERIES["nation_month"](s, d), 12).withColumnRenamed("values", "xs")


def _induce(s, d):
    """The event types of each user, given back by the rules that the table function makes of them."""
    fs.register_all(s)
    event_types(s, d).createOrReplaceTempView("rarespan_event_types")
    rules = s.sql("select series_id, rule, posexplode(split(body, ' ')) as (ix, sym) from induce(table(rarespan_event_types) partition by series_id order by pos)")
    back = expand_grammar(rules.select("series_id", F.lit(0).alias("w"), F.lit(0).alias("a"), "rule", "ix", "sym", F.col("sym").rlike("^R[0-9]+$").alias("is_rule")))
    words = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("tok_ix", "word"))), lambda x: x["word"]), " ")
    return back.groupBy("series_id").agg(F.count("*").alias("tokens"), words.alias("words"))


def _density(s):
    fs.register_all(s)
    _literal(s, _EX).createOrReplaceTempView("rarespan_example_tokens")
    return s.sql("select lo, hi, d from rule_density(table(rarespan_example_tokens) partition by series_id order by pos, last => 60)")


def _sized(s):
    return _literal(s, _EX).coalesce(1).sortWithinPartitions("pos").groupBy("series_id").agg(fs.grammar_size("word").alias("size")).select("size")


def _detect(s, d):
    fs.register_all(s)
    SERIES["part_cycle"](s, d).createOrReplaceTempView("rarespan_cycle")
    return s.sql("select rank, loc, value from detect(table(rarespan_cycle) partition by series_id order by pos, n => 40)")


# batch twins of the streams
def _events(s, d):
    return resample.with_instant(table(s, d, "events"))


_C = "cast(sum(cast(round(value * 100) as bigint)) as bigint)"
add("t01_tumbling", lambda s, d: resample.tumbling(_events(s, d)), f"select event_type as series_id, {o._epoch('ts', 3600)} as step, {_C} as x from events group by 1, 2")
add("t02_sliding", lambda s, d: resample.sliding(_events(s, d)), f"with e as (select {o._epoch('ts', 3600)} as h, value from events), z as (select (h - k) * 3600 as start, value from e, (select unnest(generate_series(0, 23)) as k)) select start, count(*) as n, {_C} as total from z group by 1")
add("t03_bursts", lambda s, d: resample.bursts(_events(s, d)), f"with e as (select user_id, epoch_us(ts) as t, value from events), a as (select *, case when t - lag(t) over (partition by user_id order by t) < 1800000000 then 0 else 1 end as fresh from e), b as (select *, sum(fresh) over (partition by user_id order by t) as g from a) select user_id, cast(min(t) // 1000000 as bigint) as start, cast((max(t) + 1800000000) // 1000000 as bigint) as stop, count(*) as n, {_C} as total from b group by user_id, g")
add("t10_dedup", lambda s, d: resample.deduplicated(_events(s, d).unionAll(_events(s, d))).select("event_id"), "select distinct event_id from events")


def _in_spans(s, d):
    """Events of the second and third day of their type, by a join with one static span a type."""
    e = _events(s, d).select("event_id", F.col("event_type").alias("series_id"), F.floor(F.unix_timestamp("ts") / 3600).alias("step"))
    spans = e.groupBy("series_id").agg((F.min("step") + 24).alias("lo"), (F.min("step") + 71).alias("hi"))
    return joins.in_spans(e, spans, width=32).select("event_id", "series_id", "lo")


def _kinds(s, d):
    """What each user does most: a map of counts, filtered and printed."""
    n = table(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    kept = F.array_sort(F.transform(F.map_entries(F.map_filter("m", lambda _, v: v > 12)), lambda e: F.concat_ws("=", e["key"], e["value"].cast("string"))))
    return m.select("user_id", F.array_join(kept, ",").alias("kinds"), F.size(F.map_keys("m")).alias("of"))


_STEP = o._epoch("ts", 3600)
add("j13_stream_static", _in_spans, f"with e as (select event_id, event_type as series_id, {_STEP} as step from events), p as (select series_id, min(step) + 24 as lo from e group by 1) select event_id, series_id, lo from e join p using (series_id) where step between lo and lo + 47")
add("j13_stream_stream", lambda s, d: joins.followed(_events(s, d).where("event_type = 'error'"), _events(s, d).where("event_type = 'purchase'")),
    "select a.user_id, a.event_id as first_id, b.event_id as second_id, epoch_us(b.ts) - epoch_us(a.ts) as gap_us from events a join events b on a.user_id = b.user_id and a.event_type = 'error' and b.event_type = 'purchase' and epoch_us(b.ts) - epoch_us(a.ts) between 0 and 3600000000")
add("g11_mode", lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.mode("l_linenumber", True).alias("most")),
    "select l_returnflag, l_linenumber as most from (select l_returnflag, l_linenumber, count(*) as c from lineitem group by 1, 2) qualify row_number() over (partition by l_returnflag order by c desc, l_linenumber) = 1")
add("g11_histogram", lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag", F.col("l_linenumber").cast("long").alias("x")).agg(F.count("*").alias("y")),
    "select l_returnflag, cast(l_linenumber as bigint) as x, count(*) as y from lineitem group by 1, 2")
add("f10_json", lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.sum(F.from_json("props", "k long")["k"]).alias("total"), F.max(F.get_json_object("props", "$.k").cast("long")).alias("top")),
    "select event_type, cast(sum(cast(props ->> '$.k' as bigint)) as bigint) as total, max(cast(props ->> '$.k' as bigint)) as top from events group by 1")
add("f11_maps", _kinds, "with n as (select user_id, event_type, count(*) as n from events group by 1, 2) select user_id, coalesce(string_agg(event_type || '=' || n, ',' order by event_type || '=' || n) filter (where n > 12), '') as kinds, cast(count(*) as int) as of from n group by 1")
add("m14d_step_trace", lambda s, d: _trace(s),
    "select cast(k as int) as step, cast(r as int) as rule, b as body from (values (1, 0, 'ab'), (2, 0, 'ab bc'), (3, 0, 'ab bc aa'), (4, 0, 'ab bc aa cc'), (5, 0, 'ab bc aa cc ca'), (6, 0, 'ab bc aa cc ca ab'), (7, 0, 'R1 aa cc ca R1'), (7, 1, 'ab bc'), (8, 0, 'R1 cc ca R1'), (8, 1, 'ab bc aa')) v(k, r, b)")
add("m22c_edges_dropped", lambda s, d: _edges_dropped(s), "select cast(r as int) as rank, cast(l as bigint) as loc, cast(v as double) as value from (values (1, 21, 4), (2, 5, 12)) v(r, l, v)")


def _trace(s):
    """The example's grammar after each of its tokens."""
    names = list(dict.fromkeys(w for w, _ in _EX))
    spell = lambda v: f"R{v >> 1}" if v & 1 else names[v >> 1]
    steps = enumerate(induce_trace([names.index(w) for w, _ in _EX]), 1)
    return s.createDataFrame([(k, r, " ".join(map(spell, body))) for k, bodies in steps for r, body in bodies.items()], "step int, rule int, body string")


def _edges_dropped(s):
    """A curve that is lowest at both ends: these windows don't count."""
    runs = [("s", 1, 4, 0.0), ("s", 5, 20, 3.0), ("s", 21, 24, 1.0), ("s", 25, 40, 3.0), ("s", 41, 44, 0.0)]
    curve = s.createDataFrame(runs, "series_id string, lo long, hi long, de double")
    return long_window_candidates(curve, 4, 2, edge="drop", segment=7).select("rank", "loc", "value")
