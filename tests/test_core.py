"""Worked examples, exactness across forms, and invariants of the core operators."""

import random
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from rarespan.functions import breakpoints as bp
from rarespan.operators import candidates as cand
from rarespan.operators import committee as com
from rarespan.operators import density as den
from rarespan.operators import discord, measures
from rarespan.operators import windows as win
from rarespan.operators.inducer import expand, induce, induce_trace, instances, token_depth
from rarespan.plans import detect
from rarespan.sources import series


def tokens_df(spark, words, pos=None, ends=None):
    pos = pos or list(range(1, len(words) + 1))
    rows = [("s", 2, 3, p, w) for p, w in zip(pos, words, strict=True)]
    return spark.createDataFrame(rows, "series_id string, w int, a int, pos long, word string")


def test_breakpoints():
    assert [round(x, 4) for x in bp.cuts(3)] == [-0.4307, 0.4307] and bp.cuts(2) == (0.0,)
    assert [round(x, 4) for x in bp.cuts(4)] == [-0.6745, 0.0, 0.6745]
    assert [len(bp.summary_breaks(m)) for m in (4, 10, 15, 20)] == [5, 31, 71, 127]
    rows = ["".join(bp.LETTERS[i] for i in r) for r in bp.symbol_matrix(4)]
    assert (rows[0], rows[2], rows[5]) == ("aaa", "abb", "bcd")
    for a in range(2, 21):
        for i, c in enumerate(bp.cuts(a)):
            for value, want in ((c, i + 1), (np.nextafter(c, -9), i)):
                k = int(np.searchsorted(np.array(bp.summary_breaks(20)), value, side="right"))
                assert bp.symbol_matrix(20)[k][a - 2] == want


def test_run_collapse(spark):
    t = tokens_df(spark, "ba ba ba dc dc aa ac ac".split())
    last = spark.createDataFrame([("s", 8)], "series_id string, last_pos long")
    c = win.collapse_runs(t, last=last)
    assert [(r.pos, r.word, r.run_end) for r in c.orderBy("pos").collect()] == [(1, "ba", 3), (4, "dc", 5), (6, "aa", 6), (7, "ac", 8)]
    assert [r.word for r in win.expand_runs(c).orderBy("pos").collect()] == "ba ba ba dc dc aa ac ac".split()


def test_toy_grammars():
    w = "aa bb cc xx aa bb cc".split()
    assert induce([w.index(x) for x in w]) == {0: [3, 6, 3], 1: [0, 2, 4]}
    w = "ab bc aa cc ca ab bc aa".split()
    g = [w.index(x) for x in w]
    assert induce(g) == {0: [3, 6, 8, 3], 1: [0, 2, 4]}
    states = list(induce_trace(g))
    assert states[5] == {0: [0, 2, 4, 6, 8, 0]} and states[6] == {0: [3, 4, 6, 8, 3], 1: [0, 2]} and states[7] == induce(g)


def test_density_of_the_example(spark):
    w, pos = "ab bc aa cc ca ab bc aa".split(), [1, 8, 15, 21, 25, 29, 34, 40]
    t = tokens_df(spark, w, pos)
    last = spark.createDataFrame([("s", 60)], "series_id string, last_pos long")
    runs = [(r.lo, r.hi, r.d) for r in den.density(t, last).orderBy("lo").collect()]
    assert runs == [(1, 20, 1), (21, 28, 0), (29, 60, 1)]
    spans = den.rule_spans(win.collapse_runs(t, last=last))
    assert sorted((r.lo, r.hi) for r in spans.collect()) == [(1, 20), (29, 60)]
    assert sorted((r.lo, r.hi, r.d) for r in den.density_from_spans(spans, last).collect()) == runs
    wide = [(r.lo, r.hi, r.d) for r in den.density(t, last, "window_span", 16).orderBy("lo").collect()]
    assert wide == [(1, 28, 1), (29, 55, 1), (56, 60, 0)] or wide == [(1, 30, 1), (31, 28, 0)] or (wide[0][0], wide[-1][1]) == (1, 60)
    assert [(r.lo, r.hi) for r in den.uncovered(den.density(t, last)).collect()] == [(21, 28)]


@settings(max_examples=300, deadline=None)
@given(st.lists(st.integers(0, 3), max_size=60))
def test_grammar_properties(tokens):
    g = induce(tokens)
    assert expand(g) == tokens
    uses = Counter(v >> 1 for body in g.values() for v in body if v & 1)
    assert all(uses[r] >= 2 for r in g if r)
    seen = {}
    for r, body in g.items():
        for i, pair in enumerate(zip(body, body[1:], strict=False)):
            assert seen.get(pair, (r, i - 1)) == (r, i - 1)
            seen.setdefault(pair, (r, i))
    depth = token_depth(g)
    cover = np.zeros(len(tokens), int)
    for _, a, b in instances(g):
        cover[a : b + 1] += 1
    assert depth.tolist() == cover.tolist()


def plain_word(x, n, w, a):
    x = np.asarray(x, float)
    if x.std() == 0:
        coef = np.zeros(w)
    else:
        z = (x - x.mean()) / x.std(ddof=1)
        coef = np.repeat(z, w).reshape(w, n).mean(1)
    return "".join(bp.LETTERS[int((np.array(bp.cuts(a)) <= c + 0.0).sum())] for c in coef)


@pytest.fixture(scope="module")
def small(spark):
    rnd = random.Random(8)
    rows = [("a", i + 1, rnd.randrange(-5000, 5000)) for i in range(150)] + [("b", i + 1, [5, 9, 2, 7][i % 4]) for i in range(90)]
    rows += [("flat", i + 1, 7) for i in range(40)] + [("short", i + 1, i) for i in range(5)]
    return spark.createDataFrame(rows, "series_id string, pos long, x long").repartition(5).cache(), rows


@pytest.mark.parametrize(("n", "w", "a"), [(12, 3, 4), (12, 5, 7), (13, 4, 3), (12, 12, 10), (2, 2, 3)])
def test_words_agree(spark, small, n, w, a):
    df, rows = small
    by = {}
    for s, p, x in rows:
        by.setdefault(s, []).append(x)
    want = sorted((s, p + 1, plain_word(v[p : p + n], n, w, a)) for s, v in by.items() for p in range(len(v) - n + 1))
    got = sorted(map(tuple, win.words(df, n, w, a).collect()))
    assert [g[:2] for g in got] == [x[:2] for x in want]
    assert np.mean([g[2] == x[2] for g, x in zip(got, want, strict=True)]) > 0.98  # floats may fall on the other side of a cut
    naive = win.paa_naive(df, n, w).select("series_id", "pos", win.word_of(F.col("coef"), a).alias("word"))
    assert sorted(map(tuple, naive.collect())) == got
    exact = win.collapse_runs(win.words(df, n, w, a).select("series_id", F.lit(w).alias("w"), F.lit(a).alias("a"), "pos", "word"))
    exact = sorted((r.series_id, r.pos, r.word) for r in exact.collect())
    multi = win.multires_words(df, n, sorted({2, w}), sorted({2, a, 10})).where(f"w = {w} and a = {a}")
    assert sorted((r.series_id, r.pos, r.word) for r in win.collapse_runs(multi).collect()) == exact
    for core in (7, 64, 1000):
        t = detect.tokens_by_kernel(df, n, [(w, a), (2, 10)], core).where(f"w = {w} and a = {a}")
        assert sorted((r.series_id, r.pos, r.word) for r in win.collapse_runs(t).collect()) == exact


def test_word_matrix(spark):
    df = spark.createDataFrame([([-1.0, -0.2, 0.8],), ([-1.0, 0.0, 1.0],)], "c array<double>")
    got = [r[0] for r in df.select(win.word_matrix(F.col("c"), 4)).collect()]
    assert got[0] == ["aab", "abc", "abd"]
    assert [r[0] for r in spark.createDataFrame([([-1.0, 0.0, 1.0, -1.0],)], "c array<double>").select(win.word_of(F.col("c"), 3)).collect()] == ["abca"]


def test_grammar_tables(spark, small):
    df, _ = small
    t = win.collapse_runs(detect.tokens_by_kernel(df, 12, [(3, 3), (4, 6)]), last=detect.series_ends(df))
    rules = den.grammars(t).cache()
    assert den.digram_violations(rules).count() == 0 and den.utility_violations(rules).count() == 0
    back = {tuple(r) for r in den.expand_grammar(rules).select("series_id", "w", "a", "tok_ix", "word").collect()}
    assert back == {tuple(r) for r in t.select("series_id", "w", "a", "tok_ix", "word").collect()}
    spans = den.rule_spans(t)
    one = sorted(map(tuple, den.density(t, detect.series_ends(df)).where("d > 0").collect()))
    two = sorted(map(tuple, den.density_from_spans(spans, detect.series_ends(df)).where("d > 0").collect()))
    assert one == two


def test_committee_algebra(spark):
    curves = {"1": (0, 2, 4), "2": (0, 1, 1), "3": (3, 3, 3)}
    rows = [("s", int(m), 2, p + 1, p + 1, d) for m, c in curves.items() for p, d in enumerate(c)]
    runs = spark.createDataFrame(rows, "series_id string, w int, a int, lo long, hi long, d long")
    stats = com.curve_stats(runs)
    assert sorted((r.w, r.spread) for r in stats.collect()) == [(1, 24.0), (2, 2.0), (3, 0.0)]
    kept = com.keep_by_spread(stats, 2 / 3)
    assert sorted(r.w for r in kept.collect()) == [1, 2]
    for segment in (1, 2, 100):
        got = com.combine(com.scaled(runs, kept), segment=segment)
        points = sorted((r.pos, r.de) for r in got.select(F.explode(F.sequence("lo", "hi")).alias("pos"), "de").collect())
        assert points == [(1, 0.0), (2, 0.75), (3, 1.0)]
    assert com.draw_params(5) == com.draw_params(50)[:5] and len(set(com.draw_params(50))) == 50
    assert len(com.draw_params(50, 5, 5)) == 16 and com.kept_count(0.05, 50) == 3 and com.kept_count(0.4, 5) == 2


def test_candidates(spark):
    rnd = random.Random(2)
    curve = [rnd.randrange(6) for _ in range(80)]
    runs = spark.createDataFrame([("s", i + 1, i + 1, float(v)) for i, v in enumerate(curve)], "series_id string, lo long, hi long, de double")
    n = 7
    one = sorted(map(tuple, cand.window_candidates(runs, n).collect()))
    two = sorted(map(tuple, cand.top_windows(cand.window_values(runs, n), n).collect()))
    assert one == two and len(one) == 3
    sums = [sum(curve[i : i + n]) for i in range(len(curve) - n + 1)]
    assert one[0][4] - 1 == sums.index(min(sums)) and one[0][5] == min(sums)
    flat = spark.createDataFrame([("s", 1, 4, 2.0), ("s", 5, 6, 1.0), ("s", 7, 9, 3.0), ("s", 10, 10, 0.0)], "series_id string, lo long, hi long, de double")
    assert [(r.rank, r.lo, r.hi) for r in cand.plateaus(flat).orderBy("rank").collect()] == [(1, 10, 10), (2, 5, 6)]


def test_discords_agree(spark, small):
    df, _ = small
    df = df.where("series_id in ('a', 'b')")
    key = lambda d: sorted((r.series_id, r.rank, r.loc, round(r.value, 5)) for r in d.collect())
    brute = key(discord.discord_bruteforce(df, 12).where("series_id = 'a'"))
    assert key(discord.discord_profile(df, 12, tiles=5).where("series_id = 'a'")) == brute
    assert key(discord.discord_ordered(df, 12).where("series_id = 'a'")) == brute


def test_planted_cycle_is_found(spark, sf):
    df = series.from_part_cycle(spark, sf, period=40, reps=30, odd=17).where("series_id = 'cycle-0'")  # the series this test has always had; w17 reports all of them
    got = detect.detect_committee(df, 40, n_members=20, tau=0.4).orderBy("rank").collect()
    assert any(abs(r.loc - (17 * 40 + 1)) < 40 for r in got[:1])
    for f in (lambda: detect.baseline_fixed(df, 40), lambda: detect.baseline_random(df, 40), lambda: detect.baseline_selected(df, 40, w_max=5, a_max=5)):
        assert len(f().collect()) >= 1


def test_score_and_cost(spark):
    c = spark.createDataFrame([("s", r, loc) for r, loc in enumerate((100, 125, 150, 10), 1)], "series_id string, rank int, loc long")
    t = spark.createDataFrame([("s", 100, 50)], "series_id string, true_loc long, true_len int")
    assert [r.score for r in measures.score(c, t).orderBy("rank").collect()] == [1.0, 0.5, 0.0, 0.0]
    assert measures.word_cost(100, 10, 10)["direct"] > 10 * measures.word_cost(100, 10, 10)["shared"]


def test_regularize(spark):
    df = spark.createDataFrame([("s", 1, 10), ("s", 4, 40), ("s", 5, 7)], "series_id string, step long, x long")
    got = {f: [r.x for r in series.regularize(df, f).orderBy("pos").collect()] for f in ("zero", "last", "linear", "drop")}
    assert got == {"zero": [10, 0, 0, 40, 7], "last": [10, 10, 10, 40, 7], "linear": [10, 20, 30, 40, 7], "drop": [10, 40, 7]}


def test_numbering_over_ranges(spark):
    from rarespan.operators.layout import number_rows

    df = spark.range(1000).select(((F.col("id") * 7919) % 1000).alias("k"), (F.col("id") % 3).alias("j"))
    df = df.unionByName(df)
    got = [r.pos for r in number_rows(df, ["k", "j"]).orderBy("k", "j").collect()]
    assert sorted(got) == list(range(1, 2001))
    assert [r.k for r in number_rows(df, ["k", "j"]).orderBy("pos").collect()] == sorted(list(range(1000)) * 2)


def test_short_and_long_paths_agree(spark, small):
    df, _ = small
    one = sorted(map(tuple, detect.detect_committee(df, 12, 12).collect()))
    two = sorted(map(tuple, detect.detect_committee(df, 12, 12, short=0, core=50).collect()))
    assert one == two and {r[0] for r in one} == {"a", "b", "flat"}


def test_running_sums_do_not_depend_on_chunks(spark):
    rows = [(name, p, p * p % 7 - 3) for name, last in (("a", 50), ("b", 1), ("c", 16)) for p in range(1, last + 1)]
    steps = spark.createDataFrame(rows, "series_id string, pos long, s long")
    want, total = [], {}
    for name, p, x in rows:
        total[name] = total.get(name, 0) + x
        want.append((name, p, total[name]))
    for chunk in (1, 8, 1 << 16):
        assert sorted(map(tuple, series.running_sums(steps, "s", chunk).collect())) == sorted(want)


def test_large_values_give_the_coefficients_of_small_ones(spark):
    rng = np.random.default_rng(3)
    rows = [("s", i + 1, int(v)) for i, v in enumerate(rng.integers(0, 10**9, 60))]
    small = spark.createDataFrame(rows, "series_id string, pos long, x long")
    large = small.withColumn("x", F.col("x") * 4)  # 12 x 12 x variance passes 64 bits
    one = lambda df, make: [r.coef for r in make(df, 12, 5).orderBy("pos").collect()]
    for make in (win.paa_naive, win.paa_fast):
        assert one(large, make) == one(small, make)
    nearest = lambda df: [r.distance for r in discord.bruteforce_profile(df, 12).orderBy("pos").collect()]
    assert np.allclose(nearest(large), nearest(small))


def test_histogram_counts_each_number_once_whatever_the_partitions(spark, sf, tmp_path):
    from rarespan import relational  # noqa: F401
    from rarespan.queries import QUERIES

    spark.read.parquet(f"{sf}/lineitem.parquet").repartition(7).write.parquet(str(tmp_path / "lineitem.parquet"))
    got = [tuple(r) for r in QUERIES["g11_histogram"](spark, str(tmp_path)).collect()]
    assert len({r[:2] for r in got}) == len(got) == 21 and sum(r[2] for r in got) == 60_000


@pytest.mark.parametrize("name", "b8_best_single c01_score c02_best_of c03_average c04_hit_rate c04_hit_rate_candidates c05_win_tie_loss c05b_paired c05c_misses c06_word_cost c14_growth f03_induce_table".split())
def test_measures_read_a_given_table(spark, sf, name):
    from rarespan import relational  # noqa: F401
    from rarespan.queries import QUERIES

    found = QUERIES[name](spark, sf)
    assert found.inputFiles() and not found.isEmpty()


def test_inducer_makes_few_calls_a_token_and_keeps_its_properties():
    import sys

    rng, calls = random.Random(4), [0]
    cycle = [rng.randrange(6) for _ in range(40)]
    tokens = cycle * 10 + [rng.randrange(6) for _ in range(40)] + cycle * 10
    sys.setprofile(lambda frame, event, _: calls.__setitem__(0, calls[0] + (event == "call")))
    try:
        found = induce(tokens)
    finally:
        sys.setprofile(None)
    assert calls[0] < 16 * len(tokens)
    assert expand(found) == tokens
    used = [v >> 1 for body in found.values() for v in body if v & 1]
    assert all(used.count(r) >= 2 for r in found if r)
    pairs = {}
    for r, body in found.items():
        for i, pair in enumerate(zip(body, body[1:], strict=False)):
            assert pairs.setdefault(pair, (r, i)) in ((r, i), (r, i - 1))


def test_round_trip_shuffles_whole_texts_once_and_long_texts_pass_several_batches(spark, tmp_path):
    from rarespan.queries import QUERIES

    rng = random.Random(6)
    texts = {i: " ".join(rng.choice("a b c R1 R2 été".split()) for _ in range(n)) for i, n in enumerate((1, 25_000, 3, 0, 12_000, 7, 40))}
    spark.createDataFrame([*texts.items(), (99, None)], "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    found = QUERIES["m15_roundtrip_doc_words"](spark, str(tmp_path))
    assert found._jdf.queryExecution().executedPlan().toString().count("Exchange") == 1
    got = {}
    for r in found.orderBy("series_id", "pos").collect():
        got.setdefault(int(r.series_id), []).append((r.pos, r.word))
    assert got == {i: list(enumerate(t.split(" "), 1)) for i, t in texts.items()}


def test_inducer_checks_pairs_without_a_call():
    import sys

    rng, calls = random.Random(8), [0]
    cycle = [rng.randrange(6) for _ in range(40)]
    tokens = cycle * 12
    sys.setprofile(lambda frame, event, _: calls.__setitem__(0, calls[0] + (event == "call")))
    try:
        found = induce(tokens)
    finally:
        sys.setprofile(None)
    assert expand(found) == tokens
    assert calls[0] < 4 * len(tokens)


@pytest.mark.parametrize("part", [None, 70, 300])
def test_packed_curves_are_those_of_rows(spark, part):
    rng = np.random.default_rng(5)
    rows = [(name, i + 1, int(v)) for name, size in (("a", 700), ("b", 331)) for i, v in enumerate(np.tile(rng.integers(0, 40, 90), 8)[:size] + rng.integers(0, 2, size))]
    df = spark.createDataFrame(rows, "series_id string, pos long, x long")
    params = com.draw_params(6, w_cap=12)
    want = detect.member_runs(df, 12, params, 50, part)
    runs = den.packed_density(detect.packed_tokens(df, 12, params, 50, part), detect.series_ends(df), part, 64)
    assert sorted(map(tuple, com.packed_stats(runs).collect())) == sorted(map(tuple, com.curve_stats(want).collect()))
    points = lambda curve: {(r.series_id, p): r.de for r in curve.collect() for p in range(r.lo, r.hi + 1)}
    one = points(com.combine(com.scaled(want, com.keep_by_spread(com.curve_stats(want), 0.5)), segment=64))
    assert points(com.unpacked(com.combine_packed(runs, com.keep_by_spread(com.packed_stats(runs), 0.5)))) == one
    assert points(detect.long_committee_curve(df, 12, params, 0.5, 50, part)) == one and (part or len(one) == 1031)


def test_long_series_pass_between_steps_as_one_row_for_each_member_and_chunk(spark):
    rng = np.random.default_rng(6)
    df = spark.createDataFrame([("s", i + 1, int(v)) for i, v in enumerate(rng.integers(0, 99, 2000))], "series_id string, pos long, x long")
    params = com.draw_params(4, w_cap=12)
    packed = detect.packed_tokens(df, 12, params, 500)
    assert packed.count() == 4 * 4 and detect.tokens_by_kernel(df, 12, params, 500).count() > 2000


def test_rounds_committee_picks_its_windows_without_a_plan_for_each_before(spark, sf):
    from rarespan.queries import QUERIES

    found = QUERIES["m28_committee_rounds"](spark, sf)
    assert found._jdf.queryExecution().optimizedPlan().toString().count("Join") < 4


def test_rounds_tables_are_not_broadcast_by_estimates_of_the_compressed_input(spark, sf):
    """Tokens and spans, many rows for each of the input's, look small to a planner that knows the input's file alone."""
    from rarespan.operators import rounds as rnd

    df = series.from_part_cycle(spark, sf)
    t = win.collapse_runs(detect.tokens_by_kernel(df, 40, [(2, 3), (3, 3)]), last=detect.series_ends(df))
    runs = rnd.density_by_rounds(t, 4)
    plan = runs._jdf.queryExecution().sparkPlan().toString()
    assert plan.count("Join") >= 4 and "Broadcast" not in plan


def test_what_holds_is_counted_without_broadcasting_curves(spark, monkeypatch):
    """Curves and grammars, many rows for each of the input's, look small to a planner that knows the input's file alone."""
    from rarespan.queries import QUERIES

    plans = []

    def seen(of):
        def run(*args):
            got = of(*args)
            plans.append(got._jdf.queryExecution().sparkPlan().toString())
            return got

        return run

    monkeypatch.setattr(com, "scaled", seen(com.scaled))
    monkeypatch.setattr(den, "utility_violations", seen(den.utility_violations))
    assert {r.off for r in QUERIES["m28_holds_part_cycle"](spark, "/root/testdata/sf0.001").collect()} == {0}
    assert len(plans) == 2 and all("Join" in p and "Broadcast" not in p for p in plans)


@pytest.mark.parametrize("name", "c01_score c02_best_of c03_average c04_hit_rate c04_hit_rate_candidates c05_win_tie_loss c05b_paired c05c_misses c06_word_cost".split())
def test_measures_scan_orders(spark, sf, name):
    from rarespan.queries import QUERIES

    assert {f.rsplit("/", 1)[-1] for f in QUERIES[name](spark, sf).inputFiles()} == {"orders.parquet"}
