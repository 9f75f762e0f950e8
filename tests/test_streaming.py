import datetime
import time

import pytest
from pyspark.sql import functions as F

from rarespan.operators import windows as win
from rarespan.plans import detect
from rarespan.sources import series
from rarespan.streaming import joins, resample, sinks, stateful


@pytest.fixture(scope="module")
def split(spark, sf, tmp_path_factory):
    folder = tmp_path_factory.mktemp("events")
    e = spark.read.parquet(f"{sf}/events.parquet")
    step = -(-e.count() // 4)
    ranked = e.withColumn("part", F.expr(f"(event_id - 1) div {step}"))
    for p in sorted(r.part for r in ranked.select("part").distinct().collect()):
        ranked.where(F.col("part") == p).drop("part").coalesce(1).write.mode("append").parquet(str(folder))
    return str(folder), resample.with_instant(e)


def drain(frame, tmp_path, name):
    q = frame.writeStream.format("memory").queryName(name).outputMode("append").option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert q.exception() is None
    return frame.sparkSession.table(name)


@pytest.mark.parametrize(("name", "f"), [("tumbling", resample.tumbling), ("sliding", resample.sliding), ("bursts", resample.bursts)])
def test_closed_windows_equal_the_batch(spark, split, tmp_path, name, f):
    folder, batch = split
    got = {tuple(r) for r in drain(f(resample.read_events(spark, folder, 4)), tmp_path, name).collect()}
    want = {tuple(r) for r in f(batch).collect()}
    assert got and got <= want and len(got) > 0.9 * len(want)


def test_duplicates_go(spark, split, tmp_path):
    folder, batch = split
    s = resample.read_events(spark, folder, 4)
    assert drain(resample.deduplicated(s.union(s)), tmp_path, "dedup").count() == batch.count()


def test_streamed_symbols_equal_batch_tokens(spark, sf, tmp_path):
    df = series.from_events(spark, sf, by="event_type").where("pos <= 300")
    folder = str(tmp_path / "points")
    for k in range(3):
        df.where(F.pmod("pos", F.lit(3)) == k).coalesce(1).write.mode("append").parquet(folder)  # far out of order
    stream = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(folder)
    params = [(3, 3), (4, 5)]
    got = sorted(map(tuple, drain(stateful.symbols(stream, 24, params), tmp_path, "symbols").collect()))
    want = win.collapse_runs(detect.tokens_by_kernel(df, 24, params)).select("series_id", "w", "a", "pos", "word")
    assert got == sorted(map(tuple, want.collect()))


def test_closed_grammars_cover_their_positions(spark, sf, tmp_path):
    df = series.from_events(spark, sf)
    t = win.collapse_runs(detect.tokens_by_kernel(df, 24, [(3, 3)])).select("series_id", "w", "a", "pos", "word")
    folder = str(tmp_path / "tokens")
    t.coalesce(1).write.parquet(folder)
    stream = spark.readStream.schema(t.schema).parquet(folder)
    got = sorted((r.lo, r.hi) for r in drain(stateful.grammars(stream, 50), tmp_path, "grammars").collect())
    assert got and all(a[1] + 1 == b[0] for a, b in zip(got, got[1:], strict=False))


def test_provisional_density():
    steps = stateful.provisional_depth("ab bc aa cc ca ab bc aa".split())
    assert steps[-1] == [1, 1, 1, 0, 0, 1, 1, 1] and steps[5] == [0] * 6


def test_stateful_grammar_equals_one_induced_at_once(spark, sf, tmp_path):
    df = series.from_events(spark, sf)
    t = win.collapse_runs(detect.tokens_by_kernel(df, 24, [(3, 3)])).select("series_id", "w", "a", "pos", "word")
    rows = t.orderBy("pos").collect()
    folder = str(tmp_path / "cut")
    for k in range(0, len(rows), -(-len(rows) // 3)):
        spark.createDataFrame(rows[k : k + -(-len(rows) // 3)], t.schema).coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema(t.schema).option("maxFilesPerTrigger", 1).parquet(folder)
    got = sorted((r.lo, r.hi, r.d) for r in drain(stateful.grammars(stream, 60), tmp_path, "whole_grammars").collect())
    want = []
    for k in range(0, len(rows) - 60, 60):
        part = rows[k : k + 60]
        runs = stateful.kernel.density_runs(stateful.np.array([r.pos for r in part]), stateful.np.array([r.word for r in part]), rows[k + 60].pos - 1, part[0].pos)
        want += [tuple(map(int, r)) for r in zip(*runs, strict=True)]
    assert got == want


def _poll(spark, name, enough, seconds=100):
    end = time.time() + seconds
    while time.time() < end:
        if enough(spark.table(name).collect()):
            return
        time.sleep(1)


def test_idle_grammars_are_closed_and_gaps_passed_over(spark, tmp_path):
    tokens = [("s", 3, 3, 10 * i + 1, w) for i, w in enumerate("ab bc aa cc ca ab bc aa".split())]
    folder = str(tmp_path / "idle")
    spark.createDataFrame(tokens, "series_id string, w int, a int, pos long, word string").coalesce(1).write.parquet(folder)
    stream = stateful.grammars(spark.readStream.schema("series_id string, w int, a int, pos long, word string").parquet(folder), idle_ms=2000)
    points = str(tmp_path / "gap")
    values = [(p, p * 7 % 5) for p in range(1, 41) if p != 15]
    spark.createDataFrame([("g", p, x) for p, x in values], "series_id string, pos long, x long").coalesce(1).write.parquet(points)
    gap = stateful.symbols(spark.readStream.schema("series_id string, pos long, x long").parquet(points), 6, [(3, 3)], patience_ms=2000)
    queries = [q.writeStream.format("memory").queryName(n).outputMode("append").option("checkpointLocation", str(tmp_path / n)).trigger(processingTime="1 second").start() for q, n in ((stream, "idle_g"), (gap, "gap_s"))]
    try:
        _poll(spark, "idle_g", bool)
        _poll(spark, "gap_s", lambda rows: any(r.pos > 15 for r in rows))
    finally:
        for q in queries:
            q.stop()
    got = sorted((r.lo, r.hi, r.d) for r in spark.table("idle_g").collect())
    assert got == [(1, 30, 1), (31, 50, 0), (51, 71, 1)]
    at = {r.pos for r in spark.table("gap_s").collect()}
    assert min(at) == 1 and 16 in at and not at & set(range(10, 16))  # no window holds position 15


def test_late_rows_are_counted_and_left_out(spark, tmp_path):
    t0 = datetime.datetime(2024, 1, 1)
    folder = str(tmp_path / "late")
    for hours in ([0, 1, 10], [11, 20], [2, 21]):  # 2 comes when the watermark is far beyond it
        rows = [(h, t0 + datetime.timedelta(hours=h, minutes=5), 1, "click", 1.0, "") for h in hours]
        spark.createDataFrame(rows, resample.EVENTS).coalesce(1).write.mode("append").parquet(folder)
        time.sleep(0.1)
    frame = resample.tumbling(resample.read_events(spark, folder, 1))
    q = sinks.to_parquet(frame, str(tmp_path / "closed"), str(tmp_path / "late_log"))
    q.awaitTermination(120)
    steps = {r.step - int(t0.replace(tzinfo=datetime.UTC).timestamp()) // 3600 for r in spark.read.parquet(str(tmp_path / "closed")).collect()}
    assert sinks.dropped_late(q) == 1 and 2 not in steps and {0, 1, 10, 11} <= steps


def test_batches_can_be_written_again(spark, split, tmp_path):
    folder, batch = split
    out = str(tmp_path / "out")
    some = resample.read_events(spark, folder, 1).select("event_id", "user_id", "event_type")
    sinks.to_batches(some, out, str(tmp_path / "log1"), ["event_id"]).awaitTermination(120)
    sinks.to_batches(some, out, str(tmp_path / "log2"), ["event_id"]).awaitTermination(120)  # the checkpoint was lost: all batches come again
    got = sinks.read_batches(spark, out, ["event_id"])
    assert spark.read.parquet(out).count() == got.count() == batch.count()


def test_stream_joins_equal_the_batch(spark, split, tmp_path):
    folder, batch = split
    step = F.floor(F.unix_timestamp("ts") / 3600)
    spans = spark.createDataFrame([("click", 473352 + 5, 473352 + 700, "a"), ("click", 473352 + 300, 473352 + 310, "b"), ("view", 0, 10, "c")], "series_id string, lo long, hi long, tag string")
    on = lambda e: joins.in_spans(e.select("event_id", F.col("event_type").alias("series_id"), step.alias("step")), spans, width=64)
    got = drain(on(resample.read_events(spark, folder, 1)), tmp_path, "spans")
    want = sorted(map(tuple, on(batch).collect()))
    assert want and sorted(map(tuple, got.collect())) == want
    pairs = lambda e, f: joins.followed(e.where("event_type = 'error'"), f.where("event_type = 'purchase'"))
    got = drain(pairs(resample.read_events(spark, folder, 4), resample.read_events(spark, folder, 4)), tmp_path, "pairs")
    want = sorted(map(tuple, pairs(batch, batch).collect()))
    assert want and sorted(map(tuple, got.collect())) == want
