"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(2 * int(cpus)))
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.checkpoint.dir", tempfile.mkdtemp(prefix="bench-checkpoint-"))
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")

    from rarespan.operators import discord
    from rarespan.plans import detect
    from rarespan.runtime import cut
    from rarespan.sources import series

    times: dict[str, float] = {}

    def timed(name: str, frame) -> float:
        t = time.perf_counter()
        frame().write.format("noop").mode("overwrite").save()
        times[name] = round(time.perf_counter() - t, 3)
        return times[name]

    def spread(df, parts: int):
        """Core so that the series is cut into about ``parts`` chunks."""
        n = df.agg(F.max("pos")).first()[0]
        return n, max(4096, -(-n // parts))

    timed("warm_up", lambda: detect.detect_single(series.from_events(spark, sf_dir), 24, 3, 3))
    begin = time.perf_counter()
    seq = cut(series.from_lineitem(spark, sf_dir))
    times["source_lineitem"] = round(time.perf_counter() - begin, 3)
    points, core = spread(seq, 2 * int(cpus))
    timed("committee_lineitem_n900", lambda: detect.detect_committee(seq, 900, k=2, core=core))
    walk = cut(series.from_orders(spark, sf_dir, "walk"))
    n_walk, core = spread(walk, 2 * int(cpus))
    for n in (100, 400):
        timed(f"committee_walk_n{n}", lambda n=n: detect.detect_committee(walk, n, core=core))
    ladder = [k for k in (10_000, 20_000, 40_000, 80_000, 150_000) if k <= n_walk]
    for k in ladder:
        part = cut(walk.where(F.col("pos") <= k))
        timed(f"committee_walk_{k}", lambda part=part: detect.detect_committee(part, 200, core=core))
        timed(f"discord_walk_{k}", lambda part=part: discord.discord_profile(part, 200, tiles=2 * int(cpus)))
    users = cut(series.from_events(spark, sf_dir, None, "user_id"))
    timed("committee_many_series", lambda: detect.detect_committee(users, 8, n_members=10))
    times.pop("warm_up")

    import math

    def slope(kind: str) -> float | None:
        xs = [(math.log(k), math.log(times[f"{kind}_walk_{k}"])) for k in ladder]
        if len(xs) < 2:
            return None
        mx, my = sum(x for x, _ in xs) / len(xs), sum(y for _, y in xs) / len(xs)
        return round(sum((x - mx) * (y - my) for x, y in xs) / sum((x - mx) ** 2 for x, _ in xs), 2)

    out = {
        "metric": "committee over all line items, n=900",
        "value": times["committee_lineitem_n900"],
        "unit": "sec",
        "queries": times,
        "sf": Path(sf_dir).name.removeprefix("sf"),
        "points": points,
        "points_per_s": round(points / times["committee_lineitem_n900"]),
        "growth_committee": slope("committee"),
        "growth_discord": slope("discord"),
        "discord_over_committee": round(times[f"discord_walk_{ladder[-1]}"] / times[f"committee_walk_{ladder[-1]}"], 2) if ladder else None,
        "cpus": int(cpus),
    }
    print(json.dumps(out), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
