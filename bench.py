"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line on standard output."""

from __future__ import annotations

import json
import os
import sys
import time
from statistics import median

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def _line(points: list[tuple[int, float]]) -> tuple[float, float]:
    """Slope for 1,000 instances and R squared of a straight line through the points."""
    n = len(points)
    mx, my = sum(x for x, _ in points) / n, sum(y for _, y in points) / n
    sxy, sxx, syy = sum((x - mx) * (y - my) for x, y in points), sum((x - mx) ** 2 for x, _ in points), sum((y - my) ** 2 for _, y in points)
    return round(1000 * sxy / (sxx or 1), 3), round(sxy * sxy / ((sxx * syy) or 1), 3)


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("OFF")

    from linkwhy.operators import rank as R
    from linkwhy.operators.grow import grow_enumerate
    from linkwhy.operators.pairs import connectedness, random_pairs, sample_pairs
    from linkwhy.plans import engine
    from linkwhy.plans.runs import RunStats, settle
    from linkwhy.sources.kb import build_kb

    queries: dict[str, float] = {}
    notes: dict[str, object] = {}

    def timed(name: str, run):
        began = time.time()
        out = run()
        queries[name] = round(time.time() - began, 2)
        return out

    def force(df):
        return df.agg(F.count(F.lit(1))).first()[0]

    kb = timed("kb_commerce_twin", lambda: build_kb(spark, sf_dir, "commerce").pinned())
    notes["commerce_edges"] = kb.edges.count()
    pairs = settle(random_pairs(kb, 30, 7, "customer", "customer"))
    timed("connectedness_30_pairs_commerce", lambda: force(connectedness(kb, pairs)))
    big = timed("explain_30_pairs_commerce_n5", lambda: engine.enumerate_explanations(kb, pairs, 5))
    notes["commerce_instances"] = big.instances.count()
    timed("top10_monocount_commerce", lambda: force(engine.rank(kb, pairs, "monocount", 10, "frontier_topk")))

    # Ten pairs of each band of connectedness, as far as the candidates have them.
    banded = timed("pairs_by_band_commerce", lambda: settle(sample_pairs(kb, 10, 7, 4, 120, "customer", "customer")))
    for band in ("low", "medium", "high"):
        own = settle(banded.filter(F.col("band") == band).select("pair_id", "start", "end"))
        notes[f"pairs_{band}"] = own.count()
        if not notes[f"pairs_{band}"]:
            continue
        for combo in ("forward+exhaustive", "activation+lineage"):
            stats = RunStats()
            timed(f"{combo}_{band}", lambda c=combo, o=own, s=stats: engine.run_combo(kb, o, c, stats=s))
            notes[f"work_{combo}_{band}"] = stats.counters
    # Edge growth against paths and unions, at the size that growth can do.
    few = settle(pairs.filter("pair_id <= 3"))
    growth = RunStats()
    timed("grow_n3_commerce_3_pairs", lambda: grow_enumerate(kb, few, 3, stats=growth))
    timed("activation+lineage_n3_commerce_3_pairs", lambda: engine.enumerate_explanations(kb, few, 3))
    notes["work_grow_n3"] = growth.counters

    # Activity graphs by width of the window of events.
    act = build_kb(spark, sf_dir, "activity", ts_to="2024-01-03").pinned()
    some = settle(random_pairs(act, 30, 7))
    for combo in engine.COMBOS:
        stats = RunStats()
        expl = timed(f"combo_{combo}", lambda c=combo, s=stats: engine.run_combo(act, some, c, stats=s))
        notes[f"work_{combo}"] = stats.counters
    points = []
    for until in ("2024-01-02", "2024-01-03", "2024-01-04"):
        g = build_kb(spark, sf_dir, "activity", ts_to=until).pinned()
        began = time.time()
        n = engine.enumerate_explanations(g, some, 5).instances.count()
        points.append((n, round(time.time() - began, 2)))
    notes["instances_and_seconds"] = points
    notes["seconds_per_1000_instances_and_r2"] = _line(points)
    stats = RunStats()
    timed("rank_full_monocount", lambda: force(R.rank_full(act, some, engine.enumerate_explanations(act, some, 5), "monocount", 10)))
    for k in (1, 5, 10, 20, 50, 100):
        s = RunStats()
        timed(f"frontier_top{k}_monocount", lambda k=k, s=s: force(engine.rank(act, some, "monocount", k, "frontier_topk", stats=s)))
        notes[f"frontier_top{k}_merges"] = s.counters.get("merges_tried")
    three = settle(some.filter("pair_id <= 3"))
    small = engine.enumerate_explanations(act, three, 5)
    timed("local_position_full", lambda: force(R.rank_full(act, three, small, "local_position", 10)))
    timed("local_position_bounded", lambda: force(R.bounded_position(act, three, small, 10, stats=stats)))
    lazy = RunStats()
    timed("size_then_local_position", lambda: force(R.rank_combined(act, three, small, ["size", "local_position"], 10, stats=lazy)))
    notes["positions_evaluated"] = {"all": small.patterns.count(), **lazy.counters}
    print(json.dumps({"metric": "explain_queries_median_seconds", "value": round(median(queries.values()), 2), "unit": "sec", "queries": queries, "sf": sf_dir.rpartition("sf")[2], "notes": notes}))
    spark.stop()


if __name__ == "__main__":
    main()
