"""Target pairs: connectedness, bands, sampling."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.kb import KnowledgeGraph, eid
from .paths import paths


def connectedness(kb: KnowledgeGraph, pairs: DataFrame, length: int = 4) -> DataFrame:
    """(pair_id, start, end, n_paths, band): simple paths of at most ``length`` edges between each pair."""
    n = paths(kb, pairs, length).groupBy("pair_id").agg(F.count(F.lit(1)).alias("n_paths"))
    out = pairs.select("pair_id", "start", "end").join(n, "pair_id", "left").withColumn("n_paths", F.coalesce("n_paths", F.lit(0)))
    return out.withColumn("band", band(F.col("n_paths")))


def band(n: Column) -> Column:
    """low: to 30; medium: to 100; high: above."""
    return F.when(n <= 30, "low").when(n <= 100, "medium").otherwise("high")


def random_pairs(kb: KnowledgeGraph, n: int, seed: int = 7, start_kind: str = "user", end_kind: str = "user") -> DataFrame:
    """``n`` pairs drawn by md5 order of each side, so that any engine draws the same ones."""
    def draw(kind: str, tag: str, column: str) -> DataFrame:
        own = kb.entities.filter(F.col("kind") == kind)
        order = F.md5(F.concat(F.lit(f"{seed}:{tag}:"), F.col("eid").cast("string")))
        first = own.withColumn("o", order).orderBy("o").limit(n)
        return first.select(F.row_number().over(Window.orderBy("o")).cast("long").alias("pair_id"), F.col("eid").alias(column))

    return draw(start_kind, "s", "start").join(draw(end_kind, "e", "end"), "pair_id").filter("start <> end")


def reachable_pairs(kb: KnowledgeGraph, n: int, seed: int = 7, length: int = 2, kind: str = "user") -> DataFrame:
    """Random starts, each with one random entity of its kind within ``length`` edges."""
    order = lambda *c: F.md5(F.concat_ws(":", F.lit(str(seed)), *[x.cast("string") for x in c]))
    own = kb.entities.filter(F.col("kind") == kind)
    starts = own.orderBy(order(F.col("eid"))).limit(n).select(F.col("eid").alias("start"))
    at = starts.withColumn("tip", F.col("start"))
    seen = None
    for _ in range(length):
        at = at.join(kb.steps, at["tip"] == kb.steps["u"]).select("start", F.col("v").alias("tip")).distinct()
        seen = at if seen is None else seen.unionByName(at)
    ends = seen.filter("start <> tip").join(own.select(F.col("eid").alias("tip")), "tip").distinct()
    pick = Window.partitionBy("start").orderBy(order(F.col("start"), F.col("tip")))
    one = ends.withColumn("r", F.row_number().over(pick)).filter("r = 1")
    return one.select(F.row_number().over(Window.orderBy("start")).cast("long").alias("pair_id"), "start", F.col("tip").alias("end"))


def session_pairs(events: DataFrame, gap: str = "30 minutes", n: int | None = None) -> DataFrame:
    """Users active on one key within one session: (start, end, sessions), most frequent first.

    A session of many users gives a chain of neighbours in time rather than all pairs.
    """
    key = F.get_json_object("props", "$.k").cast("long")
    own = events.select("ts", "user_id", key.alias("k")).dropna()
    turn = Window.partitionBy("k").orderBy("ts", "user_id")
    near = own.withColumns({"before": F.lag("user_id").over(turn), "then": F.lag("ts").over(turn)})
    near = near.filter((F.col("before") != F.col("user_id")) & (F.col("ts") <= F.col("then") + F.expr(f"INTERVAL {gap}")))
    pairs = near.select(eid("user", F.least("before", "user_id")).alias("start"), eid("user", F.greatest("before", "user_id")).alias("end"))
    out = pairs.groupBy("start", "end").agg(F.count(F.lit(1)).alias("sessions"))
    return out if n is None else out.orderBy(F.desc("sessions"), "start", "end").limit(n)


def sample_pairs(kb: KnowledgeGraph, per_band: int = 10, seed: int = 7, length: int = 4, candidates: int = 120, start_kind: str = "user", end_kind: str = "user") -> DataFrame:
    """Up to ``per_band`` pairs of each band of connectedness, from random candidates."""
    own = connectedness(kb, random_pairs(kb, candidates, seed, start_kind, end_kind), length)
    pick = Window.partitionBy("band").orderBy("pair_id")
    return own.withColumn("r", F.row_number().over(pick)).filter(F.col("r") <= per_band).drop("r")
