"""Connected components of an edge table by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from .common import settle_table

MOST_ROUNDS = 60
#: A node with more than this share of all edge ends (and HOT_ENDS of them) has them dealt to as many places.
HOT_SHARE, HOT_ENDS = 1 / 64, 1_000_000


def _at_node(rows: DataFrame, least: DataFrame, hot: list) -> DataFrame:
    """Join rows (a, b) to one row a node; the rows of hot nodes, of which there are few, go to many places."""
    if not hot:
        return rows.join(least, "a")
    n = int(1 / HOT_SHARE)
    place = F.when(F.col("a").isin(hot), F.pmod(F.xxhash64("b"), F.lit(n)).cast("int")).otherwise(0)
    many = least.withColumn("place", F.explode(F.when(F.col("a").isin(hot), F.sequence(F.lit(0), F.lit(n - 1))).otherwise(F.array(F.lit(0)))))
    return rows.withColumn("place", place).join(many, ["a", "place"]).drop("place")


def _both_ways(edges: DataFrame) -> DataFrame:
    return edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))


def connected_components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node with an edge; the root is the smallest node reachable.

    ``edges`` has columns a and b; self-loops and repeats are allowed.  Each round hangs
    every node's larger neighbours on its smallest one, then its smaller neighbours too;
    the edges end as stars after a number of rounds that grows with the logarithm of the
    longest path.  Only two counters, and the few nodes with a large share of all edges, come to the driver in a round; the edges of a round
    are written to the shared checkpoint folder, so a lost executor costs one round at most.
    """
    now = settle_table(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b").distinct())
    seen, hot = None, []
    for _ in range(MOST_ROUNDS):
        both = _both_ways(now)
        least = both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m"))
        large = _at_node(both.filter("b > a"), least, hot).select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        down = large.groupBy("a").agg(F.min("b").alias("m"))
        small = _at_node(large, down, hot).select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b")
        mark = Observation()
        now = settle_table(small.unionByName(down.select("a", F.col("m").alias("b"))).distinct().observe(mark, F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("sum")))
        n, total = mark.get["n"], mark.get["sum"]
        if seen == (n, total):
            break
        seen = (n, total)
        if 2 * n * HOT_SHARE > HOT_ENDS:  # at most 2 / HOT_SHARE nodes
            ends = _both_ways(now).groupBy("a").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > n * HOT_SHARE)
            hot = [r["a"] for r in ends.collect()]
    else:
        raise RuntimeError("components did not settle; the edges may change between reads")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
