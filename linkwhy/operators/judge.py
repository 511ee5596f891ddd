"""Judged rankings: stand-in grades, discounted scores, means, path share."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def stand_in_grades(patterns: DataFrame, judges: int = 10) -> DataFrame:
    """Grades 0, 1, 2 from a digest of judge, pair and pattern: only good for checking arithmetic."""
    own = patterns.select("pair_id", "pattern_key").distinct().withColumn("judge_id", F.explode(F.sequence(F.lit(1), F.lit(judges))))
    digest = F.md5(F.concat_ws("|", F.col("judge_id").cast("string"), F.col("pair_id").cast("string"), "pattern_key"))
    return own.select("judge_id", "pair_id", "pattern_key", (F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") % 3).cast("int").alias("grade"))


def rule_grades(expl_patterns: DataFrame, edges: DataFrame, judges: int = 1) -> DataFrame:
    """An illustrative judge: the rarer the rarest label of a pattern, the higher its grade."""
    total = edges.count() or 1
    share = edges.groupBy("rel").agg((F.count(F.lit(1)) / total).alias("share"))
    own = expl_patterns.select("pair_id", "pattern_key", F.explode("edges").alias("e")).select("pair_id", "pattern_key", "e.rel").join(share, "rel")
    rare = own.groupBy("pair_id", "pattern_key").agg(F.min("share").alias("s"))
    grade = F.when(F.col("s") < 0.05, 2).when(F.col("s") < 0.15, 1).otherwise(0)
    return rare.withColumn("judge_id", F.explode(F.sequence(F.lit(1), F.lit(judges)))).select("judge_id", "pair_id", "pattern_key", grade.alias("grade"))


def dcg_score(ranked: DataFrame, judgements: DataFrame, k: int = 10) -> DataFrame:
    """(pair_id, judge_id, score): graded ranks discounted by 1 / log2(rank + 1), scaled to 0..100.

    All judged grades 2 give 100.  A pair with fewer than k explanations is scaled by its own number.
    """
    weight = 1 / F.log2(F.col("rank") + 1)
    top = ranked.filter(F.col("rank") <= k).withColumn("w", weight)
    most = top.groupBy("pair_id").agg(F.sum(2 * F.col("w")).alias("most"))
    got = top.join(judgements, ["pair_id", "pattern_key"]).groupBy("pair_id", "judge_id").agg(F.sum(F.col("w") * F.col("grade")).alias("got"))
    return got.join(most, "pair_id").select("pair_id", "judge_id", (100 * F.col("got") / F.col("most")).alias("score"))


def mean_scores(scores: DataFrame, pairs: list[int] | None = None) -> DataFrame:
    """A row for each measure with a column for each pair and the mean: ``scores`` has measure, pair_id, score."""
    each = scores.groupBy("measure", "pair_id").agg(F.avg("score").alias("score"))
    wide = each.groupBy("measure").pivot("pair_id", pairs).agg(F.first("score")) if pairs else each.groupBy("measure").pivot("pair_id").agg(F.first("score"))
    return wide.join(each.groupBy("measure").agg(F.avg("score").alias("avg")), "measure")


def path_share(patterns: DataFrame, judgements: DataFrame, k: int) -> DataFrame:
    """(pair_id, n_best, n_paths): how many of the k explanations that judges liked best are paths."""
    liked = judgements.groupBy("pair_id", "pattern_key").agg(F.avg("grade").alias("g")).join(patterns.select("pair_id", "pattern_key", "round"), ["pair_id", "pattern_key"])
    order = Window.partitionBy("pair_id").orderBy(F.desc("g"), "pattern_key")
    best = liked.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= k)
    return best.groupBy("pair_id").agg(F.count(F.lit(1)).alias("n_best"), F.sum((F.col("round") == 1).cast("int")).alias("n_paths"))
