"""Ranking explanations: full, frontier top-k, bounded positions, combinations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.runs import RunStats, settle
from ..sources.kb import KnowledgeGraph
from . import measures as M
from .union import Explanations, combine, combine_local

TIES = ("n_nodes", "n_edges", "pattern_key")


def _order(columns: list[tuple[str, str]]):
    """Sort keys of a total order: the measures, then fewer nodes, fewer edges, smaller key."""
    own = [F.col(c).desc_nulls_last() if way == "desc" else F.col(c).asc_nulls_last() for c, way in columns]
    return own + [F.col(t).asc() for t in TIES]


def keep_topk(scored: DataFrame, k: int | None, columns: list[tuple[str, str]]) -> DataFrame:
    """Rank within each pair; a window with a limit keeps few rows for each pair before the shuffle."""
    out = scored.withColumn("rank", F.row_number().over(Window.partitionBy("pair_id").orderBy(*_order(columns))))
    return out if k is None else out.filter(F.col("rank") <= k)


def _with_shape(patterns: DataFrame, values: DataFrame, name: str = "value") -> DataFrame:
    shape = patterns.select("pair_id", "pattern_key", "n_nodes", "n_edges")
    return shape.join(values.withColumnRenamed("value", name), ["pair_id", "pattern_key"])


def rank_full(kb: KnowledgeGraph, pairs: DataFrame, expl: Explanations, measure: str, k: int | None = 10, **options) -> DataFrame:
    """Score every explanation, sort, keep the first k: (pair_id, rank, pattern_key, n_nodes, n_edges, value)."""
    values = M.measure(measure, kb, pairs, expl.patterns, expl.instances, **options)
    out = keep_topk(_with_shape(expl.patterns, values), k, [("value", M.MEASURES[measure].order)])
    return out.select("pair_id", "rank", "pattern_key", "n_nodes", "n_edges", "value")


def frontier_topk(patterns: DataFrame, instances: DataFrame, measure: str, k: int, limit: int = 5, strategy: str = "lineage", semantics: str = "simple", local: bool = True, stats: RunStats | None = None) -> tuple[DataFrame, Explanations]:
    """Top k of an anti-monotone measure without enumerating all: only explanations among the best k are extended.

    A pattern never ranks ahead of one it contains, in the total order with ties too, so
    the result equals the full ranking's.  ``patterns`` and ``instances``: the path explanations,
    which all stay available to merge with.
    """
    if measure not in M.MEASURES or M.MEASURES[measure].trend != "anti-monotone":
        raise ValueError("frontier_topk needs an anti-monotone measure: size or monocount")
    stats = stats or RunStats()

    def scored(p: DataFrame, i: DataFrame) -> DataFrame:
        return _with_shape(p, M.size(p) if measure == "size" else M.monocount(i))

    if local:
        expl = combine_local(instances, limit, strategy, semantics, (measure, k), stats)
    else:
        best = None

        def frontier(new: DataFrame, new_instances: DataFrame) -> DataFrame:
            nonlocal best
            own = scored(new, new_instances)
            every = own if best is None else best.unionByName(own)
            best = settle(keep_topk(every, k, [("value", "desc")]).drop("rank"))
            return best.select("pair_id", "pattern_key")

        expl = combine(patterns, instances, limit, strategy, semantics, stats=stats, frontier=frontier)
    top = keep_topk(scored(expl.patterns, expl.instances), k, [("value", "desc")])
    return top.select("pair_id", "rank", "pattern_key", "n_nodes", "n_edges", "value"), expl


def bounded_position(kb: KnowledgeGraph, pairs: DataFrame, expl: Explanations, k: int = 10, agg: str = "count", scope: str = "local", wave: int = 64, slices: tuple[int, ...] = (2, 16), sample: int | None = 100, seed: int = 42, kind: str | None = None, semantics: str = "simple", tie_exact: bool = True, stats: RunStats | None = None) -> DataFrame:
    """Top k by position without finishing the positions of hopeless patterns.

    Patterns come in waves, those with few nodes and edges first; without k results there is no bound, so the
    first k of a pair come at once.  The k-th best position so far is a bound: a later pattern is counted over growing slices of the ends, and
    dropped once its count passes the bound (``tie_exact``; else once it reaches it).  With
    k results the rows equal those of the full ranking.
    """
    stats = stats or RunStats()
    own = M.AGGREGATES[agg](expl.instances).join(pairs.select("pair_id", "start"), "pair_id")
    own = settle(_with_shape(expl.patterns, own))
    order = Window.partitionBy("pair_id").orderBy(*TIES)
    place = F.row_number().over(order) - 1
    todo = settle(own.withColumn("wave", F.when(place < k, 0).otherwise(1 + F.floor((place - k) / F.lit(wave))).cast("int")))
    waves = (todo.agg(F.max("wave")).first()[0] or 0) + 1 if not todo.isEmpty() else 0
    starts = None if scope == "local" else settle(M.sample_starts(kb, sample, seed, kind))
    n = slices[-1]
    best = None
    for w in range(waves):
        open_ = todo.filter(F.col("wave") == w).withColumn("p", F.lit(0.0))
        bound = None
        if best is not None:
            bound = best.filter(F.col("rank") == k).select("pair_id", F.col("value").alias("bound"))
        begin = 0
        for upto in slices if bound is not None else (n,):
            asked = open_.select("pattern_key", "start").distinct() if scope == "local" else open_.select("pattern_key").distinct()
            at = asked.select("start").distinct() if scope == "local" else starts
            rows = M.end_values(kb, asked, at, agg, semantics, slices=(n, begin, upto) if upto - begin < n else None)
            on = ["pattern_key", "start"] if scope == "local" else ["pattern_key"]
            dist = rows.groupBy(*on, "value").agg(F.count(F.lit(1)).alias("n_pairs"))
            stats.add("patterns_counted", open_.count())
            more = open_.select("pair_id", *on, "value").join(dist.withColumnRenamed("value", "other"), on).filter("other > value").groupBy("pair_id", "pattern_key").agg(F.sum("n_pairs").alias("more"))
            open_ = open_.join(more, ["pair_id", "pattern_key"], "left").withColumn("p", F.col("p") + F.coalesce("more", F.lit(0))).drop("more")
            if bound is not None:
                over = F.col("p") > F.col("bound") if tie_exact else F.col("p") >= F.col("bound")
                open_ = open_.join(bound, "pair_id", "left").filter(~F.coalesce(over, F.lit(False))).drop("bound")
            open_ = settle(open_)
            begin = upto
        done = open_.select("pair_id", "pattern_key", "n_nodes", "n_edges", F.col("p").alias("value"))
        best = done if best is None else best.drop("rank").unionByName(done)
        best = settle(keep_topk(best, k, [("value", "asc")]))
    if best is None:
        return _with_shape(expl.patterns, M.size(expl.patterns)).withColumn("rank", F.lit(1)).filter("false").select("pair_id", "rank", "pattern_key", "n_nodes", "n_edges", "value")
    return best.select("pair_id", "rank", "pattern_key", "n_nodes", "n_edges", "value")


def rank_combined(kb: KnowledgeGraph, pairs: DataFrame, expl: Explanations, measures: list[str], k: int = 10, lazy_secondary: bool = True, stats: RunStats | None = None, **options) -> DataFrame:
    """Lexicographic combination: sort by the first measure, break ties by the next.

    ``lazy_secondary`` computes a later measure only where it can matter: for explanations
    of a group of ties that reaches into the first k and has more than one member.
    """
    stats = stats or RunStats()
    ways = [(m, M.MEASURES[m].order) for m in measures]
    table = settle(_with_shape(expl.patterns, M.measure(measures[0], kb, pairs, expl.patterns, expl.instances, **options), measures[0]))
    for i, m in enumerate(measures[1:], 1):
        asked = table
        if lazy_secondary:
            tie = Window.partitionBy("pair_id", *measures[:i])
            sort = Window.partitionBy("pair_id").orderBy(*[F.col(c).desc_nulls_last() if way == "desc" else F.col(c).asc_nulls_last() for c, way in ways[:i]])
            asked = table.withColumns({"before": F.rank().over(sort), "same": F.count(F.lit(1)).over(tie)}).filter((F.col("before") <= k) & (F.col("same") > 1)).drop("before", "same")
        asked = settle(asked.select("pair_id", "pattern_key", "n_nodes", "n_edges"))
        stats.add(f"{m}_evaluated", asked.count())
        instances = expl.instances.join(asked.select("pair_id", "pattern_key"), ["pair_id", "pattern_key"], "left_semi")
        values = M.measure(m, kb, pairs, asked, instances, **options)
        table = settle(table.join(values.withColumnRenamed("value", m), ["pair_id", "pattern_key"], "left"))
    return keep_topk(table, k, ways).select("pair_id", "rank", "pattern_key", "n_nodes", "n_edges", *measures)


def learned_combination(features: DataFrame, grades: DataFrame, measures: list[str], k: int = 10):
    """Fit weights of all measures to judged grades and rank by the fitted score: (ranking, model)."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import LinearRegression

    build = VectorAssembler(inputCols=measures, outputCol="features", handleInvalid="skip")
    target = grades.groupBy("pair_id", "pattern_key").agg(F.avg("grade").alias("label"))
    model = LinearRegression(regParam=0.1).fit(build.transform(features.join(target, ["pair_id", "pattern_key"])))
    scored = model.transform(build.transform(features)).withColumnRenamed("prediction", "value")
    return keep_topk(scored, k, [("value", "desc")]).select("pair_id", "rank", "pattern_key", "n_nodes", "n_edges", "value"), model
