"""The facade: enumeration presets, ranking, counters of an explanation set, sessions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import measures as M
from ..operators import rank as R
from ..operators.grow import grow_enumerate
from ..operators.paths import path_patterns, paths
from ..operators.union import Explanations, at_all, at_models, combine, combine_local, entity_classes
from ..sources.kb import KnowledgeGraph
from .runs import RunStats, settle

#: Named combinations: (path strategy, union strategy); the last one is the default.
COMBOS = {
    "forward+exhaustive": ("forward", "exhaustive"),
    "bidirectional+exhaustive": ("bidirectional", "exhaustive"),
    "activation+exhaustive": ("activation", "exhaustive"),
    "activation+lineage": ("activation", "lineage"),
}
#: A pair with more path instances than this is combined by relational rounds.
LOCAL_INSTANCES = 50_000


def path_explanations(kb: KnowledgeGraph, pairs: DataFrame, n: int = 5, path_strategy: str = "activation", semantics: str = "simple", stats: RunStats | None = None) -> tuple[DataFrame, DataFrame]:
    """Path patterns and their instances, written once for the rounds that follow."""
    found = settle(paths(kb, pairs, n - 1, path_strategy, semantics, stats=stats))
    patterns, instances = path_patterns(found)
    return settle(patterns), settle(instances)


def fits_locally(instances: DataFrame, most: int = LOCAL_INSTANCES) -> bool:
    largest = instances.groupBy("pair_id").agg(F.count(F.lit(1)).alias("c")).agg(F.max("c")).first()[0] or 0
    return largest <= most


def enumerate_explanations(kb: KnowledgeGraph, pairs: DataFrame, n: int = 5, path_strategy: str = "activation", union_strategy: str = "lineage", semantics: str = "simple", paths_only: bool = False, merge_plan: str = "instance_first", plan: str = "auto", stats: RunStats | None = None) -> Explanations:
    """All minimal explanations of at most ``n`` nodes for a batch of pairs.

    ``plan``: relational (a few shuffles a round, any size of pair), local (one task a pair),
    or auto, which takes local if every pair's path instances fit a task, all of them or those of one set of entities a class.
    """
    stats = stats or RunStats()
    patterns, instances = path_explanations(kb, pairs, n, path_strategy, semantics, stats)
    if paths_only:
        empty = pairs.sparkSession.createDataFrame([], "pair_id long, child_key string, parent_key string, path_key string, round int")
        return Explanations(patterns, instances, empty, stats)
    if plan == "local" or (plan == "auto" and merge_plan == "instance_first" and fits_locally(instances)):
        return combine_local(instances, n, union_strategy, semantics, None, stats)
    classes = entity_classes(instances, n)
    if plan == "auto" and merge_plan == "instance_first":
        models = settle(at_models(instances, classes))
        if fits_locally(models):
            expl = combine_local(models, n, union_strategy, semantics, None, stats)
            return Explanations(expl.patterns, at_all(expl.instances, classes), expl.lineage, stats)
    return combine(patterns, instances, n, union_strategy, semantics, merge_plan, stats, classes=classes)


def run_combo(kb: KnowledgeGraph, pairs: DataFrame, combo: str, n: int = 5, **options) -> Explanations:
    """One of the compared combinations by name; ``grow`` is the edge-growth baseline."""
    if combo == "grow":
        return grow_enumerate(kb, pairs, n, **options)
    path_strategy, union_strategy = COMBOS[combo]
    return enumerate_explanations(kb, pairs, n, path_strategy, union_strategy, **options)


def rank(kb: KnowledgeGraph, pairs: DataFrame, measure: str, k: int | None = 10, strategy: str = "full", n: int = 5, semantics: str = "simple", expl: Explanations | None = None, stats: RunStats | None = None, **options) -> DataFrame:
    """Ranked explanations by one measure: full, frontier_topk (anti-monotone) or bounded_position (rarity)."""
    if strategy == "frontier_topk":
        patterns, instances = path_explanations(kb, pairs, n, "activation", semantics, stats)
        return R.frontier_topk(patterns, instances, measure, k, n, semantics=semantics, local=fits_locally(instances), stats=stats)[0]
    expl = expl or enumerate_explanations(kb, pairs, n, semantics=semantics, stats=stats)
    if strategy == "bounded_position":
        if measure not in ("local_position", "global_position"):
            raise ValueError("bounded_position ranks by local_position or global_position")
        return R.bounded_position(kb, pairs, expl, k, scope=measure.partition("_")[0], semantics=semantics, stats=stats, **options)
    return R.rank_full(kb, pairs, expl, measure, k, semantics=semantics, **options)


def explanation_stats(expl: Explanations) -> DataFrame:
    """(pair_id, round, n_patterns, n_instances): by pair and least number of covering paths."""
    n = expl.instances.groupBy("pair_id", "pattern_key").agg(F.count(F.lit(1)).alias("n"))
    return expl.patterns.join(n, ["pair_id", "pattern_key"]).groupBy("pair_id", "round").agg(F.count(F.lit(1)).alias("n_patterns"), F.sum("n").alias("n_instances"))


def measure_table(kb: KnowledgeGraph, pairs: DataFrame, expl: Explanations, measures: list[str], **options) -> DataFrame:
    """All measures side by side: (pair_id, pattern_key, n_nodes, n_edges, *measures)."""
    out = expl.patterns.select("pair_id", "pattern_key", "n_nodes", "n_edges")
    for m in measures:
        values = M.measure(m, kb, pairs, expl.patterns, expl.instances, **options)
        out = out.join(values.withColumnRenamed("value", m), ["pair_id", "pattern_key"], "left")
    return out


def make_session(app: str = "linkwhy", shuffle_partitions: int | None = None) -> SparkSession:
    """A session with adaptive execution; for scripts, not for code that is given one."""
    build = SparkSession.builder.appName(app).config("spark.sql.adaptive.enabled", "true").config("spark.sql.session.timeZone", "UTC")
    return (build.config("spark.sql.shuffle.partitions", shuffle_partitions) if shuffle_partitions else build).getOrCreate()
