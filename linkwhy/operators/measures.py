"""Interestingness of explanations: structure, aggregates, rarity in distributions, combinations.

Scores are ordered so that larger is more interesting, but for positions, where smaller is.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import middle
from ..functions.udfs import automorphism_count, edges_of, grounded_conductance, middle_sides, walk_conductance
from ..plans.runs import settle
from ..sources.kb import KnowledgeGraph
from .match import SEMANTICS, match


@dataclass(frozen=True)
class Measure:
    """trend: how the score moves when a pattern grows; order: which end is interesting."""

    trend: str
    order: str = "desc"


MEASURES = {
    "size": Measure("anti-monotone"),
    "monocount": Measure("anti-monotone"),
    "count": Measure("neither"),
    "walk": Measure("monotone"),
    "local_position": Measure("neither", "asc"),
    "global_position": Measure("neither", "asc"),
    "local_deviation": Measure("neither"),
    "global_deviation": Measure("neither"),
}
KEYS = ["pair_id", "pattern_key"]


def size(patterns: DataFrame) -> DataFrame:
    return patterns.select(*KEYS, (-F.col("n_nodes")).cast("double").alias("value"))


def walk(patterns: DataFrame, sink: float | None = None) -> DataFrame:
    """Delivered current; solved once for each different pattern."""
    f = walk_conductance if sink is None else grounded_conductance(sink)
    own = patterns.select("pattern_key").distinct().withColumn("value", f("pattern_key"))
    return patterns.select(*KEYS).join(own, "pattern_key").select(*KEYS, "value")


def count(instances: DataFrame, unit: str = "mapping", by: list[str] | None = None) -> DataFrame:
    """Number of instances; ``unit="subgraph"`` counts mirror images of one subgraph once."""
    out = instances.groupBy(*(by or KEYS)).agg(F.count(F.lit(1)).cast("double").alias("value"))
    if unit == "subgraph":
        same = out.select("pattern_key").distinct().withColumn("k", automorphism_count("pattern_key"))
        out = out.join(same, "pattern_key").withColumn("value", F.col("value") / F.col("k")).drop("k")
    return out.select(*(by or KEYS), "value")


def monocount(instances: DataFrame, approx: float | None = None, by: list[str] | None = None) -> DataFrame:
    """Least number of different entities at any variable; 1 for the direct edge, which has none."""
    by = by or KEYS
    each = instances.select(*by, F.posexplode_outer("binding").alias("place", "entity"))
    distinct = F.approx_count_distinct("entity", approx) if approx else F.count_distinct("entity")
    return each.groupBy(*by, "place").agg(distinct.alias("u")).groupBy(*by).agg(F.min(F.when(F.col("place").isNull(), 1).otherwise(F.col("u"))).cast("double").alias("value"))


AGGREGATES = {"count": count, "monocount": monocount}


def end_values(kb: KnowledgeGraph, patterns: DataFrame, starts: DataFrame | None, agg: str = "count", semantics: str = "simple", include_self: bool = False, slices=None) -> DataFrame:
    """(pattern_key, start, end, value) with the end left open, and the start too if ``starts`` is None."""
    rows = match(kb, patterns, "none" if starts is None else "start", starts, semantics, slices)
    rows = rows if include_self else rows.filter("start <> end")
    return AGGREGATES[agg](rows.select("pattern_key", "start", "end", "binding"), by=["pattern_key", "start", "end"])


def twins(kb: KnowledgeGraph, patterns: DataFrame) -> DataFrame:
    """(eid, twin, place, members): nodes with equal steps under the patterns' labels share the smallest of them as ``twin``.

    To swap two such nodes changes no step, so they have equal values against every other node.  Digests find the
    classes, and each member's steps are then held against those of its twin.
    """
    rels = patterns.select("pattern_key").distinct().select(F.explode(edges_of("pattern_key")).alias("e")).select("e.rel").distinct()
    steps = kb.steps.join(F.broadcast(rels), "rel", "left_semi").select("u", "rel", "dir", "v")
    digest = lambda seed: F.bit_xor(F.xxhash64(F.lit(seed), "rel", "dir", "v")).alias(f"h{seed}")
    own = steps.groupBy("u").agg(F.count(F.lit(1)).alias("n"), digest(1), digest(2))
    own = settle(own.withColumn("twin", F.min("u").over(Window.partitionBy("n", "h1", "h2"))).select("u", "n", "twin"))
    asked = steps.join(own.filter("u <> twin").select("u", "twin"), "u")
    same = asked.join(steps.withColumnRenamed("u", "twin"), ["twin", "rel", "dir", "v"], "left_semi").groupBy("u").agg(F.count(F.lit(1)).alias("common"))
    own = own.join(same, "u", "left").withColumn("twin", F.when(F.col("common") == F.col("n"), F.col("twin")).otherwise(F.col("u")))
    klass = Window.partitionBy("twin")
    return settle(own.select(F.col("u").alias("eid"), "twin", F.row_number().over(klass.orderBy("u")).alias("place"), F.count(F.lit(1)).over(klass).alias("members")))


def twin_values(kb: KnowledgeGraph, patterns: DataFrame, own: DataFrame, agg: str = "count", semantics: str = "simple", include_self: bool = False) -> DataFrame:
    """(pattern_key, twin, value, n_pairs): for a start of each class of ``twins``, how many ends have each value.

    The first of a class stands for its starts.  Among the ends it stands for its class too, and the second for the others of the start's own class.
    """
    starts = own.filter("place = 1").select(F.col("eid").alias("start"))
    rows = match(kb, patterns, "start", starts, semantics, among=own.filter("place <= 2"))
    rows = AGGREGATES[agg](rows.select("pattern_key", "start", "end", "binding"), by=["pattern_key", "start", "end"])
    rows = rows.join(own.select(F.col("eid").alias("end"), "twin", "place", "members"), "end")
    weight = (
        F.when(F.col("start") == F.col("end"), F.lit(1 if include_self else 0))
        .when(F.col("twin") == F.col("start"), F.col("members") - 1)
        .when(F.col("place") == 1, F.col("members"))
        .otherwise(0)
    )
    rows = rows.withColumn("w", weight).filter("w > 0")
    return rows.groupBy("pattern_key", F.col("start").alias("twin"), F.col("value").cast("long").alias("value")).agg(F.sum("w").alias("n_pairs"))


#: Steps of a pattern that a block of ends, and at least a block of starts, takes.
BLOCK_STEPS, LEAST_STEPS = 1 << 21, 1 << 15
#: Partitions of the block pairs at most; beyond it a task takes several.
MOST_TASKS = 20_000


def middle_values(kb: KnowledgeGraph, patterns: DataFrame, starts: DataFrame | None = None, semantics: str = "simple", include_self: bool = False, by_start: bool = True) -> DataFrame:
    """(pattern_key, start, value, n_pairs) of patterns with one variable, without a row for any instance or pair; start is null unless ``by_start``.

    ``patterns``: pattern_key and ``sides``.  Each target's entities are one array.  Targets are dealt to blocks by a hash, a block is packed into
    one row, and a task counts a block of starts against one of ends.  What is written grows with the steps and, by
    the copies of packed blocks, with the number of their pairs.
    """
    if semantics not in SEMANTICS:
        raise ValueError(f"semantics must be one of {SEMANTICS}")
    spark = patterns.sparkSession
    keys = settle(patterns.select("pattern_key", "sides").withColumn("p", F.row_number().over(Window.orderBy("pattern_key"))))
    ways = keys.select("p", F.explode("sides").alias("s")).select("p", "s.*")
    ways = ways.withColumn("need", F.count(F.lit(1)).over(Window.partitionBy("p", "side")))
    steps = kb.steps if semantics == "sql" else kb.steps.filter("u <> v")
    met = steps.join(F.broadcast(ways), ["rel", "dir"]).groupBy("p", "side", "u", "v").agg(F.count(F.lit(1)).alias("n"), F.first("need").alias("need"))
    met = met.filter("n = need").groupBy("p", "side", "u").agg(F.collect_list("v").alias("vs"))
    if starts is not None:
        met = met.join(starts.select(F.col("start").alias("u"), F.lit(True).alias("asked")).distinct(), "u", "left").filter("side = 1 OR asked").drop("asked")
    met = settle(met)

    n = lambda side: F.coalesce(F.sum(F.when(F.col("side") == side, F.size("vs"))), F.lit(0))
    a_task = F.least(F.lit(BLOCK_STEPS), F.greatest(F.lit(LEAST_STEPS), F.ceil(n(0) / F.lit(4 * spark.sparkContext.defaultParallelism))))
    blocks = settle(met.groupBy("p").agg(F.ceil(n(0) / a_task).cast("int").alias("b0"), F.ceil(n(1) / F.lit(BLOCK_STEPS)).cast("int").alias("b1")).filter("b0 > 0 AND b1 > 0"))
    tasks = blocks.agg(F.sum(F.col("b0").cast("long") * F.col("b1"))).first()[0] or 0
    own = F.when(F.col("side") == 0, F.col("b0")).otherwise(F.col("b1"))
    dealt = met.join(F.broadcast(blocks), "p").select("p", "side", F.pmod(F.xxhash64("u"), own).cast("int").alias("block"), "u", "vs")
    packed = settle(dealt.groupBy("p", "side", "block").applyInArrow(middle.pack, middle.BLOCK)).join(F.broadcast(blocks), "p")

    places = max(1, min(tasks, MOST_TASKS))
    copies = lambda other: F.explode(F.sequence(F.lit(0), F.col(other) - 1))
    left = packed.filter("side = 0").select("p", F.col("block").alias("i"), copies("b1").alias("j"), F.col("data").alias("starts")).repartition(places, "p", "i", "j")
    right = packed.filter("side = 1").select(F.col("p").alias("q"), copies("b0").alias("i"), F.col("block").alias("j"), F.col("data").alias("ends")).repartition(places, "q", "i", "j")
    meet = middle.counter(by_start, include_self and semantics == "sql")
    rows = left.groupBy("p", "i", "j").cogroup(right.groupBy("q", "i", "j")).applyInArrow(meet, middle.VALUES)
    rows = rows.groupBy("p", "start", "value").agg(F.sum("n_pairs").alias("n_pairs"))
    return rows.join(F.broadcast(keys.select("p", "pattern_key")), "p").select("pattern_key", "start", "value", "n_pairs")


def by_shape(patterns: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(patterns with one variable and their ``sides``, the other patterns)."""
    own = settle(patterns.select("pattern_key").distinct().withColumn("sides", middle_sides("pattern_key")))
    return own.filter("sides IS NOT NULL"), own.filter("sides IS NULL").select("pattern_key")


def local_distribution(kb: KnowledgeGraph, patterns: DataFrame, starts: DataFrame, agg: str = "count", semantics: str = "simple", include_self: bool = False, by_twins: bool = False) -> DataFrame:
    """(pattern_key, start, value, n_pairs): how many ends have each value, with the start fixed.

    ``by_twins``, for many starts: patterns with one variable are counted block by block, where count and monocount are
    one; of others a class of interchangeable nodes is counted once.
    """
    if by_twins:
        single, other = by_shape(patterns)
        out = None if single.isEmpty() else middle_values(kb, single, starts, semantics, include_self)
        if out is None or not other.isEmpty():
            classes = twins(kb, other)
            dist = twin_values(kb, other, classes, agg, semantics, include_self)
            asked = starts.select("start").distinct().join(classes.select(F.col("eid").alias("start"), "twin"), "start")
            dist = asked.join(dist, "twin").select("pattern_key", "start", "value", "n_pairs")
            out = dist if out is None else out.unionByName(dist)
        return out
    own = end_values(kb, patterns, starts, agg, semantics, include_self)
    return own.groupBy("pattern_key", "start", F.col("value").cast("long").alias("value")).agg(F.count(F.lit(1)).alias("n_pairs"))


def sample_starts(kb: KnowledgeGraph, n: int = 100, seed: int = 42, kind: str | None = None) -> DataFrame:
    """Starts drawn by an order that any engine can reproduce: md5 of seed and identifier."""
    own = kb.entities.filter(F.col("kind") == kind) if kind else kb.entities
    return own.orderBy(F.md5(F.concat(F.lit(f"{seed}:"), F.col("eid").cast("string")))).limit(n).select(F.col("eid").alias("start"))


def global_distribution(kb: KnowledgeGraph, patterns: DataFrame, agg: str = "count", sample: int | None = 100, seed: int = 42, kind: str | None = None, scale: bool = False, semantics: str = "simple", include_self: bool = False) -> DataFrame:
    """(pattern_key, value, n_pairs) over all pairs, or over ``sample`` random starts.

    Exact (``sample=None``) counts patterns with one variable block by block; of others its work grows with the square of the
    different classes of ``twins``.  ``scale`` blows the sampled numbers up to all entities.
    """
    if sample is None:
        single, other = by_shape(patterns)
        out = None if single.isEmpty() else middle_values(kb, single, None, semantics, include_self, by_start=False).drop("start")
        if out is None or not other.isEmpty():
            classes = twins(kb, other)
            dist = twin_values(kb, other, classes, agg, semantics, include_self).join(classes.filter("place = 1").select("twin", "members"), "twin")
            dist = dist.groupBy("pattern_key", "value").agg(F.sum(F.col("n_pairs") * F.col("members")).alias("n_pairs"))
            out = dist if out is None else out.unionByName(dist)
        return out
    starts = settle(sample_starts(kb, sample, seed, kind))
    own = end_values(kb, patterns, starts, agg, semantics, include_self)
    out = own.groupBy("pattern_key", F.col("value").cast("long").alias("value")).agg(F.count(F.lit(1)).alias("n_pairs"))
    if scale and sample is not None:
        every = kb.entities.filter(F.col("kind") == kind).count() if kind else kb.entities.count()
        out = out.withColumn("n_pairs", F.col("n_pairs") * F.lit(every / max(1, min(sample, every))))
    return out


def position(scored: DataFrame, dist: DataFrame) -> DataFrame:
    """How many pairs of a distribution exceed each explanation's own value.

    ``scored``: pair_id, pattern_key, value (and start for local distributions).
    """
    on = ["pattern_key"] + (["start"] if "start" in dist.columns else [])
    above = scored.join(dist.withColumnRenamed("value", "other"), on).filter("other > value").groupBy(*KEYS).agg(F.sum("n_pairs").cast("double").alias("p"))
    return scored.select(*KEYS).join(above, KEYS, "left").select(*KEYS, F.coalesce("p", F.lit(0.0)).alias("value"))


def deviation(scored: DataFrame, dist: DataFrame, ddof: int = 0, include_zero: int | None = None) -> DataFrame:
    """(value - mean) / standard deviation of a distribution; null where it does not vary.

    ``include_zero``: the number of possible ends, of which those without instances count as 0.
    """
    on = ["pattern_key"] + (["start"] if "start" in dist.columns else [])
    n = F.sum("n_pairs") if include_zero is None else F.lit(include_zero)
    m = dist.groupBy(*on).agg(n.cast("double").alias("n"), F.sum(F.col("value") * F.col("n_pairs")).cast("double").alias("s"), F.sum(F.col("value") * F.col("value") * F.col("n_pairs")).cast("double").alias("q"))
    m = m.select(*on, (F.col("s") / F.col("n")).alias("mean"), F.sqrt((F.col("q") - F.col("s") * F.col("s") / F.col("n")) / F.nullif(F.col("n") - ddof, F.lit(0.0))).alias("sd"))
    return scored.join(m, on, "left").select(*KEYS, F.when(F.col("sd") > 0, (F.col("value") - F.col("mean")) / F.col("sd")).alias("value"))


def measure(name: str, kb: KnowledgeGraph, pairs: DataFrame, patterns: DataFrame, instances: DataFrame, agg: str = "count", sample: int | None = 100, seed: int = 42, kind: str | None = None, semantics: str = "simple", include_self: bool = False) -> DataFrame:
    """(pair_id, pattern_key, value) of a measure of the registry."""
    if name == "size":
        return size(patterns)
    if name == "walk":
        return walk(patterns)
    if name in AGGREGATES:
        return AGGREGATES[name](instances)
    scope, _, form = name.partition("_")
    own = AGGREGATES[agg](instances).join(pairs.select("pair_id", "start"), "pair_id")
    if scope == "local":
        asked = own.select("pattern_key", "start").distinct()  # a distribution for each pattern and start that the batch has
        dist = local_distribution(kb, asked, asked.select("start").distinct(), agg, semantics, include_self)
    else:
        dist = global_distribution(kb, patterns, agg, sample, seed, kind, False, semantics, include_self)
    return position(own, dist) if form == "position" else deviation(own, dist)
