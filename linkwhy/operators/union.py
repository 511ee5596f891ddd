"""Combining path explanations into all minimal explanations, round by round."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.local import Union
from ..functions.udfs import edges_of, name_merge
from ..plans.runs import RunStats, settle

PATTERN = ["pair_id", "pattern_key", "n_nodes", "n_edges", "edges", "round"]
MOST_ROUNDS = 64


@dataclass
class Explanations:
    """patterns, instances and lineage of a batch of pairs, and the work it took."""

    patterns: DataFrame
    instances: DataFrame
    lineage: DataFrame
    stats: RunStats

    def write(self, path: str, run_id: str) -> None:
        for name in ("patterns", "instances", "lineage"):
            getattr(self, name).withColumn("run_id", F.lit(run_id)).write.mode("append").partitionBy("run_id").parquet(f"{path}/{name}")


def merge_instances(left: DataFrame, right: DataFrame, limit: int, semantics: str, allowed: DataFrame | None = None, merge_plan: str = "instance_first") -> DataFrame:
    """Merge explanations of one pair that bind a common entity.

    ``left`` and ``right``: (pair_id, pattern_key, binding).  Returns (pair_id, left_key,
    path_key, pattern_key, n_nodes, n_edges, edges, binding); never an empty merge.

    instance_first joins the bindings on as many shared entities as a merge within ``limit`` must have (with
    coinciding variables: on one); their overlap is the map between variables (any non-empty one-to-one part of it).
    pattern_first lists the maps between patterns and then joins instances on the matched
    places; both give the same rows.
    """
    a = left.select("pair_id", F.col("pattern_key").alias("left_key"), F.col("binding").alias("lb")).filter(F.size("lb") > 0)
    b = right.select("pair_id", F.col("pattern_key").alias("path_key"), F.col("binding").alias("rb")).filter(F.size("rb") > 0)
    if merge_plan == "pattern_first":
        met = _pattern_first(a, b, limit, allowed)
    else:
        if semantics == "simple":
            a, b = _shared(a, "lb", "m1", "m2", limit), _shared(b, "rb", "m2", "m1", limit)
            met = a.join(b, ["pair_id", "m1", "m2", "x"]).drop("m1", "m2", "x")
        else:
            met = a.withColumn("x", F.explode(F.array_distinct("lb"))).join(b.withColumn("x", F.explode(F.array_distinct("rb"))), ["pair_id", "x"]).drop("x")
        if allowed is not None:
            met = met.join(allowed, ["pair_id", "left_key", "path_key"], "left_semi")
        met = met.distinct()
        if semantics == "simple":
            met = met.withColumn("match", F.transform("lb", lambda x: F.array_position("rb", x).cast("int")))
        else:
            met = met.withColumn("match", F.explode(_part_maps(F.col("lb"), F.col("rb"))))
    free = F.filter(F.transform("rb", lambda x, i: F.when(~F.array_contains("match", i + 1), x)), lambda x: x.isNotNull())
    if semantics == "simple":  # entities that are not matched must differ
        met = met.filter(F.size(F.array_intersect("lb", "rb")) == F.size(F.filter("match", lambda j: j > 0)))
    met = met.withColumn("raw", F.concat("lb", free)).filter(F.size("raw") + 2 <= limit)
    names = met.select("left_key", "path_key", "match").distinct().withColumn("p", name_merge("left_key", "path_key", "match"))
    out = met.join(names, ["left_key", "path_key", "match"])
    return out.select(
        "pair_id", "left_key", "path_key", F.col("p.pattern_key").alias("pattern_key"), "p.n_nodes", "p.n_edges", "p.edges",
        F.transform(F.col("p.perm"), lambda i: F.element_at("raw", i)).alias("binding"),
    )


def _shared(rows: DataFrame, binding: str, own: str, other: str, limit: int) -> DataFrame:
    """A row for each size of the other binding and each set ``x`` of entities that may be the least that both must share."""
    size = F.size(binding)
    rows = rows.withColumn(own, size).withColumn(other, F.explode(F.sequence(F.lit(1), F.lit(max(1, limit - 2)))))
    need = F.greatest(F.lit(1), size + F.col(other) + F.lit(2 - limit))
    rows = rows.withColumn("need", need).filter(F.col("need") <= F.least(size, F.col(other)))
    some = F.aggregate(
        F.sort_array(binding),
        F.array(F.array().cast("array<long>")),
        lambda acc, e: F.concat(acc, F.transform(F.filter(acc, lambda s: F.size(s) < F.col("need")), lambda s: F.concat(s, F.array(e)))),
    )
    return rows.withColumn("x", F.explode(F.filter(some, lambda s: F.size(s) == F.col("need")))).drop("need")


def _part_maps(lb, rb):
    """All non-empty one-to-one parts of the relation "binds the same entity", as match arrays."""
    maps = F.array(F.transform(lb, lambda _: F.lit(0)))

    def grow(acc, i):
        each = F.transform(
            acc,
            lambda m: F.concat(
                F.array(m),
                F.transform(
                    F.filter(F.sequence(F.lit(1), F.size(rb)), lambda j: (F.element_at(rb, j) == F.element_at(lb, i)) & ~F.array_contains(m, j)),
                    lambda j: F.transform(m, lambda x, k: F.when(k == i - 1, j).otherwise(x)),
                ),
            ),
        )
        return F.flatten(each)

    grown = F.aggregate(F.sequence(F.lit(1), F.size(lb)), maps, grow)
    return F.filter(grown, lambda m: F.exists(m, lambda x: x > 0))


def _pattern_first(a: DataFrame, b: DataFrame, limit: int, allowed: DataFrame | None) -> DataFrame:
    """Pattern pairs of each target pair, their maps, then instances that agree on the matched places."""
    keys = a.select("pair_id", "left_key", F.size("lb").alias("m1")).distinct().join(b.select("pair_id", "path_key", F.size("rb").alias("m2")).distinct(), "pair_id")
    if allowed is not None:
        keys = keys.join(allowed, ["pair_id", "left_key", "path_key"], "left_semi")
    maps = F.array(F.array().cast("array<int>"))

    def longer(acc, i):
        return F.flatten(F.transform(acc, lambda m: F.transform(F.filter(F.sequence(F.lit(0), F.col("m2")), lambda j: (j == 0) | ~F.array_contains(m, j)), lambda j: F.concat(m, F.array(j)))))

    keys = keys.withColumn("match", F.explode(F.aggregate(F.sequence(F.lit(1), F.col("m1")), maps, longer)))
    used = F.size(F.filter("match", lambda j: j > 0))
    keys = keys.filter((used > 0) & (F.col("m1") + F.col("m2") - used + 2 <= limit)).drop("m1", "m2")
    met = keys.join(a, ["pair_id", "left_key"])
    at_left = F.filter(F.transform("match", lambda j, i: F.when(j > 0, F.element_at("lb", i + 1))), lambda x: x.isNotNull())
    met = met.withColumn("agree", at_left)
    other = keys.join(b, ["pair_id", "path_key"]).withColumn("agree", F.transform(F.filter("match", lambda j: j > 0), lambda j: F.element_at("rb", j)))
    return met.join(other.select("pair_id", "left_key", "path_key", "match", "agree", "rb"), ["pair_id", "left_key", "path_key", "match", "agree"]).drop("agree")


def allowed_pairs(lineage: DataFrame) -> DataFrame:
    """(pair_id, left_key, path_key): merges that some sibling licenses.

    An explanation needs to meet a path only if an explanation of the same round, itself
    perhaps, was made from one of its own parents with that path.
    """
    own = lineage.select("pair_id", "parent_key", F.col("child_key").alias("left_key"))
    return own.join(lineage.select("pair_id", "parent_key", "path_key"), ["pair_id", "parent_key"]).select("pair_id", "left_key", "path_key").distinct()


def _entities(binding: str):
    return F.array_sort(F.array_distinct(binding))


def _places(binding, e):
    return F.transform(binding, lambda x: F.array_position(e, x).cast("int"))


def _parts(sets: DataFrame, e: str, sizes: list[int], most: int) -> DataFrame:
    """A row for each part of the sets ``e`` of at most ``most`` that has one of ``sizes``: its places in the set, and itself."""
    lists = lambda k: F.array(*(F.array(*map(F.lit, some)) for m in sizes if m for some in combinations(range(1, k + 1), m)))
    some = F.when(F.size(e) == 0, F.array(F.array().cast("array<int>")))
    for k in range(1, most + 1):
        some = some.when(F.size(e) == k, lists(k).cast("array<array<int>>"))
    return sets.withColumn("places", F.explode(some)).withColumn("part", F.transform("places", lambda i: F.element_at(e, i)))


def entity_classes(instances: DataFrame, limit: int) -> DataFrame:
    """(pair_id, e, model): each set of entities that explanations within ``limit`` may bind, sorted, and the set that stands for it.

    Sets of one class have the same path patterns at the same places, and every merge that ends in a set is made of paths inside it.
    So what is found for ``model`` holds for all of them, place by place.  A class is told by its whole list of paths, not by a digest.
    """
    own = instances.select("pair_id", "pattern_key", "binding", _entities("binding").alias("e"))
    own = own.withColumn("path", F.struct("pattern_key", _places("binding", F.col("e")).alias("at")))
    own = settle(own.groupBy("pair_id", "e").agg(F.array_sort(F.collect_set("path")).alias("paths")))
    sizes = sorted(r[0] for r in own.select(F.size("e")).distinct().collect())
    sets = own.select("pair_id", "e")
    base = new = sets.filter(F.size("e").between(2, limit - 3))
    while any(2 <= k <= limit - 3 for k in sizes):
        left, right = new.withColumn("x", F.explode("e")), base.select("pair_id", F.col("e").alias("f")).withColumn("x", F.explode("f"))
        grown = left.join(right, ["pair_id", "x"]).select("pair_id", F.array_sort(F.array_union("e", "f")).alias("e")).filter(F.size("e") <= limit - 2)
        grown = settle(grown.distinct().join(sets, ["pair_id", "e"], "left_anti"))
        if grown.isEmpty():
            break
        sets, new = sets.unionByName(grown), grown.filter(F.size("e") <= limit - 3)
    inside = _parts(sets, "e", sizes, max([limit - 2, *sizes])).join(own.withColumnRenamed("e", "part"), ["pair_id", "part"])
    kinds = settle(inside.groupBy("pair_id", "e").agg(F.array_sort(F.collect_list(F.struct("places", "paths"))).alias("kind")))
    models = kinds.groupBy("pair_id", "kind").agg(F.min("e").alias("model"))
    return settle(kinds.join(models, ["pair_id", "kind"]).select("pair_id", "e", "model"))


def at_models(instances: DataFrame, classes: DataFrame) -> DataFrame:
    """The path instances inside the models of ``entity_classes``."""
    models = classes.select("pair_id", "model").distinct()
    sizes = [r[0] for r in instances.select(F.size(_entities("binding"))).distinct().collect()]
    most = models.agg(F.max(F.size("model"))).first()[0] or 0
    parts = _parts(models, "model", sizes, most).select("pair_id", F.col("part").alias("e")).distinct()
    return instances.withColumn("e", _entities("binding")).join(parts, ["pair_id", "e"], "left_semi").drop("e")


def at_all(instances: DataFrame, classes: DataFrame) -> DataFrame:
    """Instances of models carried over to every set of their class."""
    own = instances.withColumn("model", _entities("binding")).withColumn("at", _places("binding", F.col("model")))
    met = own.join(classes, ["pair_id", "model"])
    return met.withColumn("binding", F.transform("at", lambda i: F.element_at("e", i))).select("pair_id", "pattern_key", "binding")


def combine(patterns: DataFrame, instances: DataFrame, limit: int = 5, strategy: str = "lineage", semantics: str = "simple", merge_plan: str = "instance_first", stats: RunStats | None = None, frontier=None, classes: DataFrame | None = None) -> Explanations:
    """All minimal explanations of at most ``limit`` nodes from the path explanations.

    exhaustive: the newest explanations meet all paths in every round.  lineage: from the
    second round on, only merges that ``allowed_pairs`` names.  ``frontier`` may cut the
    explanations that are extended further (top-k pruning): it gets the newest patterns with
    their instances and returns the (pair_id, pattern_key) to extend.  A round is written to the
    shared folder; its column ``round`` is the least number of paths that cover a pattern.
    The rounds see one set of entities of each of ``entity_classes``; the others follow at the end.
    """
    if strategy not in ("exhaustive", "lineage"):
        raise ValueError("strategy must be exhaustive or lineage")
    stats = stats or RunStats()
    spark = patterns.sparkSession
    patterns = settle(patterns.select(*PATTERN))
    classes = entity_classes(instances, limit) if classes is None else classes
    base = instances = settle(at_models(instances, classes))
    known, new, new_instances = patterns, patterns, instances
    lineage = spark.createDataFrame([], "pair_id long, child_key string, parent_key string, path_key string, round int")
    allowed = None
    for r in range(2, MOST_ROUNDS):
        left = new_instances
        if frontier is not None:
            left = left.join(frontier(new, at_all(new_instances, classes)), ["pair_id", "pattern_key"], "left_semi")
        made = settle(merge_instances(left, base, limit, semantics, allowed, merge_plan))
        stats.add("merged_rows", made.count())
        fresh = made.join(known.select("pair_id", "pattern_key"), ["pair_id", "pattern_key"], "left_anti")
        new = settle(fresh.withColumn("round", F.lit(r)).select(*PATTERN).dropDuplicates(["pair_id", "pattern_key"]))
        n = new.count()
        if n == 0:
            break
        stats.add(f"round_{r}_patterns", n)
        born = settle(fresh.select("pair_id", F.col("pattern_key").alias("child_key"), F.col("left_key").alias("parent_key"), "path_key", F.lit(r).alias("round")).distinct())
        new_instances = settle(fresh.select("pair_id", "pattern_key", "binding").distinct())
        tried = born.count()
        stats.add("merges_kept", tried)
        lineage = lineage.unionByName(born)
        known = known.unionByName(new)
        instances = instances.unionByName(new_instances)
        if strategy == "lineage":
            allowed = settle(allowed_pairs(born))
    else:
        raise RuntimeError("the union did not end")
    return Explanations(known, at_all(instances, classes), lineage, stats)


def combine_local(instances: DataFrame, limit: int = 5, strategy: str = "lineage", semantics: str = "simple", top: tuple[str, int] | None = None, stats: RunStats | None = None) -> Explanations:
    """As ``combine``, with all rounds of a pair in one task: one shuffle by pair instead of one a round.

    For pairs whose instances fit a task; ``plans.engine`` checks that first.  ``top``:
    (measure, k) extends only explanations among the best k, as ``rank.frontier_topk``.
    """
    stats = stats or RunStats()

    def run(key, frame):
        import pandas as pd

        paths: dict[str, set] = {}
        for k, b in zip(frame["pattern_key"], frame["binding"], strict=True):
            paths.setdefault(k, set()).add(tuple(int(x) for x in b))
        done = Union(paths, limit, strategy, semantics, top).run()
        rows = []
        for k, bindings in done.instances.items():
            rows += [(key[0], "instance", k, done.round[k], list(b), None, None, 0) for b in sorted(bindings)]
        rows += [(key[0], "lineage", child, r, None, parent, path, 0) for child, parent, path, r in done.lineage]
        rows += [(key[0], name, None, 0, None, None, None, n) for name, n in done.work.items()]
        return pd.DataFrame(rows, columns=["pair_id", "kind", "pattern_key", "round", "binding", "parent_key", "path_key", "n"])

    schema = "pair_id long, kind string, pattern_key string, round int, binding array<long>, parent_key string, path_key string, n long"
    out = settle(instances.groupBy("pair_id").applyInPandas(run, schema))
    own = out.filter("kind = 'instance'")
    kinds = own.groupBy("pair_id", "pattern_key", "round").agg(F.first("binding").alias("b"))
    shape = kinds.select("pattern_key").distinct().withColumn("edges", edges_of("pattern_key"))
    patterns = kinds.join(shape, "pattern_key").select("pair_id", "pattern_key", (F.size("b") + 2).alias("n_nodes"), F.size("edges").alias("n_edges"), "edges", "round")
    lineage = out.filter("kind = 'lineage'").select("pair_id", F.col("pattern_key").alias("child_key"), "parent_key", "path_key", "round")
    for row in out.filter("n > 0").groupBy("kind").agg(F.sum("n").alias("n")).collect():
        stats.add(row["kind"], row["n"])
    return Explanations(patterns, own.select("pair_id", "pattern_key", "binding"), lineage, stats)
