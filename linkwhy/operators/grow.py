"""Baseline: enumerate explanations by growing general patterns edge by edge."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.udfs import is_minimal, name_growth
from ..plans.runs import RunStats, settle
from ..sources.kb import KnowledgeGraph
from .union import PATTERN, Explanations


def grow_enumerate(kb: KnowledgeGraph, pairs: DataFrame, limit: int, max_rounds: int | None = None, semantics: str = "simple", stats: RunStats | None = None) -> Explanations:
    """All minimal explanations, by way of every pattern that has instances.

    From the lone start node a pattern grows by one edge at a time, to a new node, to the
    end or between nodes that it has.  Patterns that are not minimal must be grown on,
    which is what makes this slow; minimal ones are picked at the end.
    """
    stats = stats or RunStats()
    steps = kb.steps
    lone = pairs.filter("start <> end").select("pair_id", "start", "end", F.lit("").alias("pattern_key"), F.array().cast("array<long>").alias("binding"), F.lit(False).alias("ended"))
    rows, known, found, instances = settle(lone), None, None, None
    r = 0
    while max_rounds is None or r < max_rounds:
        r += 1
        # positions: 0 start, 1 end (once reached), 2.. variables
        nodes = F.concat(F.array(F.struct(F.lit(0).alias("a"), F.col("start").alias("u"))), F.when(F.col("ended"), F.array(F.struct(F.lit(1).alias("a"), F.col("end").alias("u")))).otherwise(F.array().cast("array<struct<a:int,u:bigint>>")), F.transform("binding", lambda x, i: F.struct((i + 2).cast("int").alias("a"), x.alias("u"))))
        at = rows.withColumn("x", F.explode(nodes)).select("*", "x.a", "x.u").drop("x")
        out = at.join(steps, "u")
        place = F.array_position("binding", F.col("v")).cast("int")
        b = F.when(F.col("v") == F.col("end"), 1).when(F.col("v") == F.col("start"), 0).when(place > 0, place + 1).otherwise(F.size("binding") + 2)
        if semantics != "simple":
            b = F.explode(F.when(F.col("v") == F.col("end"), F.array(F.lit(1))).when(F.col("v") == F.col("start"), F.array(F.lit(0))).otherwise(
                F.concat(F.filter(F.transform("binding", lambda x, i: F.when(x == F.col("v"), (i + 2).cast("int"))), lambda i: i.isNotNull()), F.array((F.size("binding") + 2).cast("int")))))
        out = out.withColumn("b", b).filter("a <> b")
        fresh = F.col("b") == F.size("binding") + 2
        out = out.withColumns({"binding": F.when(fresh, F.concat("binding", F.array("v"))).otherwise(F.col("binding")), "ended": F.col("ended") | (F.col("b") == 1)})
        out = out.filter(F.size("binding") + 2 <= limit)
        out = out.withColumns({"p": F.when(F.col("dir") < 0, F.col("b")).otherwise(F.col("a")), "q": F.when(F.col("dir") < 0, F.col("a")).otherwise(F.col("b")), "directed": F.col("dir") != 0, "n": F.size("binding") + 2})
        out = settle(out.select("pair_id", "start", "end", F.col("pattern_key").alias("old"), "n", "p", "rel", "q", "directed", "binding", "ended"))
        stats.add("growth_rows", out.count())
        names = out.select("old", "n", "p", "rel", "q", "directed").distinct().withColumn("new", name_growth("old", "n", "p", "rel", "q", "directed"))
        out = out.join(names, ["old", "n", "p", "rel", "q", "directed"]).filter(F.col("new.pattern_key") != F.col("old"))
        grown = out.select("pair_id", "start", "end", F.col("new.pattern_key").alias("pattern_key"), F.transform(F.col("new.perm"), lambda i: F.element_at("binding", i)).alias("binding"), "ended", F.col("new.n_nodes").alias("n_nodes"), F.col("new.n_edges").alias("n_edges"), F.col("new.edges").alias("edges"))
        if known is not None:
            grown = grown.join(known, ["pair_id", "pattern_key", "ended"], "left_anti")
        grown = settle(grown.dropDuplicates(["pair_id", "pattern_key", "binding", "ended"]))
        n = grown.select("pair_id", "pattern_key", "ended").distinct()
        count = n.count()
        stats.add("patterns_expanded", count)
        if count == 0:
            break
        known = settle(n if known is None else known.unionByName(n))
        whole = grown.filter("ended").filter(is_minimal("pattern_key"))
        kinds = whole.withColumn("round", F.lit(r)).select(*PATTERN).dropDuplicates(["pair_id", "pattern_key"])
        own = whole.select("pair_id", "pattern_key", "binding")
        found = kinds if found is None else found.unionByName(kinds)
        instances = own if instances is None else instances.unionByName(own)
        rows = grown.select("pair_id", "start", "end", "pattern_key", "binding", "ended")
    spark = pairs.sparkSession
    lineage = spark.createDataFrame([], "pair_id long, child_key string, parent_key string, path_key string, round int")
    if found is None:
        found = spark.createDataFrame([], "pair_id long, pattern_key string, n_nodes int, n_edges int, edges array<struct<a:int,rel:string,b:int,directed:boolean>>, round int")
        instances = spark.createDataFrame([], "pair_id long, pattern_key string, binding array<long>")
    return Explanations(settle(found), settle(instances), lineage, stats)
