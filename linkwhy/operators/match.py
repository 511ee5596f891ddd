"""Instances of given patterns: for a pair, for a start with any end, or for any two ends.

Patterns are data: each has a plan of steps (from, label, direction, to), and one join with
the graph's steps carries all patterns, and all starts, one edge further.  So patterns
that begin alike share their rows and the read of the graph, and the number of jobs does not grow
with the number of patterns.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import pattern as P
from ..functions.udfs import match_steps
from ..plans.runs import RunStats, settle
from ..sources.kb import MOST_WAYS, KnowledgeGraph

SEMANTICS = ("simple", "homomorphic", "sql")


def match(kb: KnowledgeGraph, patterns: DataFrame, bind: str = "pair", at: DataFrame | None = None, semantics: str = "simple", slices: tuple[int, int, int] | None = None, stats: RunStats | None = None, among: DataFrame | None = None) -> DataFrame:
    """(…keys of ``at``, pattern_key, start, end, binding), each instance once.

    ``patterns`` has pattern_key, and may have pair_id or start: then a pattern is matched for
    its own pairs or starts.  bind pair: ``at`` holds start and end; start: it holds start;
    none: every entity is a start.  simple: all entities differ; homomorphic: variables may
    coincide but avoid the targets; sql: no condition, as a plain join has it.
    ``slices`` (n, from, to) keeps ends whose hash modulo n is in [from, to), ``among`` (eid) those that it names.

    The plans of the patterns form a tree: what begins alike is joined once for a pair or start, and each
    depth of the tree is one join; every third is written to the shared folder.  ``stats`` counts the rows of all depths.
    """
    if semantics not in SEMANTICS:
        raise ValueError(f"semantics must be one of {SEMANTICS}")
    bound = (0, 1) if bind == "pair" else (0,)
    keys = [c for c in ("pair_id",) if at is not None and c in at.columns]
    ends = ["end"] if bind == "pair" else []
    on = [k for k in ("pair_id", "start") if at is not None and k in at.columns and k in patterns.columns]
    shapes = patterns.select("pattern_key").distinct().withColumn("plan", match_steps(bound, kb.fan_out)("pattern_key"))
    asked = settle(patterns.select(*on, "pattern_key").distinct().join(shapes, "pattern_key"))
    nodes = F.array_max(F.transform("plan", lambda s: F.greatest(s["origin"], s["target"]))) + 1
    text = F.transform("plan", lambda s: F.concat_ws(" ", s["origin"].cast("string"), s["dir"].cast("string"), s["target"].cast("string"), s["rel"]))
    asked = asked.withColumns({"n": nodes, "texts": text})
    deepest, widest = asked.agg(F.max(F.size("plan")), F.max("n")).first()
    if (deepest or 0) > MOST_EDGES:
        raise ValueError(f"a pattern has more than {MOST_EDGES} edges")
    deepest, widest = deepest or 0, widest or 2
    head = lambda n: F.array_join(F.slice("texts", F.lit(1), n), "|")
    branches = asked.select(*on, "texts", F.posexplode("plan").alias("depth", "step"))
    branches = branches.select(*on, "depth", head(F.col("depth")).alias("prefix"), head(F.col("depth") + 1).alias("after"), "step.*").distinct()
    leaves = asked.select(*on, "pattern_key", "n", F.size("plan").alias("depth"), head(F.size("plan")).alias("prefix"))

    if on:
        rows = at.select(*keys, "start", *ends).join(asked.select(*on).distinct(), on)
    elif ends:  # plans may begin at either target
        rows = at.select(*keys, "start", *ends)
    else:  # only starts that have an edge for the first step of a pattern
        first = branches.filter("depth = 0").select("rel", "dir").distinct()
        rows = kb.steps.join(first, ["rel", "dir"]).select(F.col("u").alias("start")).distinct()
        rows = rows if at is None else at.select(*keys, "start").join(rows, "start")
    end = F.col("end") if ends else F.lit(None).cast("long")
    rows = rows.select(*{*keys, "start"}, F.lit("").alias("prefix"), F.concat(F.array("start", end), F.array_repeat(F.lit(None).cast("long"), widest - 2)).alias("at"))
    link = [*dict.fromkeys([*on, "prefix"])]
    steps, done = kb.steps.select("u", "rel", "dir", "v"), None
    if among is not None:
        steps = steps.join(among.select(F.col("eid").alias("v"), F.lit(True).alias("may_end")), "v", "left")
        uses = F.when(F.col("may_end"), F.array(F.lit(False), F.lit(True))).otherwise(F.array(F.lit(False)))
        steps = settle(steps.select("u", "rel", "dir", "v", F.explode(uses).alias("to_end")))
    for i in range(deepest):
        ready = rows.join(branches.filter(F.col("depth") == i).drop("depth"), link).withColumn("u", F.try_element_at("at", F.col("origin") + 1))
        if among is None:  # met on the first node alone, so that a pinned graph stays where it is
            ways = {(r["rel"], r["dir"]) for r in branches.filter(F.col("depth") == i).select("rel", "dir").distinct().limit(MOST_WAYS + 1).collect()}
            asks = ready.select(*ready.columns, F.array("rel").alias("by"), F.array("dir").alias("way")).drop("rel", "dir").withColumnRenamed("u", "tip")
            out = kb.reach(asks, "tip", ways if len(ways) <= MOST_WAYS else None)
            out = out.filter(F.array_contains("by", F.col("rel")) & F.array_contains("way", F.col("dir")))
        else:
            out = ready.withColumn("to_end", F.col("target") == 1).join(steps, ["u", "rel", "dir", "to_end"])
        held = F.try_element_at("at", F.col("target") + 1)
        ok = (held == F.col("v")) | (held.isNull() & _free(semantics))
        if slices:
            n, a, b = slices
            part = F.pmod(F.xxhash64("v"), F.lit(n))
            ok = ok & ((F.col("target") != 1) | (part >= a) & (part < b))
        placed = F.transform("at", lambda x, k: F.when(k == F.col("target"), F.col("v")).otherwise(x))
        rows = out.filter(ok).select(*{*keys, "start"}, F.col("after").alias("prefix"), placed.alias("at"))
        if stats is not None or (i % 3 == 2 and i + 1 < deepest):
            rows = settle(rows)  # between them, equal subplans share their exchanges
        if stats is not None:
            stats.add("match_rows", rows.count())
        ripe = rows.join(leaves.filter(F.col("depth") == i + 1).drop("depth"), link)
        done = ripe if done is None else done.unionByName(ripe)
    if done is None:
        done = rows.join(leaves, link).filter("false")
    whole = done.select(*keys, "pattern_key", "start", F.try_element_at("at", F.lit(2)).alias("end"), F.slice("at", F.lit(3), F.col("n") - 2).alias("binding"))
    if semantics == "homomorphic":
        whole = whole.filter(~F.array_contains("binding", F.col("end")))
    return whole


MOST_EDGES = 64


def _free(semantics: str):
    """May a so far unbound node take entity v?"""
    seen = F.coalesce(F.array_contains("at", F.col("v")), F.lit(False))
    if semantics == "simple":
        return ~seen
    if semantics == "homomorphic":
        return (F.col("v") != F.try_element_at("at", F.lit(1))) & ~F.coalesce(F.try_element_at("at", F.lit(2)) == F.col("v"), F.lit(False))
    return F.lit(True)


def position_sql(pattern_key: str, start: int, above: int, limit: int | None = None, view: str = "kb_edges", include_start: bool = True) -> str:
    """One query over a relation (eid1, eid2, rel): the ends whose number of instances from ``start`` exceeds ``above``.

    The number of its rows is the local position of a pair whose own count is ``above``; with
    ``limit`` it stops once the position cannot be among the best.
    """
    edges = sorted(P.parse_key(pattern_key))
    column: dict[int, list[str]] = {}
    where = []
    for i, (a, rel, b, directed) in enumerate(edges):
        if not directed:
            raise ValueError("undirected labels need both orders; use the DataFrame form")
        column.setdefault(a, []).append(f"t{i}.eid1")
        column.setdefault(b, []).append(f"t{i}.eid2")
        where.append(f"t{i}.rel = '{rel.replace(chr(39), chr(39) * 2)}'")
    where += [f"{c[0]} = {other}" for c in column.values() for other in c[1:]]
    where.append(f"{column[0][0]} = {int(start)}")
    end = column[1][0]
    if not include_start:
        where.append(f"{end} <> {int(start)}")
    tail = f" LIMIT {int(limit)}" if limit is not None else ""
    return f"SELECT {end} AS end_id, count(*) AS n FROM {', '.join(f'{view} t{i}' for i in range(len(edges)))} WHERE {' AND '.join(where)} GROUP BY {end} HAVING count(*) > {int(above)}{tail}"
