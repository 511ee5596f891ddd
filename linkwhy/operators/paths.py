"""Paths between target pairs: forward, bidirectional, by activation, by label sequences first.

A partial path is a row (pair_id, start, end, nodes, sig, tip): the entities from its own
target on, and the steps ``>rel`` (along), ``<rel`` (against), ``~rel`` (undirected) taken.
Pairs come as a batch; one join with the steps extends all their partial paths by one edge.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.udfs import name_path
from ..plans.runs import RunStats, settle
from ..sources.kb import KnowledgeGraph

STRATEGIES = ("forward", "bidirectional", "activation", "label_first")


def mark(direction: Column) -> Column:
    return F.when(direction > 0, ">").when(direction < 0, "<").otherwise("~")


def seed(pairs: DataFrame, side: str = "start") -> DataFrame:
    return pairs.select("pair_id", "start", "end", F.array(side).alias("nodes"), F.array().cast("array<string>").alias("sig"), F.col(side).alias("tip"))


def expand(frontier: DataFrame, kb: KnowledgeGraph, semantics: str, side: str = "start", ways: set | None = None) -> DataFrame:
    """Extend partial paths of one side by one edge; a path that meets a target stops there.

    simple: no entity twice.  homomorphic: variables may coincide, never with a target.
    ``ways`` names the labels and directions that are worth a step.
    """
    return _extended(kb.reach(frontier, "tip", ways), semantics, side)


def _extended(out: DataFrame, semantics: str, side: str) -> DataFrame:
    out = out.filter(F.col("v") != F.col(side))
    if semantics == "simple":
        out = out.filter(~F.array_contains("nodes", F.col("v")))
    step = F.concat(mark(F.col("dir")), F.col("rel"))
    return out.select("pair_id", "start", "end", F.concat("nodes", F.array("v")).alias("nodes"), F.concat("sig", F.array(step)).alias("sig"), F.col("v").alias("tip"))


def _joined(fwd: DataFrame, bwd: DataFrame, semantics: str) -> DataFrame:
    """Whole paths from halves that meet at one entity; the backward half is turned round."""
    b = bwd.select("pair_id", "tip", F.col("nodes").alias("b_nodes"), F.col("sig").alias("b_sig"))
    out = fwd.join(b, ["pair_id", "tip"])
    rest = F.reverse(F.slice("b_nodes", 1, F.size("b_nodes") - 1))
    if semantics == "simple":
        out = out.filter(~F.arrays_overlap("nodes", rest))
    turn = F.transform(F.reverse("b_sig"), lambda s: F.concat(F.translate(F.substring(s, 1, 1), "<>", "><"), F.substring(s, 2, 1 << 20)))
    return out.select("pair_id", F.concat("nodes", rest).alias("nodes"), F.concat("sig", turn).alias("sig"))


def paths(kb: KnowledgeGraph, pairs: DataFrame, length: int = 4, strategy: str = "bidirectional", semantics: str = "simple", batch: int | None = None, stats: RunStats | None = None) -> DataFrame:
    """All start-end paths of at most ``length`` edges: (pair_id, nodes, sig), each once.

    All strategies give the same rows; they differ in the partial paths that they build.
    ``batch`` asks the activation strategy for the literal order, so many tips at a time.
    """
    if strategy not in STRATEGIES:
        raise ValueError(f"strategy must be one of {STRATEGIES}")
    pairs = pairs.select("pair_id", "start", "end").filter("start <> end")
    if strategy == "forward":
        return _forward(kb, pairs, length, semantics, stats)
    if strategy == "bidirectional":
        return _bidirectional(kb, pairs, length, semantics, stats)
    if strategy == "label_first":
        return _label_first(kb, pairs, length, semantics)
    if batch is None:
        return _wavefront(kb, pairs, length, semantics, stats)
    return _literal(kb, pairs, length, semantics, batch, stats)


def _count(stats: RunStats | None, name: str, df: DataFrame) -> None:
    if stats is not None:
        stats.add(name, df.count())


def _forward(kb, pairs, length, semantics, stats):
    """One side only; the last edge is looked up among those of the other target, as no other one ends a path."""
    at, found = seed(pairs), None
    for n in range(1, length + 1):
        if n < length:
            grown = settle(expand(at, kb, semantics))
        else:
            last = _last_steps(kb, pairs)
            grown = settle(_extended(at.join(last, (at["tip"] == last["u"]) & (at["end"] == last["v"])), semantics, "start"))
        _count(stats, "partial_paths", grown)
        hit = grown.filter("tip = end").select("pair_id", "nodes", "sig")
        found = hit if found is None else found.unionByName(hit)
        at = grown.filter("tip <> end")
    return found


def _last_steps(kb: KnowledgeGraph, pairs: DataFrame) -> DataFrame:
    """(u, rel, dir, v): the steps into the ends of the pairs, from the steps out of them turned round."""
    own = kb.reach(pairs.select(F.col("end").alias("tip")).distinct(), "tip")
    return own.select(F.col("v").alias("u"), "rel", (-F.col("dir")).cast("int").alias("dir"), F.col("tip").alias("v"))


def _useful(kb: KnowledgeGraph, pairs: DataFrame, length: int) -> dict[str, list[set | None]]:
    """For each side, by number of edges that may still follow: the labels and ways of a step that can lead to the other target.

    Judged by labels alone, so a step that is left out has no path behind it, whatever the semantics.
    """
    follow = kb.follow
    if follow is None:
        return {side: [None] * length for side in ("start", "end")}
    targets = pairs.select(F.explode(F.array(F.struct(F.lit("start").alias("side"), F.col("start").alias("tip")), F.struct(F.lit("end").alias("side"), F.col("end").alias("tip")))).alias("t")).select("t.*").distinct()
    out = {(r["side"], r["rel"], r["dir"]) for r in kb.reach(targets, "tip").select("side", "rel", "dir").distinct().collect()}
    useful = {}
    for side, other in (("start", "end"), ("end", "start")):
        last = {(rel, -way) for s, rel, way in out if s == other}
        levels = [last]
        for _ in range(length - 1):
            levels.append(last | {w for w, after in follow.items() if after & levels[-1]})
        useful[side] = levels
    useful["first"] = {side: {(rel, way) for s, rel, way in out if s == side} for side in ("start", "end")}
    return useful


def _inner(frontier: DataFrame) -> DataFrame:
    """Partial paths that end at no target."""
    return frontier.filter("tip <> start and tip <> end")


def _bidirectional(kb, pairs, length, semantics, stats):
    fwd, bwd = {0: seed(pairs)}, {0: seed(pairs, "end")}
    useful = _useful(kb, pairs, length)
    for side, depth, own in (("start", -(-length // 2), fwd), ("end", length // 2, bwd)):
        for d in range(1, depth + 1):
            own[d] = settle(expand(own[d - 1] if d == 1 else _inner(own[d - 1]), kb, semantics, side, useful[side][length - d]))
            _count(stats, "partial_paths", own[d])
    return _by_lengths(fwd, bwd, length, semantics)


def _by_lengths(fwd: dict, bwd: dict, length: int, semantics: str) -> DataFrame:
    """Each path length is made by one split of the depths that were reached, so each path once."""
    found = None
    for n in range(1, length + 1):
        a = next(a for a in sorted(range(n + 1), key=lambda a: abs(2 * a - n - 0.1)) if a in fwd and n - a in bwd)
        b = n - a
        left = fwd[a].filter("tip = end") if b == 0 else _inner(fwd[a]) if a else fwd[a]
        right = _inner(bwd[b]) if b and a else bwd[b].filter("tip = start") if b else bwd[0]
        part = _joined(left, right, semantics)
        found = part if found is None else found.unionByName(part)
    return found


def _wavefront(kb, pairs, length, semantics, stats):
    """Whole rounds; the side whose tips promise less work goes next.

    This is the intuition of waiting at hubs in a form that is one join for a whole batch of
    pairs.  The work of a side is the sum of the degrees of its tips, or where the labels say which steps can lead to the
    other target, the mean number of those.  The choice reads a few rows a round on the driver.
    """
    sides = {"start": {0: seed(pairs)}, "end": {0: seed(pairs, "end")}}
    useful = _useful(kb, pairs, length)

    def work(side: str) -> float:
        d = max(sides[side])
        tips = sides[side][d] if d == 0 else _inner(sides[side][d])
        ways = useful[side][length - d - 1]
        if ways is None:
            degrees = kb.degrees
            return tips.join(degrees, tips["tip"] == degrees["eid"]).agg(F.sum("degree")).first()[0] or 0
        fan = lambda after: sum(kb.fan_out[w] for w in after & ways if w in kb.fan_out)
        if d == 0:
            return tips.count() * fan(useful["first"][side])
        way = {">": 1, "<": -1, "~": 0}
        last = tips.groupBy(F.element_at("sig", -1).alias("s")).count().collect()
        return sum(r["count"] * fan(kb.follow.get((r["s"][1:], way[r["s"][0]]), set())) for r in last)

    cost = {side: work(side) for side in sides}
    while sum(max(s) for s in sides.values()) < length:
        side = min(sides, key=lambda s: (cost[s], s != "start"))
        d = max(sides[side])
        at = sides[side][d] if d == 0 else _inner(sides[side][d])
        sides[side][d + 1] = settle(expand(at, kb, semantics, side, useful[side][length - d - 1]))
        _count(stats, "partial_paths", sides[side][d + 1])
        if sum(max(s) for s in sides.values()) < length:
            cost[side] = work(side)
    return _by_lengths(sides["start"], sides["end"], length, semantics)


def _literal(kb, pairs, length, semantics, batch, stats):
    """Prioritised order: always extend the partial paths of the most active tips.

    A target starts with activation 1 / degree; an extended tip hands its activation, divided
    by the neighbour's degree, to each neighbour that is no target, and drops to zero.  The
    rounds end when every partial path has been extended whose depth the other side may
    need: depth reached by start and by end, all shallower ones done, add up to ``length``.
    """
    degrees = kb.degrees
    half = {"start": -(-length // 2), "end": length // 2}
    done = {s: seed(pairs, s).withColumn("depth", F.lit(0)) for s in half}
    todo = {s: done[s] for s in half}
    active = None
    for s in half:
        own = pairs.join(degrees, pairs[s] == degrees["eid"]).select("pair_id", F.lit(s).alias("side"), F.col(s).alias("tip"), (1 / F.col("degree")).alias("activation"))
        active = own if active is None else active.unionByName(own)
    active, rounds = settle(active), 0
    while True:
        waiting = None
        for s in half:
            tips = todo[s].filter(F.col("depth") < half[s]).select("pair_id", F.lit(s).alias("side"), "tip").distinct()
            waiting = tips if waiting is None else waiting.unionByName(tips)
        chosen = waiting.join(active, ["pair_id", "side", "tip"], "left").fillna(0.0, ["activation"])
        chosen = settle(chosen.orderBy(F.desc("activation"), F.desc("side"), "tip").limit(batch))
        if chosen.isEmpty():
            break
        spread = None
        for s in half:
            mine = chosen.filter(F.col("side") == s).select("pair_id", "tip", "activation")
            ready = todo[s].filter(F.col("depth") < half[s]).join(mine.select("pair_id", "tip"), ["pair_id", "tip"], "left_semi")
            grown = settle(expand(ready.select("pair_id", "start", "end", "nodes", "sig", "tip"), kb, semantics, s).withColumn("depth", F.size("sig")))
            _count(stats, "partial_paths", grown)
            todo[s] = settle(todo[s].join(mine.select("pair_id", "tip"), ["pair_id", "tip"], "left_anti").unionByName(_inner(grown)).unionByName(
                todo[s].join(mine.select("pair_id", "tip"), ["pair_id", "tip"], "left_semi").filter(F.col("depth") >= half[s])))
            done[s] = done[s].unionByName(grown)
            to = mine.join(kb.steps, mine["tip"] == kb.steps["u"]).join(pairs.select("pair_id", "start", "end"), "pair_id").filter("v <> start and v <> end")
            to = to.join(degrees, to["v"] == degrees["eid"]).select("pair_id", F.lit(s).alias("side"), F.col("v").alias("tip"), (F.col("activation") / F.col("degree")).alias("activation"))
            spread = to if spread is None else spread.unionByName(to)
        rounds += 1
        if rounds % 16 == 0:  # the plan stays short, however many rounds
            done = {s: settle(done[s]) for s in half}
        stats and stats.add("activation_rounds", 1)
        reset = active.join(chosen.select("pair_id", "side", "tip"), ["pair_id", "side", "tip"], "left_anti")
        active = settle(reset.unionByName(spread).groupBy("pair_id", "side", "tip").agg(F.sum("activation").alias("activation")))
    reached = {s: {d: done[s].filter(F.col("depth") == d).drop("depth") for d in range(half[s] + 1)} for s in half}
    return _by_lengths(reached["start"], reached["end"], length, semantics)


def _label_first(kb, pairs, length, semantics):
    """Label sequences first: those that the kinds of entities allow, then their instances."""
    steps = kb.steps
    kinds = kb.entities.select("eid", "kind")
    typed = steps.join(kinds.select(F.col("eid").alias("u"), F.col("kind").alias("ku")), "u").join(kinds.select(F.col("eid").alias("v"), F.col("kind").alias("kv")), "v")
    schema = settle(typed.select("ku", "rel", "dir", "kv").distinct())
    ends = pairs.join(kinds.select(F.col("eid").alias("start"), F.col("kind").alias("ks")), "start").join(kinds.select(F.col("eid").alias("end"), F.col("kind").alias("ke")), "end")
    found = None
    at = ends.select("ks", "ke").distinct().select("ks", "ke", F.col("ks").alias("tip"), F.array().cast("array<struct<rel:string,dir:int>>").alias("plan"))
    for n in range(1, length + 1):
        at = settle(at.join(schema, at["tip"] == schema["ku"]).select("ks", "ke", F.col("kv").alias("tip"), F.concat("plan", F.array(F.struct("rel", "dir"))).alias("plan")))
        rows = ends.join(at.filter("tip = ke").select("ks", "ke", "plan"), ["ks", "ke"]).select("pair_id", "start", "end", "plan", F.array("start").alias("nodes"), F.col("start").alias("tip"))
        for i in range(n):
            step = F.element_at("plan", i + 1)
            joined = rows.withColumns({"u": F.col("tip"), "rel": step["rel"], "dir": step["dir"]}).join(steps, ["u", "rel", "dir"])
            stop = F.col("v") == F.col("end") if i + 1 == n else (F.col("v") != F.col("end"))
            joined = joined.filter(stop & (F.col("v") != F.col("start")))
            if semantics == "simple":
                joined = joined.filter(~F.array_contains("nodes", F.col("v")))
            rows = joined.select("pair_id", "start", "end", "plan", F.concat("nodes", F.array("v")).alias("nodes"), F.col("v").alias("tip"))
        part = rows.select("pair_id", "nodes", F.transform("plan", lambda s: F.concat(mark(s["dir"]), s["rel"])).alias("sig"))
        found = part if found is None else found.unionByName(part)
    return found


def path_patterns(found: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Group path instances to patterns: (patterns, instances); entities become variables."""
    kinds = found.select("sig").distinct().withColumn("p", name_path("sig"))
    rows = found.join(kinds, "sig")
    raw = F.slice("nodes", 2, F.size("nodes") - 2)
    bound = F.transform(F.col("p.perm"), lambda i: F.element_at("raw", i))
    instances = rows.withColumn("raw", raw).select("pair_id", F.col("p.pattern_key").alias("pattern_key"), bound.alias("binding")).distinct()
    shapes = found.select("pair_id", "sig").distinct().join(kinds, "sig")
    patterns = shapes.select("pair_id", "p.pattern_key", "p.n_nodes", "p.n_edges", "p.edges", F.lit(1).alias("round")).dropDuplicates(["pair_id", "pattern_key"])
    return patterns, instances
