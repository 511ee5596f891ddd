"""One small test for each finding of round 2 that was right."""

import pytest
from pyspark.sql import functions as F

from linkwhy import contract
from linkwhy.functions import pattern as P
from linkwhy.functions.local import Union
from linkwhy.operators import measures as M
from linkwhy.operators import rank as R
from linkwhy.operators.match import match
from linkwhy.operators.paths import paths
from linkwhy.operators.union import _shared, combine, combine_local, merge_instances
from linkwhy.plans import engine
from linkwhy.plans.runs import RunStats
from linkwhy.sources.kb import KnowledgeGraph
from linkwhy.streaming import edges as stream

from .compare import compare, connect


def test_mirrored_patterns_have_one_current():
    for x in range(1, 7):
        for y in range(1, 7):
            one = [(0, f"a{i}", 2, True) for i in range(x)] + [(1, f"b{i}", 2, True) for i in range(y)]
            other = [(1 if a == 0 else 0, rel, b, d) for a, rel, b, d in one]
            assert P.conductance(frozenset(one), 3) == P.conductance(frozenset(other), 3) == pytest.approx(x * y / (x + y))


def graph(spark, rows):
    edges = spark.createDataFrame(rows, "src long, rel string, dst long, directed boolean")
    ends = edges.select(F.explode(F.array("src", "dst")).alias("eid")).distinct()
    return KnowledgeGraph(ends.select("eid", F.lit("node").alias("kind"), F.col("eid").cast("string").alias("name")), edges)


def pair(spark, start, end):
    return spark.createDataFrame([(1, start, end)], "pair_id long, start long, end long")


def test_match_of_plans_that_begin_at_the_end(spark):
    # many a-steps lead into the start and one b-step out of the end, so the plan begins at the end
    kb = graph(spark, [(i, "a", 1, True) for i in range(10, 30)] + [(10, "b", 2, True)])
    keys = spark.createDataFrame([("2>a>0;2>b>1",)], "pattern_key string")
    rows = match(kb, keys, "pair", pair(spark, 1, 2)).collect()
    assert [(r["start"], r["end"], r["binding"]) for r in rows] == [(1, 2, [10])]


def test_merges_look_only_at_bindings_that_fit_the_limit(spark):
    square = "0>a>2;1>a>4;3>a>2;3>a>4"
    paths = {square: {(1, u, 2) for u in range(100, 200)}, "0>a>2;1>a>2": {(1,), (2,), (3,)}}
    union = Union(paths, 5, "exhaustive", "simple")
    assert {b for _, b in union.near((1, 150, 2))} == {(1, 150, 2), (1,), (2,)}
    rows = [(1, k, list(b)) for k, bs in paths.items() for b in bs]
    own = spark.createDataFrame(rows, "pair_id long, pattern_key string, binding array<long>")
    met = merge_instances(own, own, 5, "simple")
    shared = _shared(own.filter(F.size("binding") == 3), "binding", "m1", "m2", 5)
    assert {(r["m2"], len(r["x"])) for r in shared.collect()} == {(1, 1), (2, 2), (3, 3)} and met.filter(F.size("binding") > 3).isEmpty()


def test_paths_leave_steps_that_cannot_reach_the_other_target(spark):
    # 20 dead ends behind the middle node; the last edge of forward paths is looked up at the end
    kb = graph(spark, [(1, "a", 3, True), (3, "b", 2, True), (2, "b", 4, True)] + [(3, "dead", i, True) for i in range(10, 30)] + [(i, "far", 50, True) for i in range(10, 30)])
    sets = []
    for strategy in ("forward", "bidirectional", "activation"):
        stats = RunStats()
        rows = paths(kb, pair(spark, 1, 2), 3, strategy, stats=stats).collect()
        sets.append({(tuple(r["nodes"]), tuple(r["sig"])) for r in rows})
        assert stats.counters["partial_paths"] < (30 if strategy == "forward" else 10)
    assert sets == [{((1, 3, 2), (">a", ">b"))}] * 3


def test_drained_rows_lie_in_the_shared_folder(spark, tmp_path):
    for i in range(3):
        spark.range(i * 10, i * 10 + 10).write.mode("append").parquet(str(tmp_path / "in"))
    rows = spark.readStream.schema("id long").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    out = stream.drain(rows, "drained")
    assert sorted(r["id"] for r in out.collect()) == list(range(30)) and out.inputFiles()
    counts = stream.drain(rows.groupBy((F.col("id") % 3).alias("k")).count(), "drained_counts", "complete")
    assert sorted(tuple(r) for r in counts.collect()) == [(0, 10), (1, 10), (2, 10)]


@pytest.mark.parametrize("include_self", [False, True])
def test_distributions_by_twins_equal_those_by_pairs(spark, include_self):
    # 1-4 are twins, 5 and 6 are, 7 is alone
    rows = [(u, "r", k, True) for u in (1, 2, 3, 4) for k in (101, 102)] + [(u, "r", k, True) for u in (5, 6) for k in (102, 103)] + [(7, "r", 101, True)]
    kb = graph(spark, rows)
    keys = spark.createDataFrame([("0>r>2;1>r>2",)], "pattern_key string")
    starts = spark.createDataFrame([(i,) for i in range(1, 8)], "start long")
    plain = M.local_distribution(kb, keys, starts, include_self=include_self)
    fast = M.local_distribution(kb, keys, starts, include_self=include_self, by_twins=True)
    assert {(r["eid"], r["twin"]) for r in M.twins(kb, keys).collect() if r["eid"] < 8} == {(1, 1), (2, 1), (3, 1), (4, 1), (5, 5), (6, 5), (7, 7)}
    assert sorted(tuple(r) for r in plain.collect()) == sorted(tuple(r) for r in fast.collect())


@pytest.mark.parametrize("chains", [(), (100, 130)])
def test_rounds_see_one_entity_set_of_a_class(spark, chains):
    # 60 middle nodes alike, 8 with one label more, and chains over two of them and a node between
    rows = [(1, r, m, True) for r in "ab" for m in range(100, 168)] + [(2, "a", m, True) for m in range(100, 168)] + [(2, "c", m, True) for m in range(100, 108)]
    kb = graph(spark, rows + [(50, "a", k, True) for k in chains])
    patterns, instances = engine.path_explanations(kb, pair(spark, 1, 2), 5)
    whole = lambda e: {(r["pattern_key"], tuple(r["binding"])) for r in e.instances.collect()}
    shape = lambda e: {(r["pattern_key"], r["n_nodes"], r["n_edges"], r["round"]) for r in e.patterns.collect()}
    stats, every = RunStats(), combine_local(instances, 5, "exhaustive")
    rounds = combine(patterns, instances, 5, "lineage", stats=stats)
    assert whole(rounds) == whole(every) and shape(rounds) == shape(every) and rounds.instances.count() == len(whole(every))
    assert chains or stats.counters["merged_rows"] < 68


def test_positions_are_counted_once_and_leave_the_graph_in_place(spark):
    kb = graph(spark, [(u, "a", k, True) for u in range(1, 7) for k in (101, 102, 103) if (u + k) % 3] + [(u, "b", 102, True) for u in (1, 3)]).pinned()
    pairs = spark.createDataFrame([(1, 1, 2), (2, 3, 4)], "pair_id long, start long, end long")
    expl = engine.enumerate_explanations(kb, pairs, 3)
    n = expl.patterns.groupBy("pair_id").count().agg(F.max("count")).first()[0]
    full = sorted(map(tuple, R.rank_full(kb, pairs, expl, "local_position", n).collect()))
    stats = RunStats()
    assert sorted(map(tuple, R.bounded_position(kb, pairs, expl, n, wave=1, stats=stats).collect())) == full
    assert stats.counters["patterns_counted"] == expl.patterns.count()  # without a bound nothing is counted in slices
    threshold = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = match(kb, expl.patterns.select("pattern_key").distinct(), "start", pairs.select("start"))._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", threshold)
    assert "hashpartitioning(tip" in plan and "hashpartitioning(u" not in plan


def test_toy_explanations_come_from_the_events(spark, tmp_path):
    own, sql = contract.QUERIES["toy_explanations"], contract.ORACLES["toy_explanations"]
    what, ours, theirs = compare(own(spark, "/root/testdata/sf0.001"), connect("/root/testdata/sf0.001"), sql)
    assert not what, (what, ours, theirs)
    with pytest.raises(Exception, match="events.parquet"):
        own(spark, str(tmp_path))
