import pytest
from pyspark.sql import functions as F

from linkwhy.functions import pattern as P
from linkwhy.functions.udfs import cover_size, is_minimal
from linkwhy.operators import judge, render
from linkwhy.operators import measures as M
from linkwhy.operators import rank as R
from linkwhy.operators.grow import grow_enumerate
from linkwhy.operators.match import match
from linkwhy.operators.paths import path_patterns, paths
from linkwhy.operators.union import combine, combine_local
from linkwhy.plans import engine
from linkwhy.plans.runs import RunStats
from linkwhy.sources.kb import TOY, build_kb, toy_ids
from linkwhy.sources.tables import read_edges

from .reference import bindings, explanations

PAIRS = {1: ("ann", "bob"), 2: ("ann", "cy"), 3: ("dee", "bob")}


@pytest.fixture(scope="module")
def toy(spark):
    kb = build_kb(spark, "", "toy").pinned()
    ids = toy_ids()
    pairs = spark.createDataFrame([(i, ids[a], ids[b]) for i, (a, b) in PAIRS.items()], "pair_id long, start long, end long")
    return kb, pairs, ids


@pytest.fixture(scope="module")
def expl(toy):
    kb, pairs, _ = toy
    return engine.enumerate_explanations(kb, pairs, 5)


def instance_set(e, pair=None):
    rows = e.instances.collect()
    return {(r.pair_id, r.pattern_key, tuple(r.binding)) for r in rows if pair in (None, r.pair_id)}


def toy_edges():
    ids = toy_ids()
    return [(*(ids[x] if i != 1 else x for i, x in enumerate((a, rel, b))), "~" not in p) for rel, ps in TOY.items() for p in ps.split() for a, b in [p.replace("~", ">").split(">")]]


@pytest.mark.parametrize("semantics,counts", [("simple", {1: 11, 2: 13, 3: 12}), ("homomorphic", {1: 15})])
def test_path_strategies_agree(toy, semantics, counts):
    kb, pairs, _ = toy
    sets = []
    for strategy, batch in (("forward", None), ("bidirectional", None), ("activation", None), ("activation", 1000), ("label_first", None)):
        rows = paths(kb, pairs, 4, strategy, semantics, batch).collect()
        own = [(r.pair_id, tuple(r.nodes), tuple(r.sig)) for r in rows]
        assert len(own) == len(set(own))
        sets.append(set(own))
    assert all(s == sets[0] for s in sets)
    for pair, n in counts.items():
        assert sum(r[0] == pair for r in sets[0]) == n


def test_toy_explanations_equal_brute_force(toy, expl):
    ids = toy_ids()
    for pair, (a, b) in PAIRS.items():
        want = explanations(toy_edges(), ids[a], ids[b], 5)
        got = {}
        for _, key, binding in instance_set(expl, pair):
            got.setdefault(key, set()).add(binding)
        assert got == want
    assert expl.patterns.filter("pair_id = 1").count() == 17 and len(instance_set(expl, 1)) == 23


def test_unions_agree_and_rounds_are_cover_sizes(toy, expl):
    kb, pairs, _ = toy
    patterns, instances = engine.path_explanations(kb, pairs, 5)
    want = instance_set(expl)
    for e in (
        combine_local(instances, 5, "exhaustive"),
        combine(patterns, instances, 5, "lineage"),
        combine(patterns, instances, 5, "exhaustive", merge_plan="pattern_first"),
    ):
        assert instance_set(e) == want
    assert expl.patterns.filter(~is_minimal("pattern_key")).count() == 0
    assert expl.patterns.filter(cover_size("pattern_key") != F.col("round")).count() == 0


def test_homomorphic_counts(toy):
    kb, pairs, _ = toy
    one = pairs.filter("pair_id = 1")
    patterns, instances = engine.path_explanations(kb, one, 5, semantics="homomorphic")
    a, b = combine(patterns, instances, 5, "lineage", "homomorphic"), combine_local(instances, 5, "lineage", "homomorphic")
    assert instance_set(a) == instance_set(b) and len(instance_set(a)) == 69 and a.patterns.count() == 50


def test_growth_baseline_agrees(toy):
    kb, pairs, _ = toy
    small = grow_enumerate(kb, pairs, 4)
    assert instance_set(small) == instance_set(engine.enumerate_explanations(kb, pairs, 4))


def test_match_gives_the_instances(toy, expl):
    kb, pairs, _ = toy
    got = match(kb, expl.patterns.select("pair_id", "pattern_key"), "pair", pairs)
    assert {(r.pair_id, r.pattern_key, tuple(r.binding)) for r in got.collect()} == instance_set(expl)
    ids = toy_ids()
    key = "0>acts>2;0>acts>3;4>directs>2;4>directs>3;4>mentors>1"
    own = bindings(P.parse_key(key), toy_edges(), ids["ann"], ids["bob"], ids.values())
    assert {b for p, k, b in instance_set(expl, 1) if k == key} == own and len(own) == 2


def test_measures_on_worked_patterns(toy, expl):
    kb, pairs, ids = toy
    one = pairs.filter("pair_id = 1")
    value = lambda df: {r.pattern_key: r.value for r in df.filter("pair_id = 1").collect()}
    count, mono = value(M.count(expl.instances)), value(M.monocount(expl.instances))
    chain, twin = "0>acts>2;3>directs>2;3>mentors>1", "0>acts>2;0>acts>3;4>directs>2;4>directs>3;4>mentors>1"
    assert (count[chain], mono[chain]) == (2, 1) and (count["0~married~1"], mono["0~married~1"]) == (1, 1)
    assert count[twin] == 2 and value(M.count(expl.instances, "subgraph"))[twin] == 1
    assert value(M.size(expl.patterns))[chain] == -4 and value(M.walk(expl.patterns))[chain] == pytest.approx(1 / 3)
    pos = value(M.measure("local_position", kb, one, expl.patterns.filter("pair_id = 1"), expl.instances.filter("pair_id = 1")))
    assert pos["0>acts>2;1>acts>2"] == 2 and pos["0~married~1"] == 0
    own = M.measure("local_position", kb, one, expl.patterns.filter("pair_id = 1"), expl.instances.filter("pair_id = 1"), semantics="sql", include_self=True)
    assert value(own)["0>acts>2;1>acts>2"] == 3


def test_position_of_a_given_distribution(spark):
    dist = spark.createDataFrame([("k", 9, 1, 130), ("k", 9, 2, 8), ("k", 9, 3, 10), ("k", 9, 4, 2)], "pattern_key string, start long, value long, n_pairs long")
    scored = spark.createDataFrame([(1, "k", 9, 1.0), (2, "k", 9, 4.0)], "pair_id long, pattern_key string, start long, value double")
    assert {r.pair_id: r.value for r in M.position(scored, dist).collect()} == {1: 20.0, 2: 0.0}
    assert M.deviation(scored, dist).filter("pair_id = 2").first().value > 4


def test_anti_monotone_along_lineage(expl):
    mono, walk = M.monocount(expl.instances), M.walk(expl.patterns)
    for values, bad in ((mono, "child > parent"), (walk, "child < parent - 1e-9")):
        v = values.select("pair_id", "pattern_key", "value")
        link = expl.lineage.join(v.withColumnsRenamed({"pattern_key": "child_key", "value": "child"}), ["pair_id", "child_key"]).join(v.withColumnsRenamed({"pattern_key": "parent_key", "value": "parent"}), ["pair_id", "parent_key"])
        assert link.count() > 0 and link.filter(bad).count() == 0


@pytest.mark.parametrize("k", [1, 3, 10])
def test_frontier_equals_full(toy, expl, k):
    kb, pairs, _ = toy
    full = R.rank_full(kb, pairs, expl, "monocount", k).collect()
    assert sorted(map(tuple, engine.rank(kb, pairs, "monocount", k, "frontier_topk").collect())) == sorted(map(tuple, full))
    with pytest.raises(ValueError):
        engine.rank(kb, pairs, "walk", k, "frontier_topk")


def test_frontier_does_less_work(toy):
    kb, pairs, _ = toy
    full, top = RunStats(), RunStats()
    engine.enumerate_explanations(kb, pairs, 5, stats=full)
    engine.rank(kb, pairs, "size", 2, "frontier_topk", stats=top)
    assert top.counters["merges_tried"] < full.counters["merges_tried"]


def test_bounded_position_equals_full(toy, expl):
    kb, pairs, _ = toy
    full = sorted(map(tuple, R.rank_full(kb, pairs, expl, "local_position", 4).collect()))
    assert sorted(map(tuple, R.bounded_position(kb, pairs, expl, 4, wave=20).collect())) == full


def test_lazy_combination_equals_eager(toy, expl):
    kb, pairs, _ = toy
    stats = RunStats()
    lazy = R.rank_combined(kb, pairs, expl, ["size", "local_position"], 3, stats=stats)
    eager = R.rank_combined(kb, pairs, expl, ["size", "local_position"], 3, lazy_secondary=False)
    keys = lambda df: sorted((r.pair_id, r.rank, r.pattern_key) for r in df.collect())
    assert keys(lazy) == keys(eager) and stats.counters["local_position_evaluated"] < expl.patterns.count()


def test_reversed_pair_mirrors(toy):
    kb, pairs, _ = toy
    back = engine.enumerate_explanations(kb, pairs.select("pair_id", F.col("end").alias("start"), F.col("start").alias("end")), 4)
    there = engine.enumerate_explanations(kb, pairs, 4)
    turned = set()
    for r in back.patterns.collect():
        e = P.renumber(P.parse_key(r.pattern_key), [1, 0, 2, 3])
        turned.add((r.pair_id, P.canonical(e, r.n_nodes)[0]))
    assert turned == {(r.pair_id, r.pattern_key) for r in there.patterns.collect()}


def test_scores(spark):
    ranked = spark.createDataFrame([(1, i, f"k{i}") for i in range(1, 11)], "pair_id long, rank int, pattern_key string")
    grades = lambda g: spark.createDataFrame([(1, 1, f"k{i}", g(i)) for i in range(1, 11)], "judge_id int, pair_id long, pattern_key string, grade int")
    score = lambda g: judge.dcg_score(ranked, grades(g)).first().score
    assert score(lambda i: 2) == pytest.approx(100) and score(lambda i: 0) == 0
    assert score(lambda i: 2 * (i == 1)) == pytest.approx(22.01, abs=0.01)


def test_learned_combination(toy, expl):
    kb, pairs, _ = toy
    features = engine.measure_table(kb, pairs, expl, ["size", "count", "monocount", "walk"])
    top, model = R.learned_combination(features, judge.rule_grades(expl.patterns, kb.edges), ["size", "count", "monocount", "walk"], 3)
    assert top.count() == 9 and len(model.coefficients) == 4


def test_decoration_and_text(toy, expl):
    kb, pairs, _ = toy
    top = R.rank_full(kb, pairs, expl, "monocount", 2)
    text = render.describe(top, expl.instances, kb).collect()
    assert len(text) == 6 and all(r.examples for r in text)
    own = expl.instances.join(top, ["pair_id", "pattern_key"], "left_semi")
    assert render.decorate(own, kb, ["in_guild"]).count() > 0


def test_store_and_import(spark, toy, tmp_path):
    kb, pairs, _ = toy
    kb.write(str(tmp_path / "kb"))
    from linkwhy.sources.kb import KnowledgeGraph

    again = KnowledgeGraph.read(spark, str(tmp_path / "kb"))
    assert paths(again, pairs, 4).count() == paths(kb, pairs, 4).count()
    (tmp_path / "e.csv").write_text("s,p,o\n1,knows,2\n1,knows,2\n2,knows,2\nx,knows,1\n")
    edges = read_edges(spark, str(tmp_path / "e.csv"), mapping={"src": "s", "rel": "p", "dst": "o"})
    assert edges.count() == 2
    (tmp_path / "e.txt").write_text("1 knows 2\n\n7\n8 knows\n  \n2 likes 3\n")
    assert read_edges(spark, str(tmp_path / "e.txt"), "triples").count() == 2


def test_far_edges_change_nothing(spark, toy, expl):
    kb, pairs, ids = toy
    from linkwhy.sources.kb import KnowledgeGraph

    extra = spark.createDataFrame([(900, "acts", 901, True)], kb.edges.schema)
    more = KnowledgeGraph(kb.entities, kb.edges.unionByName(extra))
    assert instance_set(engine.enumerate_explanations(more, pairs, 5)) == instance_set(expl)


def test_pair_without_paths_and_empty_batch(spark, toy):
    kb, _, ids = toy
    none = spark.createDataFrame([(7, ids["g1"], 12345)], "pair_id long, start long, end long")
    assert engine.enumerate_explanations(kb, none, 5).patterns.count() == 0
    assert engine.enumerate_explanations(kb, none.filter("false"), 5).instances.count() == 0


def test_path_grouping_keeps_order(toy):
    kb, pairs, _ = toy
    _, instances = path_patterns(paths(kb, pairs, 4))
    got = match(kb, instances.select("pair_id", "pattern_key").distinct(), "pair", pairs)
    assert got.count() == instances.count()


def test_the_pinned_graph_does_not_move(spark, toy):
    kb, pairs, _ = toy
    threshold = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = kb.reach(pairs.withColumnRenamed("start", "tip"), "tip")._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", threshold)
    assert "hashpartitioning(tip" in plan and "hashpartitioning(u" not in plan


def test_hubs_are_dealt_to_many_places(spark, toy, expl, monkeypatch):
    from linkwhy.sources import kb as K

    monkeypatch.setattr(K, "HUB_STEPS", 0)
    monkeypatch.setattr(K, "HUB_SHARE", 1 / 10)
    kb, pairs, _ = toy
    split = build_kb(spark, "", "toy").pinned()
    assert split.cache["hubs"]
    rows = lambda g: sorted((r.pair_id, tuple(r.nodes), tuple(r.sig)) for r in paths(g, pairs, 4, "bidirectional").collect())
    assert rows(split) == rows(kb)


def test_similar_vectors_are_all_pairs_of_a_label(spark, monkeypatch):
    import numpy as np

    from linkwhy.sources import kb as K

    monkeypatch.setattr(K, "VECTOR_BLOCK", 7)
    rng = np.random.default_rng(5)
    rows = [(i, int(rng.integers(0, 3)), rng.normal(size=4).tolist()) for i in range(60)] + [(90, None, [1.0] * 4), (91, 1, None)]
    got = {(r.a, r.b) for r in K.similar_pairs(spark.createDataFrame(rows, "vec_id long, label long, embedding array<double>"), 0.5).collect()}
    cos = lambda x, y: np.dot(x, y) / np.sqrt(np.dot(x, x) * np.dot(y, y))
    assert got == {(i, j) for i, k, x in rows[:60] for j, m, y in rows[:60] if i < j and k == m and cos(x, y) >= 0.5}
