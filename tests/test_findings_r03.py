"""Small tests for the findings of round 3 that were right."""

from collections import Counter

import pytest

from linkwhy.functions import middle
from linkwhy.functions import pattern as P
from linkwhy.operators import measures as M

from .test_findings_r02 import graph

USERS, KEYS = range(1, 25), range(101, 113)
ROWS = [(u, rel, k, True) for rel, m in (("a", 3), ("b", 4)) for u in USERS for k in KEYS if (u * u * 7 + k * 11 + u * k) % 13 % m == 0] + [(u, "u", k, False) for u in USERS for k in KEYS if (u * 5 + k * k) % 7 == 0]
SINGLE = ("0>a>2;1>a>2", "0>a>2;0>b>2;1>a>2", "0~u~2;1>a>2", "2>a>0;2>a>1")


def keys_of(spark, keys):
    return spark.createDataFrame([(k,) for k in keys], "pattern_key string")


def no_match(*args, **options):
    raise AssertionError("a row for each instance")


def test_sides_of_patterns_with_one_variable():
    sides = lambda key: middle.sides(P.parse_key(key))
    assert sides("0>a>2;2>b>1") == [(0, "a", 1), (1, "b", -1)] and sides("0~u~2;1>a>2") == [(0, "u", 0), (1, "a", 1)]
    assert [sides(k) for k in ("0>a>1", "0>a>2;1>a>2;0>b>1", "0>a>2;2>a>3;1>a>3", "0>a>2")] == [None] * 4


@pytest.mark.parametrize("semantics,include_self", [("simple", False), ("homomorphic", True), ("sql", True)])
def test_local_distributions_make_no_row_for_an_instance(spark, monkeypatch, semantics, include_self):  # F1
    kb = graph(spark, ROWS)
    starts = spark.createDataFrame([(i,) for i in [*USERS][::2] + [*KEYS][::3]], "start long")
    plain = sorted(tuple(r) for r in M.local_distribution(kb, keys_of(spark, SINGLE), starts, semantics=semantics, include_self=include_self).collect())
    assert {r[0] for r in plain} == set(SINGLE)
    monkeypatch.setattr(M, "match", no_match)
    for steps in (M.BLOCK_STEPS, 30):  # one block, and several
        monkeypatch.setattr(M, "BLOCK_STEPS", steps)
        monkeypatch.setattr(M, "LEAST_STEPS", min(steps, 20))
        own = M.local_distribution(kb, keys_of(spark, SINGLE), starts, semantics=semantics, include_self=include_self, by_twins=True)
        assert sorted(tuple(r) for r in own.collect()) == plain


def test_blocks_and_twins_are_put_together(spark):
    kb = graph(spark, ROWS)
    keys = keys_of(spark, [SINGLE[0], "0>a>2;1>a>3;4>b>2;4>b>3"])
    starts = spark.createDataFrame([(1,), (2,)], "start long")
    plain, own = (sorted(tuple(r) for r in M.local_distribution(kb, keys, starts, by_twins=t).collect()) for t in (False, True))
    assert own == plain and len({r[0] for r in own}) == 2


@pytest.mark.parametrize("dom,most", [(6, 5), (400, 3), (400, 300)])
def test_blocks_count_shared_entities(dom, most):
    import pyarrow as pa

    def block(side, sets):
        t = pa.table({"u": pa.array(list(sets), pa.int64()), "vs": pa.array([list(v) for v in sets.values()], pa.list_(pa.int64()))})
        return middle.pack((pa.scalar(1), pa.scalar(side), pa.scalar(0)), t).column("data")[0].as_py()

    starts = {u * 10: {(u * u * 31 + i * 17 + u) % dom for i in range(1 + (u * most // 20) % most)} for u in range(30, 0, -1)}
    ends = {u * 5: {(u * u * 13 + i * 7) % (dom + 3) + 2 for i in range(1 + (u * most // 30) % most)} for u in range(50)}
    for with_self in (False, True):
        want = {s: Counter(len(x & y) for e, y in ends.items() if with_self or e != s) for s, x in starts.items()}
        got = {int(s): dict(zip(v.tolist(), n.tolist(), strict=True)) for s, v, n in middle.count_block(block(0, starts), block(1, ends), with_self)}
        assert {s: {v: n for v, n in c.items() if v} for s, c in want.items()} == {s: got.get(s, {}) for s in starts}


@pytest.mark.parametrize("steps", [1 << 21, 30])
def test_exact_global_distributions_make_no_row_for_an_instance(spark, monkeypatch, steps):  # F2
    kb = graph(spark, ROWS)
    near = lambda rel: {u: {k for a, r, k, _ in ROWS if (a, r) == (u, rel)} for u in USERS}
    want = Counter((f"0>{r}>2;1>{r}>2", len(near(r)[x] & near(r)[y])) for r in "ab" for x in USERS for y in USERS if x != y)
    monkeypatch.setattr(M, "match", no_match)
    monkeypatch.setattr(M, "BLOCK_STEPS", steps)
    monkeypatch.setattr(M, "LEAST_STEPS", min(steps, 20))
    own = M.global_distribution(kb, keys_of(spark, ["0>a>2;1>a>2", "0>b>2;1>b>2"]), sample=None)
    assert {(r["pattern_key"], r["value"]): r["n_pairs"] for r in own.collect()} == {k: n for k, n in want.items() if k[1]}
