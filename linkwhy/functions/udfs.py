"""Arrow-batched functions over pattern columns.  They see patterns, never instances."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import middle
from . import pattern as P

# Types as objects: this module is also imported by workers, which have no session to parse them.
_INT, _STR = T.IntegerType(), T.StringType()
EDGES = T.ArrayType(T.StructType([T.StructField("a", _INT), T.StructField("rel", _STR), T.StructField("b", _INT), T.StructField("directed", T.BooleanType())]))
NAMED = T.StructType(
    [T.StructField("pattern_key", _STR), T.StructField("perm", T.ArrayType(_INT)), T.StructField("n_nodes", _INT), T.StructField("n_edges", _INT), T.StructField("edges", EDGES)]
)
SIDES = T.ArrayType(T.StructType([T.StructField("side", _INT), T.StructField("rel", _STR), T.StructField("dir", _INT)]))
STEPS = T.ArrayType(T.StructType([T.StructField("origin", _INT), T.StructField("rel", _STR), T.StructField("dir", _INT), T.StructField("target", _INT)]))


def as_edges(rows) -> frozenset:
    return frozenset((int(r["a"]), r["rel"], int(r["b"]), bool(r["directed"])) for r in rows)


def as_rows(edges) -> list[dict]:
    return [{"a": a, "rel": rel, "b": b, "directed": d} for a, rel, b, d in sorted(edges)]


def named(edges: frozenset, n_nodes: int) -> dict:
    """Key, order of the variables (as places in a binding, from 1), sizes and edges of the canonical pattern."""
    key, order = P.canonical(edges, n_nodes)
    place = {0: 0, 1: 1} | {old: new + 2 for new, old in enumerate(order)}
    return {"pattern_key": key, "perm": [v - 1 for v in order], "n_nodes": n_nodes, "n_edges": len(edges), "edges": as_rows(P.renumber(edges, place))}


@F.pandas_udf(NAMED)
def name_path(steps: pd.Series) -> pd.DataFrame:
    return pd.DataFrame([named(*P.path_edges(list(s))) for s in steps])


@F.pandas_udf(NAMED)
def name_merge(left: pd.Series, right: pd.Series, match: pd.Series) -> pd.DataFrame:
    """``match[i]``: place (from 1) in the right binding of the entity at place i of the left one, 0 if none."""
    out = []
    for a, b, m in zip(left, right, match, strict=True):
        a, b = P.parse_key(a), P.parse_key(b)
        n_left = len(m) + 2
        back = {int(j) + 1: i + 2 for i, j in enumerate(m) if j}
        out.append(named(*P.merged(a, n_left, b, P.nodes_of(b), back)))
    return pd.DataFrame(out)


@F.pandas_udf(NAMED)
def name_growth(left: pd.Series, n_nodes: pd.Series, a: pd.Series, rel: pd.Series, b: pd.Series, directed: pd.Series) -> pd.DataFrame:
    """A pattern with one edge more; node numbers from ``n_nodes`` on are new variables."""
    out = []
    for key, n, *e in zip(left, n_nodes, a, rel, b, directed, strict=True):
        edges = (P.parse_key(key) if key else frozenset()) | {P.oriented(int(e[0]), e[1], int(e[2]), bool(e[3]))}
        out.append(named(edges, max(int(n), P.nodes_of(edges))))
    return pd.DataFrame(out)


@F.pandas_udf(EDGES)
def edges_of(key: pd.Series) -> pd.Series:
    return key.map(lambda k: as_rows(P.parse_key(k)))


@F.pandas_udf(SIDES)
def middle_sides(key: pd.Series) -> pd.Series:
    """The edges of a pattern with one variable by target, null for other patterns."""
    own = (middle.sides(P.parse_key(k)) for k in key)
    return pd.Series([x and [{"side": t, "rel": r, "dir": d} for t, r, d in x] for x in own], dtype=object)


@F.pandas_udf(T.BooleanType())
def is_essential(key: pd.Series) -> pd.Series:
    return key.map(lambda k: P.is_essential(P.parse_key(k)))


@F.pandas_udf(T.BooleanType())
def is_decomposable(key: pd.Series) -> pd.Series:
    return key.map(lambda k: P.is_decomposable(P.parse_key(k)))


@F.pandas_udf(T.BooleanType())
def is_minimal(key: pd.Series) -> pd.Series:
    return key.map(lambda k: P.is_minimal(P.parse_key(k)))


@F.pandas_udf(_STR)
def canonical_key(key: pd.Series) -> pd.Series:
    """The canonical key of edges written in any numbering."""
    return key.map(lambda k: P.canonical(P.parse_key(k), P.nodes_of(P.parse_key(k)))[0])


@F.pandas_udf(_INT)
def cover_size(key: pd.Series) -> pd.Series:
    return key.map(lambda k: len(P.covering_paths(P.parse_key(k))))


@F.pandas_udf(_INT)
def automorphism_count(key: pd.Series) -> pd.Series:
    return key.map(lambda k: P.automorphisms(P.parse_key(k), P.nodes_of(P.parse_key(k))))


@F.pandas_udf(T.DoubleType())
def walk_conductance(key: pd.Series) -> pd.Series:
    return key.map(lambda k: P.conductance(P.parse_key(k), P.nodes_of(P.parse_key(k))))


def grounded_conductance(sink: float):
    @F.pandas_udf(T.DoubleType())
    def grounded(key: pd.Series) -> pd.Series:
        return key.map(lambda k: P.conductance(P.parse_key(k), P.nodes_of(P.parse_key(k)), sink))

    return grounded


def match_steps(bound: tuple[int, ...], fan: dict[tuple[str, int], float] | None = None):
    @F.pandas_udf(STEPS)
    def steps(key: pd.Series) -> pd.Series:
        return key.map(lambda k: [{"origin": a, "rel": r, "dir": d, "target": b} for a, r, d, b in P.match_plan(P.parse_key(k), bound, fan)])

    return steps


@F.pandas_udf(T.LongType())
def monocount_of(binding: pd.Series) -> int:
    """Grouped aggregate: least number of different entities at any place (1 without places)."""
    rows = [list(b) for b in binding]
    return min((len(set(column)) for column in zip(*rows, strict=True)), default=1)


@F.udtf(returnType=T.StructType([T.StructField("new_key", _STR), T.StructField("match", T.ArrayType(_INT)), T.StructField("n_nodes", _INT)]))
class MergeMaps:
    """All merges of two patterns within a node limit: (key, map, nodes)."""

    def eval(self, left: str, right: str, limit: int):
        a, b = P.parse_key(left), P.parse_key(right)
        for m in P.partial_maps(P.nodes_of(a), P.nodes_of(b), limit):
            edges, n = P.merged(a, P.nodes_of(a), b, P.nodes_of(b), m)
            back = {v: k for k, v in m.items()}
            yield P.canonical(edges, n)[0], [back.get(i, 1) - 1 for i in range(2, P.nodes_of(a))], n


def register(spark: SparkSession) -> None:
    """Make the pattern functions callable from SQL."""
    for f in (is_essential, is_decomposable, is_minimal, canonical_key, cover_size, automorphism_count, walk_conductance):
        spark.udf.register(f.__name__, f)
    spark.udtf.register("merge_maps", MergeMaps)
