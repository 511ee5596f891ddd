"""The registered queries over the given tables, and the SQL that each must agree with.

Queries of one family share their graph, pairs and SQL fragments, so that every strategy
of a method is held against the same rows.
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import permutations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .operators import judge, render
from .operators import measures as M
from .operators import rank as R
from .operators.grow import grow_enumerate
from .operators.match import match, position_sql
from .operators.pairs import connectedness, random_pairs, sample_pairs, session_pairs
from .operators.paths import path_patterns, paths
from .plans import engine
from .plans.runs import settle
from .sources.kb import KIND, KINDS, KnowledgeGraph, build_kb, eid
from .sources.tables import load
from .streaming import edges as stream

#: Five-node explanations between users run on this window of events: over all 30 days of sf0.01 a pair of users has about
#: 60,000 paths of four edges, and the forward strategy builds 14 million partial ones for it.
UNTIL = "2024-01-04"
N_PAIRS = 30
START_USERS, SEED = 5, 7

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


# --- graphs -------------------------------------------------------------------------------

U, K = KINDS["user"] * KIND, KINDS["key"] * KIND


def _edges_sql(until: str | None = UNTIL) -> str:
    where = f" AND ts < TIMESTAMP '{until}'" if until else ""
    return f"""edges AS (SELECT DISTINCT {U} + user_id AS src, event_type AS rel, {K} + CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS BIGINT) AS dst
        FROM events WHERE regexp_extract(props, '"k": *([0-9]+)', 1) <> ''{where})"""


PAIRS_SQL = f"""users AS (SELECT DISTINCT src AS eid FROM edges),
    s AS (SELECT row_number() OVER (ORDER BY md5('{SEED}:s:' || eid)) AS pair_id, eid AS s FROM users QUALIFY pair_id <= {N_PAIRS}),
    e AS (SELECT row_number() OVER (ORDER BY md5('{SEED}:e:' || eid)) AS pair_id, eid AS e FROM users QUALIFY pair_id <= {N_PAIRS}),
    pairs AS (SELECT pair_id, s, e FROM s JOIN e USING (pair_id) WHERE s <> e)"""


def _setting(spark: SparkSession, sf_dir: str, until: str | None = UNTIL) -> tuple[KnowledgeGraph, DataFrame]:
    kb = build_kb(spark, sf_dir, "activity", ts_to=until).pinned()
    return kb, settle(random_pairs(kb, N_PAIRS, SEED))


@query("kb_edges_activity", f"WITH {_edges_sql(None)} SELECT src, rel, dst FROM edges")
def kb_edges_activity(spark, sf_dir):
    return build_kb(spark, sf_dir, "activity").edges.select("src", "rel", "dst")


def _md5(x: str) -> str:
    return f"CAST('0x' || substr(md5({x}), 1, 12) AS BIGINT)"


def _no(kind: str) -> int:
    return KINDS[kind] * KIND


COMMERCE_SQL = f"""edges AS (
    SELECT {_no("customer")} + c_custkey AS src, 'lives_in' AS rel, {_no("nation")} + c_nationkey AS dst FROM customer
    UNION SELECT {_no("customer")} + c_custkey, 'in_segment', {_no("segment")} + {_md5("c_mktsegment")} FROM customer
    UNION SELECT {_no("supplier")} + s_suppkey, 'based_in', {_no("nation")} + s_nationkey FROM supplier
    UNION SELECT {_no("nation")} + n_nationkey, 'in_region', {_no("region")} + n_regionkey FROM nation
    UNION SELECT {_no("customer")} + o_custkey, 'placed', {_no("order")} + o_orderkey FROM orders
    UNION SELECT {_no("order")} + l_orderkey, 'contains', {_no("part")} + l_partkey FROM lineitem
    UNION SELECT {_no("supplier")} + l_suppkey, 'fills', {_no("order")} + l_orderkey FROM lineitem
    UNION SELECT {_no("part")} + p_partkey, 'has_brand', {_no("brand")} + {_md5("p_brand")} FROM part
    UNION SELECT {_no("part")} + p_partkey, 'has_type', {_no("type")} + {_md5("p_type")} FROM part)"""


@query("kb_edges_commerce", f"WITH {COMMERCE_SQL} SELECT src, rel, dst FROM edges")
def kb_edges_commerce(spark, sf_dir):
    return build_kb(spark, sf_dir, "commerce").edges.select("src", "rel", "dst")


@query(
    "kb_edges_content",
    f"""WITH copies AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS first FROM documents),
    v AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings)
    SELECT {_no("document")} + doc_id AS src, 'in_lang' AS rel, {_no("lang")} + {_md5("lang")} AS dst, true AS directed FROM documents WHERE lang IS NOT NULL
    UNION SELECT {_no("document")} + doc_id, 'from_source', {_no("source")} + {_md5("source")}, true FROM documents WHERE source IS NOT NULL
    UNION SELECT {_no("document")} + doc_id, 'graded', {_no("grade")} + quality, true FROM labels WHERE quality IS NOT NULL
    UNION SELECT {_no("document")} + first, 'near_copy', {_no("document")} + doc_id, false FROM copies WHERE first < doc_id
    UNION SELECT {_no("page")} + page_id, 'hosted_by', {_no("host")} + {_md5("regexp_extract(url, '^[a-z]+://([^/]+)', 1)")}, true FROM pages
    UNION SELECT {_no("vector")} + vec_id, 'labelled', {_no("label")} + label, true FROM embeddings
    UNION SELECT {_no("vector")} + x.vec_id, 'similar', {_no("vector")} + y.vec_id, false FROM v x JOIN v y ON x.label = y.label AND x.vec_id < y.vec_id
        WHERE list_dot_product(x.e, y.e) >= 0.5 * sqrt(list_dot_product(x.e, x.e)) * sqrt(list_dot_product(y.e, y.e))
    UNION SELECT {_no("conversation")} + conv_id, 'has_role', {_no("role")} + {_md5("role")}, true FROM conversations""",
)
def kb_edges_content(spark, sf_dir):
    return build_kb(spark, sf_dir, "content").edges


@query(
    "kb_summary",
    f"""WITH {COMMERCE_SQL} SELECT coalesce(CAST(floor(src / {KIND}) AS INT), -1) AS kind, coalesce(rel, '*') AS rel, count(*) AS n_edges,
    count(DISTINCT src) AS n_src, count(DISTINCT dst) AS n_dst FROM (SELECT CAST(floor(src / {KIND}) AS INT) AS k, * FROM edges) GROUP BY ROLLUP (k, rel)""".replace(
        f"coalesce(CAST(floor(src / {KIND}) AS INT), -1) AS kind", "coalesce(k, -1) AS kind"
    ),
)
def kb_summary(spark, sf_dir):
    return build_kb(spark, sf_dir, "commerce").summary()


@query("kb_degrees", f"WITH {COMMERCE_SQL} SELECT eid, count(*) AS degree FROM (SELECT src AS eid FROM edges UNION ALL SELECT dst FROM edges) GROUP BY eid")
def kb_degrees(spark, sf_dir):
    return build_kb(spark, sf_dir, "commerce").degrees


# --- paths --------------------------------------------------------------------------------

_TWO = "JOIN edges a ON a.src = p.s JOIN edges b ON b.dst = a.dst AND b.src = p.e"
_FOUR = """JOIN edges a ON a.src = p.s JOIN edges b ON b.dst = a.dst AND b.src <> p.s AND b.src <> p.e
    JOIN edges c ON c.src = b.src AND c.dst <> a.dst JOIN edges d ON d.dst = c.dst AND d.src = p.e"""
PATHS_SQL = f"WITH {_edges_sql()}, {PAIRS_SQL}"


ALL_PATHS_SQL = f"WITH {_edges_sql(None)}, {PAIRS_SQL}"


def _path_rows(spark, sf_dir, length, until=None):
    kb, pairs = _setting(spark, sf_dir, until)
    return paths(kb, pairs, length).select("pair_id", F.array_join(F.transform("nodes", lambda x: x.cast("string")), ",").alias("nodes"), F.array_join("sig", ",").alias("sig"))


_L2 = f"SELECT p.pair_id, concat_ws(',', p.s, a.dst, p.e) AS nodes, '>' || a.rel || ',<' || b.rel AS sig FROM pairs p {_TWO}"
_L4 = f"SELECT p.pair_id, concat_ws(',', p.s, a.dst, b.src, c.dst, p.e), '>' || a.rel || ',<' || b.rel || ',>' || c.rel || ',<' || d.rel FROM pairs p {_FOUR}"
query("path_instances_l2", f"{ALL_PATHS_SQL} {_L2}")(lambda spark, sf_dir: _path_rows(spark, sf_dir, 2))
query("path_instances_l3", f"{ALL_PATHS_SQL} {_L2}")(lambda spark, sf_dir: _path_rows(spark, sf_dir, 3))
query("path_instances_l4", f"{PATHS_SQL} {_L2} UNION ALL {_L4}")(lambda spark, sf_dir: _path_rows(spark, sf_dir, 4, UNTIL))


def _least_text(edges: list[tuple[str, str, str]]) -> str:
    """SQL for the canonical key of a pattern whose nodes are placeholders k1, u, k2."""
    texts = []
    for p in permutations("234"):
        place = dict(zip(("k1", "u", "k2"), p, strict=True)) | {"0": "0", "1": "1"}
        parts = ", ".join(f"'{place[x]}>' || {rel} || '>{place[y]}'" for x, rel, y in edges)
        texts.append(f"array_to_string(list_sort([{parts}]), ';')")
    return f"least({', '.join(texts)})"


_KEY2 = "'0>' || a.rel || '>2;1>' || b.rel || '>2'"
_KEY4 = _least_text([("0", "a.rel", "k1"), ("u", "b.rel", "k1"), ("u", "c.rel", "k2"), ("1", "d.rel", "k2")])
PATTERNS_SQL = f"""{PATHS_SQL} SELECT pair_id, pattern_key, count(*) AS n_instances FROM (
    SELECT p.pair_id, {_KEY2} AS pattern_key FROM pairs p {_TWO} UNION ALL SELECT p.pair_id, {_KEY4} FROM pairs p {_FOUR}) GROUP BY ALL"""


def _pattern_rows(spark, sf_dir, strategy, **options):
    kb, pairs = _setting(spark, sf_dir)
    _, instances = path_patterns(paths(kb, pairs, 4, strategy, **options))
    return instances.groupBy("pair_id", "pattern_key").agg(F.count(F.lit(1)).alias("n_instances"))


for _name in ("forward", "bidirectional", "activation", "label_first"):
    query(f"path_patterns_{_name}", PATTERNS_SQL)(lambda spark, sf_dir, s=_name: _pattern_rows(spark, sf_dir, s))
query("path_patterns_activation_literal", PATTERNS_SQL)(lambda spark, sf_dir: _pattern_rows(spark, sf_dir, "activation", batch=1_000))


#: Simple paths of one to four edges between pairs (pair_id, s, e) over ``ways`` (u, rel, v), counted from the middle.
COUNT_PATHS_SQL = """ways AS (SELECT src AS u, rel, dst AS v FROM edges UNION ALL SELECT dst, rel || '-', src FROM edges),
    s1 AS (SELECT p.pair_id, p.s, p.e, x.v FROM pairs p JOIN ways x ON x.u = p.s),
    e1 AS (SELECT p.pair_id, p.s, p.e, x.v FROM pairs p JOIN ways x ON x.u = p.e WHERE x.v <> p.s),
    s2 AS (SELECT h.pair_id, h.e, h.v AS a, x.v FROM s1 h JOIN ways x ON x.u = h.v WHERE h.v <> h.e AND x.v <> h.s AND x.v <> h.e),
    e2 AS (SELECT h.pair_id, h.v AS a, x.v FROM e1 h JOIN ways x ON x.u = h.v WHERE x.v <> h.s AND x.v <> h.e),
    m AS (SELECT pair_id, v, count(*) AS n FROM e1 GROUP BY ALL),
    f2 AS (SELECT pair_id, v, count(*) AS n FROM s2 GROUP BY ALL), g2 AS (SELECT pair_id, v, count(*) AS n FROM e2 GROUP BY ALL),
    same AS (SELECT x.pair_id, x.n * y.n AS n FROM (SELECT pair_id, a, v, count(*) AS n FROM s2 GROUP BY ALL) x JOIN (SELECT pair_id, a, v, count(*) AS n FROM e2 GROUP BY ALL) y USING (pair_id, a, v)),
    three AS (SELECT x.pair_id, sum(x.n * m.n) AS n FROM f2 x JOIN m USING (pair_id, v) GROUP BY x.pair_id),
    found AS (
        SELECT pair_id, count(*) AS n FROM s1 WHERE v = e GROUP BY pair_id
        UNION ALL SELECT x.pair_id, sum(m.n) FROM s1 x JOIN m ON m.pair_id = x.pair_id AND m.v = x.v GROUP BY x.pair_id
        UNION ALL SELECT pair_id, n FROM three
        UNION ALL SELECT x.pair_id, sum(x.n * y.n) FROM f2 x JOIN g2 y USING (pair_id, v) GROUP BY x.pair_id
        UNION ALL SELECT pair_id, -sum(n) FROM same GROUP BY pair_id),
    counted AS (SELECT p.pair_id, p.s, p.e, CAST(coalesce(sum(f.n), 0) AS BIGINT) AS n_paths FROM pairs p LEFT JOIN found f USING (pair_id) GROUP BY ALL),
    banded AS (SELECT pair_id, s AS "start", e AS "end", n_paths, CASE WHEN n_paths <= 30 THEN 'low' WHEN n_paths <= 100 THEN 'medium' ELSE 'high' END AS band FROM counted)"""
#: Customers drawn as candidates for the pairs of three bands, and pairs of each band.
CANDIDATES, PER_BAND = 120, 10


def _customers_sql(n: int) -> str:
    draw = lambda tag, c: f"{c} AS (SELECT row_number() OVER (ORDER BY md5('{SEED}:{tag}:' || eid)) AS pair_id, eid AS {c} FROM people QUALIFY pair_id <= {n})"
    return f"people AS (SELECT DISTINCT src AS eid FROM edges WHERE rel = 'lives_in'), {draw('s', 's')}, {draw('e', 'e')}, pairs AS (SELECT pair_id, s, e FROM s JOIN e USING (pair_id) WHERE s <> e)"


@query("pair_connectedness", f"WITH {COMMERCE_SQL}, {_customers_sql(N_PAIRS)}, {COUNT_PATHS_SQL} SELECT * FROM banded")
def pair_connectedness(spark, sf_dir):
    kb = build_kb(spark, sf_dir, "commerce").pinned()
    return connectedness(kb, settle(random_pairs(kb, N_PAIRS, SEED, "customer", "customer")))


@query("pairs_by_band", f"""WITH {COMMERCE_SQL}, {_customers_sql(CANDIDATES)}, {COUNT_PATHS_SQL}
    SELECT pair_id, "start", "end", n_paths, band FROM banded QUALIFY row_number() OVER (PARTITION BY band ORDER BY pair_id) <= {PER_BAND}""")
def pairs_by_band(spark, sf_dir):
    """Ten pairs of low, ten of medium and ten of high connectedness, as far as the candidates have them."""
    kb = build_kb(spark, sf_dir, "commerce").pinned()
    return sample_pairs(kb, PER_BAND, SEED, 4, CANDIDATES, "customer", "customer")


# --- explanations of three nodes: a closed form exists ---------------------------------------


def _subset(var: str, mask: str, node: int) -> str:
    return f"list_transform(list_filter(range(1, len({var}) + 1), lambda i: ({mask} >> CAST(i - 1 AS INT)) & 1 = 1), lambda i: '{node}>' || {var}[i] || '>2')"


N3_SQL = f"""WITH {_edges_sql(None)}, {PAIRS_SQL},
    lab AS (SELECT src, dst, list_sort(list(rel)) AS ls FROM edges GROUP BY ALL),
    shared AS (SELECT p.pair_id, p.s, p.e, a.ls AS l, b.ls AS r FROM pairs p JOIN lab a ON a.src = p.s JOIN lab b ON b.src = p.e AND b.dst = a.dst),
    picks AS (SELECT pair_id, {_subset("l", "m", 0)} AS x, {_subset("r", "n", 1)} AS y
        FROM (SELECT *, unnest(range(1, 1 << len(l))) AS m FROM shared) t, LATERAL (SELECT unnest(range(1, 1 << len(t.r))) AS n)),
    expl AS (SELECT pair_id, array_to_string(list_concat(x, y), ';') AS pattern_key, len(x) AS a, len(y) AS b, len(x) + len(y) AS n_edges, count(*) AS n FROM picks GROUP BY ALL)"""


def _n3(spark, sf_dir, union="exhaustive", plan="auto", **more):
    kb, pairs = _setting(spark, sf_dir, None)
    return kb, pairs, engine.enumerate_explanations(kb, pairs, 3, "bidirectional", union, plan=plan, **more)


def _expl_rows(expl):
    n = expl.instances.groupBy("pair_id", "pattern_key").agg(F.count(F.lit(1)).alias("n_instances"))
    return expl.patterns.join(n, ["pair_id", "pattern_key"]).select("pair_id", "pattern_key", "n_nodes", "n_edges", "n_instances")


EXPL3 = f"{N3_SQL} SELECT pair_id, pattern_key, CAST(3 AS INT) AS n_nodes, CAST(n_edges AS INT) AS n_edges, n AS n_instances FROM expl"
query("explanations_n3", EXPL3)(lambda spark, sf_dir: _expl_rows(_n3(spark, sf_dir)[2]))
query("explanations_n3_lineage", EXPL3)(lambda spark, sf_dir: _expl_rows(_n3(spark, sf_dir, "lineage")[2]))
query("explanations_n3_relational", EXPL3)(lambda spark, sf_dir: _expl_rows(_n3(spark, sf_dir, "lineage", "relational")[2]))
query("explanations_n3_pattern_first", EXPL3)(lambda spark, sf_dir: _expl_rows(_n3(spark, sf_dir, "lineage", "relational", merge_plan="pattern_first")[2]))


@query("grow_n3", EXPL3)
def grow_n3(spark, sf_dir):
    kb, pairs = _setting(spark, sf_dir, None)
    return _expl_rows(grow_enumerate(kb, pairs, 3))


@query("paths_only_n3", f"{N3_SQL} SELECT pair_id, pattern_key, CAST(3 AS INT) AS n_nodes, CAST(2 AS INT) AS n_edges, n AS n_instances FROM expl WHERE n_edges = 2")
def paths_only_n3(spark, sf_dir):
    return _expl_rows(_n3(spark, sf_dir, paths_only=True)[2])


@query("explanation_stats_n3", f"{N3_SQL} SELECT pair_id, CAST(greatest(a, b) AS INT) AS round, count(*) AS n_patterns, CAST(sum(n) AS BIGINT) AS n_instances FROM expl GROUP BY ALL")
def explanation_stats_n3(spark, sf_dir):
    return engine.explanation_stats(_n3(spark, sf_dir, "lineage")[2])


#: Five-node patterns matched one by one: a chain with a double edge, a square, and two shared keys.
SELECTED = (
    "0>click>2;1>view>3;4>click>2;4>view>3",
    "0>view>2;0>view>3;1>click>2;1>view>3",
    "0>click>2;1>click>2",
)


def _match_sql(key: str) -> str:
    edges = [tuple(part.split(">")) for part in key.split(";")]
    nodes = sorted({n for a, _, b in edges for n in (a, b)} - {"0", "1"})
    col: dict[str, str] = {"0": "p.s", "1": "p.e"}
    on = []
    for i, (a, rel, b) in enumerate(edges):
        on.append(f"t{i}.rel = '{rel}'")
        for node, c in ((a, f"t{i}.src"), (b, f"t{i}.dst")):
            if node in col:
                on.append(f"{c} = {col[node]}")
            else:
                col[node] = c
    on += [f"{col[x]} <> {col[y]}" for i, x in enumerate(["0", "1", *nodes]) for y in nodes if y > x and y != x]
    return f"SELECT p.pair_id, '{key}' AS pattern_key, count(*) AS n_instances FROM pairs p, {', '.join(f'edges t{i}' for i in range(len(edges)))} WHERE {' AND '.join(on)} GROUP BY p.pair_id"


@query("match_selected", f"WITH {_edges_sql()}, {PAIRS_SQL} {' UNION ALL '.join(map(_match_sql, SELECTED))}")
def match_selected(spark, sf_dir):
    kb, pairs = _setting(spark, sf_dir)
    keys = spark.createDataFrame([(k,) for k in SELECTED], "pattern_key string")
    return match(kb, keys, "pair", pairs).groupBy("pair_id", "pattern_key").agg(F.count(F.lit(1)).alias("n_instances"))


def _match_in(semantics: str) -> str:
    """The selected patterns where variables may coincide: never with a target (homomorphic), or with anything (sql)."""
    out = []
    for key in SELECTED:
        sql = _match_sql(key)
        kept = [c for c in sql.partition(" WHERE ")[2].rpartition(" GROUP BY ")[0].split(" AND ") if " <> " not in c or (semantics == "homomorphic" and " <> t" in c and c.startswith("p."))]
        out.append(f"{sql.partition(' WHERE ')[0]} WHERE {' AND '.join(kept)} GROUP BY p.pair_id")
    return f"WITH {_edges_sql()}, {PAIRS_SQL} {' UNION ALL '.join(out)}"


def _match_rows(spark, sf_dir, semantics):
    kb, pairs = _setting(spark, sf_dir)
    keys = spark.createDataFrame([(k,) for k in SELECTED], "pattern_key string")
    return match(kb, keys, "pair", pairs, semantics).groupBy("pair_id", "pattern_key").agg(F.count(F.lit(1)).alias("n_instances"))


for _name in ("homomorphic", "sql"):
    query(f"match_{_name}", _match_in(_name))(lambda spark, sf_dir, s=_name: _match_rows(spark, sf_dir, s))


@query("explanations_n5_selected", f"WITH {_edges_sql()}, {PAIRS_SQL} {' UNION ALL '.join(map(_match_sql, SELECTED))}")
def explanations_n5_selected(spark, sf_dir):
    kb, pairs = _setting(spark, sf_dir)
    expl = engine.enumerate_explanations(kb, pairs, 5)
    return expl.instances.filter(F.col("pattern_key").isin(list(SELECTED))).groupBy("pair_id", "pattern_key").agg(F.count(F.lit(1)).alias("n_instances"))


def _masked(var: str, mask: str) -> str:
    return f"list_transform(list_filter(range(1, len({var}) + 1), lambda i: ({mask} >> CAST(i - 1 AS INT)) & 1 = 1), lambda i: {var}[i])"


def _square_texts() -> list[str]:
    """The text of a square pattern in each numbering of its two keys and its user (x, u, y)."""
    out = []
    for p in permutations("234"):
        x, u, y = p
        parts = [f"list_transform(r.{c}, lambda l: '{a}>' || l || '>{b}')" for c, a, b in (("a1", "0", x), ("a2", "0", y), ("b1", "1", x), ("b2", "1", y), ("c1", u, x), ("c2", u, y))]
        joined = parts[0]
        for q in parts[1:]:
            joined = f"list_concat({joined}, {q})"
        order = sorted(zip(p, ("r.k1", "r.u", "r.k2"), strict=True))
        out.append(f"{{'t': array_to_string(list_sort({joined}), ';'), 'v2': {order[0][1]}, 'v3': {order[1][1]}, 'v4': {order[2][1]}}}")
    return out


#: All minimal explanations between users up to five nodes: a shared key, or two keys and a user between them.
#: A set of labels at each of the six places; ``kinds`` has one row a pattern, with count, monocount and delivered current.
N5_SQL = N3_SQL.replace(_edges_sql(None), _edges_sql()).replace("expl AS (", "small AS (") + f""",
    mids AS (SELECT x.src AS u, x.dst AS k1, y.dst AS k2, x.ls AS c1, y.ls AS c2 FROM lab x JOIN lab y ON x.src = y.src AND x.dst < y.dst),
    squares AS (SELECT p.pair_id, m.*, coalesce(a1.ls, []) AS a1, coalesce(a2.ls, []) AS a2, coalesce(b1.ls, []) AS b1, coalesce(b2.ls, []) AS b2
        FROM pairs p JOIN mids m ON m.u <> p.s AND m.u <> p.e
        LEFT JOIN lab a1 ON a1.src = p.s AND a1.dst = m.k1 LEFT JOIN lab a2 ON a2.src = p.s AND a2.dst = m.k2
        LEFT JOIN lab b1 ON b1.src = p.e AND b1.dst = m.k1 LEFT JOIN lab b2 ON b2.src = p.e AND b2.dst = m.k2
        WHERE (a1.ls IS NOT NULL AND b2.ls IS NOT NULL) OR (a2.ls IS NOT NULL AND b1.ls IS NOT NULL)),
    masks AS (SELECT s.*, q1.m AS ma1, q2.m AS ma2, q3.m AS mb1, q4.m AS mb2, q5.m AS mc1, q6.m AS mc2 FROM squares s,
        LATERAL (SELECT unnest(range(0, 1 << len(s.a1))) AS m) q1, LATERAL (SELECT unnest(range(0, 1 << len(s.a2))) AS m) q2,
        LATERAL (SELECT unnest(range(0, 1 << len(s.b1))) AS m) q3, LATERAL (SELECT unnest(range(0, 1 << len(s.b2))) AS m) q4,
        LATERAL (SELECT unnest(range(1, 1 << len(s.c1))) AS m) q5, LATERAL (SELECT unnest(range(1, 1 << len(s.c2))) AS m) q6
        WHERE (q1.m > 0 AND q4.m > 0) OR (q2.m > 0 AND q3.m > 0)),
    r AS (SELECT pair_id, k1, u, k2, {", ".join(f"{_masked(c, 'm' + c)} AS {c}" for c in ("a1", "a2", "b1", "b2", "c1", "c2"))} FROM masks),
    texts AS (SELECT r.*, [{", ".join(_square_texts())}] AS t FROM r),
    placed AS (SELECT pair_id, a1, a2, b1, b2, c1, c2, list_min(list_transform(t, lambda z: z.t)) AS pattern_key, unnest(t) AS one FROM texts),
    wide AS (SELECT pair_id, pattern_key, count(*) AS n, least(count(DISTINCT one.v2), count(DISTINCT one.v3), count(DISTINCT one.v4)) AS mono,
        any_value(len(a1) + len(a2) + len(b1) + len(b2) + len(c1) + len(c2)) AS n_edges,
        any_value({{'a1': len(a1), 'a2': len(a2), 'b1': len(b1), 'b2': len(b2), 'c': 1.0 / (1.0 / len(c1) + 1.0 / len(c2))}}) AS g FROM placed WHERE one.t = pattern_key GROUP BY ALL),
    solved AS (SELECT *, g.a1 + g.b1 + g.c AS d1, g.a2 + g.b2 + g.c AS d2 FROM wide),
    kinds AS (SELECT pair_id, pattern_key, 3 AS n_nodes, n_edges, n, n AS mono, 1.0 / (1.0 / a + 1.0 / b) AS walk FROM small
        UNION ALL SELECT pair_id, pattern_key, 5, n_edges, n, mono, (g.b1 * (g.a1 * d2 + g.c * g.a2) + g.b2 * (g.a2 * d1 + g.c * g.a1)) / (d1 * d2 - g.c * g.c) FROM solved)"""
EXPL5 = f"{N5_SQL} SELECT pair_id, pattern_key, CAST(n_nodes AS INT) AS n_nodes, CAST(n_edges AS INT) AS n_edges, n AS n_instances FROM kinds"


def _n5(spark, sf_dir, combo="activation+lineage", **more):
    kb, pairs = _setting(spark, sf_dir)
    return kb, pairs, engine.run_combo(kb, pairs, combo, **more)


for _name in engine.COMBOS:
    query("explanations_n5_" + _name.replace("+", "_"), EXPL5)(lambda spark, sf_dir, c=_name: _expl_rows(_n5(spark, sf_dir, c)[2]))
query("explanations_n5_relational", EXPL5)(lambda spark, sf_dir: _expl_rows(_n5(spark, sf_dir, plan="relational")[2]))


#: Nations and parts: pairs whose explanations have one, two or three variables of three kinds.
#: x: nation, customer, order, part; y: nation, supplier, order, part.  ``every`` has all instances between any nation and any part.
N_TRADE = 1000


def _key_of(edges: list[tuple[str, str, str]], nodes: str) -> str:
    """The canonical text of edges between named nodes: the least over all numberings of ``nodes``."""
    texts = []
    for p in permutations(range(2, 2 + len(nodes))):
        place = dict(zip(nodes, p, strict=True)) | {"n": 0, "p": 1}
        texts.append(";".join(sorted(f"{place[a]}>{rel}>{place[b]}" for a, rel, b in edges)))
    return min(texts)


def _trade(nodes: str, edges: str) -> str:
    names = {"l": "lives_in", "d": "placed", "t": "contains", "b": "based_in", "f": "fills"}
    return _key_of([(e[0], names[e[1]], e[2]) for e in edges.split()], nodes)


TRADE_SQL = f"""{COMMERCE_SQL}, e AS (SELECT * FROM edges),
    x AS (SELECT l.dst AS n, l.src AS c, d.dst AS o, t.dst AS p FROM e l JOIN e d ON d.src = l.src AND d.rel = 'placed' JOIN e t ON t.src = d.dst AND t.rel = 'contains' WHERE l.rel = 'lives_in'),
    y AS (SELECT b.dst AS n, b.src AS s, f.dst AS o, t.dst AS p FROM e b JOIN e f ON f.src = b.src AND f.rel = 'fills' JOIN e t ON t.src = f.dst AND t.rel = 'contains' WHERE b.rel = 'based_in'),
    every AS (
        SELECT n, p, '{_trade("co", "cln cdo otp")}' AS pattern_key, 4 AS n_nodes, 3 AS n_edges, 1.0 / 3 AS walk, c AS v2, o AS v3, o AS v4 FROM x
        UNION ALL SELECT n, p, '{_trade("so", "sbn sfo otp")}', 4, 3, 1.0 / 3, s, o, o FROM y
        UNION ALL SELECT x.n, x.p, '{_trade("cso", "cln cdo otp sbn sfo")}', 5, 5, 0.5, x.c, y.s, x.o FROM x JOIN y ON x.n = y.n AND x.p = y.p AND x.o = y.o
        UNION ALL SELECT x.n, x.p, '{_trade("cab", "cln cda cdb atp btp")}', 5, 5, 0.5, x.c, x.o, z.o FROM x JOIN x z ON x.n = z.n AND x.p = z.p AND x.c = z.c AND x.o <> z.o
        UNION ALL SELECT y.n, y.p, '{_trade("sab", "sbn sfa sfb atp btp")}', 5, 5, 0.5, y.s, y.o, z.o FROM y JOIN y z ON y.n = z.n AND y.p = z.p AND y.s = z.s AND y.o <> z.o
        UNION ALL SELECT y.n, y.p, '{_trade("abo", "abn bbn afo bfo otp")}', 5, 5, 0.5, y.s, z.s, y.o FROM y JOIN y z ON y.n = z.n AND y.p = z.p AND y.o = z.o AND y.s <> z.s),
    tally AS (SELECT n, p, pattern_key, n_nodes, n_edges, walk, count(*) AS c, least(count(DISTINCT v2), count(DISTINCT v3), count(DISTINCT v4)) AS mono FROM every GROUP BY ALL),
    parts AS (SELECT DISTINCT src AS eid FROM edges WHERE rel = 'has_brand'),
    pairs AS (SELECT row_number() OVER (ORDER BY md5('{SEED}:' || eid)) AS pair_id, eid AS e FROM parts QUALIFY pair_id <= {N_TRADE}),
    kinds AS (SELECT q.pair_id, t.*, c AS count FROM pairs q JOIN tally t ON t.p = q.e AND t.n = {KINDS["nation"] * KIND} + q.pair_id % 25),
    posed AS (SELECT k.*, (SELECT count(*) FROM tally o WHERE o.n = k.n AND o.pattern_key = k.pattern_key AND o.c > k.c) AS position FROM kinds k)"""


def _trade_setting(spark, sf_dir):
    kb = build_kb(spark, sf_dir, "commerce").pinned()
    parts = M.sample_starts(kb, N_TRADE, SEED, "part").select(F.col("start").alias("end"))
    order = Window.orderBy(F.md5(F.concat(F.lit(f"{SEED}:"), F.col("end").cast("string"))))
    pairs = parts.withColumn("pair_id", F.row_number().over(order).cast("long"))
    return kb, settle(pairs.select("pair_id", (F.lit(KINDS["nation"] * KIND) + F.col("pair_id") % 25).alias("start"), "end"))


def _trade_expl(spark, sf_dir, **more):
    kb, pairs = _trade_setting(spark, sf_dir)
    return kb, pairs, engine.enumerate_explanations(kb, pairs, 5, **more)


_TRADE_ROWS = f"WITH {TRADE_SQL} SELECT pair_id, pattern_key, CAST(n_nodes AS INT) AS n_nodes, CAST(n_edges AS INT) AS n_edges, c AS n_instances FROM kinds"
query("explanations_n5_trade", _TRADE_ROWS)(lambda spark, sf_dir: _expl_rows(_trade_expl(spark, sf_dir)[2]))
query("explanations_n5_trade_relational", _TRADE_ROWS)(lambda spark, sf_dir: _expl_rows(_trade_expl(spark, sf_dir, plan="relational")[2]))
query("match_n5_trade", _TRADE_ROWS)(lambda spark, sf_dir: _matched(spark, sf_dir))


def _matched(spark, sf_dir):
    """Every pattern of the trade explanations matched anew for every pair, whether it has instances there or not."""
    kb, pairs = _trade_setting(spark, sf_dir)
    keys = settle(engine.enumerate_explanations(kb, pairs, 5).patterns.select("pattern_key", "n_nodes", "n_edges").distinct())
    n = match(kb, keys, "pair", pairs).groupBy("pair_id", "pattern_key").agg(F.count(F.lit(1)).alias("n_instances"))
    return n.join(keys, "pattern_key").select("pair_id", "pattern_key", "n_nodes", "n_edges", "n_instances")


# --- measures ------------------------------------------------------------------------------


def _value_rows(df: DataFrame) -> DataFrame:
    return df.select("pair_id", "pattern_key", F.round("value", 6).alias("value"))


def _measure_n3(name: str):
    def run(spark, sf_dir):
        kb, pairs, expl = _n3(spark, sf_dir, "lineage")
        return _value_rows(M.measure(name, kb, pairs, expl.patterns, expl.instances))

    return run


VALUES3 = {"count": "CAST(n AS DOUBLE)", "walk": "round(1.0 / (1.0 / a + 1.0 / b), 6)"}
for _name, _sql in VALUES3.items():
    query(f"measure_{_name}_n3", f"{N3_SQL} SELECT pair_id, pattern_key, {_sql} AS value FROM expl")(_measure_n3(_name))


def _measure_of(setting, name: str, **options):
    def run(spark, sf_dir):
        kb, pairs, expl = setting(spark, sf_dir)
        return _value_rows(M.measure(name, kb, pairs, expl.patterns, expl.instances, **options))

    return run


VALUES5 = {"size": "CAST(-n_nodes AS DOUBLE)", "count": "CAST(n AS DOUBLE)", "monocount": "CAST(mono AS DOUBLE)", "walk": "round(CAST(walk AS DOUBLE), 6)"}
for _name, _sql in VALUES5.items():
    query(f"measure_{_name}_n5", f"{N5_SQL} SELECT pair_id, pattern_key, {_sql} AS value FROM kinds")(_measure_of(_n5, _name))
query("measure_monocount_trade", f"WITH {TRADE_SQL} SELECT pair_id, pattern_key, {VALUES5['monocount']} AS value FROM kinds")(_measure_of(_trade_expl, "monocount"))


def _trade4(spark, sf_dir):
    """Up to four nodes: with five, every order of a supplier would meet every other one for each nation."""
    kb, pairs = _trade_setting(spark, sf_dir)
    return kb, pairs, engine.enumerate_explanations(kb, pairs, 4)


query("measure_local_position_n4", f"WITH {TRADE_SQL} SELECT pair_id, pattern_key, CAST(position AS DOUBLE) AS value FROM posed WHERE n_nodes = 4")(_measure_of(_trade4, "local_position"))


def _starts(spark, kb):
    return settle(M.sample_starts(kb, START_USERS, SEED, "user"))


STARTS_SQL = f"starts AS (SELECT eid AS s FROM users ORDER BY md5('{SEED}:' || eid) LIMIT {START_USERS})"
TWO_STEP = ("purchase", "view", "click")
_ALL = f"WITH {_edges_sql(None)}, {PAIRS_SQL}, {STARTS_SQL}"
_LABELS = ", ".join(f"'{x}'" for x in TWO_STEP)
_ENDS = "SELECT a.src AS s, b.src AS e, a.rel AS r1, b.rel AS r2, count(*) AS n FROM edges a JOIN edges b ON a.dst = b.dst AND a.src <> b.src"


def _two_step(spark):
    return spark.createDataFrame([(f"0>{r}>2;1>{r}>2",) for r in TWO_STEP], "pattern_key string")


_KEYS2 = "'0>' || r1 || '>2;1>' || r2 || '>2'"


@query("local_distribution", f"""{_ALL}, ends AS ({_ENDS} WHERE a.rel = b.rel AND a.rel IN ({_LABELS}) AND a.src IN (SELECT s FROM starts) GROUP BY ALL)
    SELECT {_KEYS2} AS pattern_key, s AS "start", n AS value, count(*) AS n_pairs FROM ends GROUP BY ALL""")
def local_distribution(spark, sf_dir):
    kb, _ = _setting(spark, sf_dir, None)
    return M.local_distribution(kb, _two_step(spark), _starts(spark, kb))


@query("global_distribution_exact", f"""{_ALL}, ends AS ({_ENDS} WHERE a.rel = b.rel AND a.rel IN ({_LABELS}) GROUP BY ALL)
    SELECT {_KEYS2} AS pattern_key, n AS value, count(*) AS n_pairs FROM ends GROUP BY ALL""")
def global_distribution_exact(spark, sf_dir):
    kb, _ = _setting(spark, sf_dir, None)
    return M.global_distribution(kb, _two_step(spark), sample=None).filter(F.lit(True))


@query("global_distribution_sampled", f"""{_ALL}, ends AS ({_ENDS} WHERE a.rel = b.rel AND a.rel IN ({_LABELS}) AND a.src IN (SELECT s FROM starts) GROUP BY ALL)
    SELECT {_KEYS2} AS pattern_key, n AS value, count(*) AS n_pairs FROM ends GROUP BY ALL""")
def global_distribution_sampled(spark, sf_dir):
    kb, _ = _setting(spark, sf_dir, None)
    return M.global_distribution(kb, _two_step(spark), sample=START_USERS, seed=SEED, kind="user")


_POS = f"""{_ALL}, ends AS ({_ENDS} WHERE a.src IN (SELECT s FROM pairs) GROUP BY ALL),
    own AS (SELECT p.pair_id, x.* FROM pairs p JOIN ends x ON x.s = p.s AND x.e = p.e)"""


def _path3(spark, sf_dir):
    kb, pairs, expl = _n3(spark, sf_dir, paths_only=True)
    return kb, pairs, expl


LOCAL_POS = f"""{_POS} SELECT o.pair_id, {_KEYS2.replace("r1", "o.r1").replace("r2", "o.r2")} AS pattern_key,
    CAST(count(x.n) AS DOUBLE) AS value FROM own o LEFT JOIN ends x ON x.s = o.s AND x.r1 = o.r1 AND x.r2 = o.r2 AND x.n > o.n GROUP BY ALL"""


@query("local_position", LOCAL_POS)
def local_position(spark, sf_dir):
    kb, pairs, expl = _path3(spark, sf_dir)
    return _value_rows(M.measure("local_position", kb, pairs, expl.patterns, expl.instances))


@query("local_deviation", f"""{_POS}, m AS (SELECT s, r1, r2, avg(n) AS mean, stddev_pop(n) AS sd FROM ends GROUP BY ALL)
    SELECT o.pair_id, {_KEYS2.replace("r1", "o.r1").replace("r2", "o.r2")} AS pattern_key, CASE WHEN m.sd > 1e-9 THEN round((o.n - m.mean) / m.sd, 6) END AS value
    FROM own o JOIN m USING (s, r1, r2)""")
def local_deviation(spark, sf_dir):
    kb, pairs, expl = _path3(spark, sf_dir)
    return _value_rows(M.measure("local_deviation", kb, pairs, expl.patterns, expl.instances))


@query("global_position_sampled", f"""{_ALL}, ends AS ({_ENDS} WHERE a.src IN (SELECT s FROM starts) GROUP BY ALL),
    mine AS ({_ENDS} WHERE a.src IN (SELECT s FROM pairs) GROUP BY ALL), own AS (SELECT p.pair_id, x.* FROM pairs p JOIN mine x ON x.s = p.s AND x.e = p.e)
    SELECT o.pair_id, {_KEYS2.replace("r1", "o.r1").replace("r2", "o.r2")} AS pattern_key, CAST(count(x.n) AS DOUBLE) AS value
    FROM own o LEFT JOIN ends x ON x.r1 = o.r1 AND x.r2 = o.r2 AND x.n > o.n GROUP BY ALL""")
def global_position_sampled(spark, sf_dir):
    kb, pairs, expl = _path3(spark, sf_dir)
    return _value_rows(M.measure("global_position", kb, pairs, expl.patterns, expl.instances, sample=START_USERS, seed=SEED, kind="user"))


@query("local_position_sql", f"""{_ALL} SELECT b.src AS end_id, count(*) AS n FROM edges a JOIN edges b ON a.dst = b.dst AND a.rel = 'purchase' AND b.rel = 'purchase'
    WHERE a.src = (SELECT s FROM starts ORDER BY md5('{SEED}:' || s) LIMIT 1) GROUP BY b.src HAVING count(*) > 1""")
def local_position_sql(spark, sf_dir):
    """Ends that share more than one purchase with a start, by the generated SQL over the relation of edges."""
    kb, _ = _setting(spark, sf_dir, None)
    kb.register("kb")
    start = _starts(spark, kb).orderBy(F.md5(F.concat(F.lit(f"{SEED}:"), F.col("start").cast("string")))).first()[0]
    return spark.sql(position_sql("0>purchase>2;1>purchase>2", start, 1))


# --- rankings ------------------------------------------------------------------------------

TOP = 10


def _top_sql(order: str, value: str, source: str = N3_SQL) -> str:
    return f"""{source} SELECT * FROM (SELECT pair_id, CAST(row_number() OVER (PARTITION BY pair_id ORDER BY {order}, n_edges, pattern_key) AS INT) AS rank, pattern_key,
    CAST(3 AS INT) AS n_nodes, CAST(n_edges AS INT) AS n_edges, {value} AS value FROM expl) WHERE rank <= {TOP}"""


def _rank_n3(measure, **options):
    def run(spark, sf_dir):
        kb, pairs, expl = _n3(spark, sf_dir, "lineage")
        return R.rank_full(kb, pairs, expl, measure, TOP, **options).withColumn("value", F.round("value", 6))

    return run


for _name in ("count", "walk"):
    query(f"topk_{_name}", _top_sql(f"{VALUES3[_name]} DESC", VALUES3[_name]))(_rank_n3(_name))


@query("topk_monocount_frontier", _top_sql("n DESC", "CAST(n AS DOUBLE)"))
def topk_monocount_frontier(spark, sf_dir):
    kb, pairs = _setting(spark, sf_dir, None)
    return engine.rank(kb, pairs, "monocount", TOP, "frontier_topk", 3)


@query("topk_monocount_frontier_relational", _top_sql("n DESC", "CAST(n AS DOUBLE)"))
def topk_monocount_frontier_relational(spark, sf_dir):
    kb, pairs = _setting(spark, sf_dir, None)
    return R.frontier_topk(*engine.path_explanations(kb, pairs, 3), "monocount", TOP, 3, local=False)[0]


def _top_of(source: str, table: str, order: str, value: str) -> str:
    return f"""{source} SELECT * FROM (SELECT pair_id, CAST(row_number() OVER (PARTITION BY pair_id ORDER BY {order}, n_nodes, n_edges, pattern_key) AS INT) AS rank, pattern_key,
    CAST(n_nodes AS INT) AS n_nodes, CAST(n_edges AS INT) AS n_edges, {value} AS value FROM {table}) WHERE rank <= {TOP}"""


def _full_of(setting, measure):
    def run(spark, sf_dir):
        kb, pairs, expl = setting(spark, sf_dir)
        return R.rank_full(kb, pairs, expl, measure, TOP).withColumn("value", F.round("value", 6))

    return run


def _combined_of(setting, measures, **options):
    def run(spark, sf_dir):
        kb, pairs, expl = setting(spark, sf_dir)
        out = R.rank_combined(kb, pairs, expl, measures, TOP, **options)
        return out.select("pair_id", "rank", "pattern_key", "n_nodes", "n_edges", F.round(measures[1], 6).alias("value"))

    return run


_TOP_MONO5 = _top_of(N5_SQL, "kinds", "mono DESC", VALUES5["monocount"])
query("topk_monocount_n5", _TOP_MONO5)(_full_of(_n5, "monocount"))
query("topk_size_n5", _top_of(N5_SQL, "kinds", "n_nodes", VALUES5["size"]))(_full_of(_n5, "size"))


@query("topk_frontier_n5", _TOP_MONO5)
def topk_frontier_n5(spark, sf_dir):
    kb, pairs = _setting(spark, sf_dir)
    return engine.rank(kb, pairs, "monocount", TOP, "frontier_topk")


@query("topk_frontier_n5_relational", _TOP_MONO5)
def topk_frontier_n5_relational(spark, sf_dir):
    kb, pairs = _setting(spark, sf_dir)
    return R.frontier_topk(*engine.path_explanations(kb, pairs, 5), "monocount", TOP, 5, local=False)[0]


query("topk_size_monocount", _top_of(N5_SQL, "kinds", "n_nodes, mono DESC", VALUES5["monocount"]))(_combined_of(_n5, ["size", "monocount"], lazy_secondary=False))
@query("topk_position_bounded_n4", _top_of(f"WITH {TRADE_SQL}, four AS (SELECT * FROM posed WHERE n_nodes = 4)", "four", "position", "CAST(position AS DOUBLE)"))
def topk_position_bounded_n4(spark, sf_dir):
    kb, pairs, expl = _trade4(spark, sf_dir)
    return R.bounded_position(kb, pairs, expl, TOP, wave=1)


#: Values of every explanation with three nodes at every end of the pairs' starts.
_N3_POS = N3_SQL + f""", reach AS (SELECT p.pair_id, b.src AS other, a.ls AS l, b.ls AS r FROM pairs p JOIN lab a ON a.src = p.s JOIN lab b ON b.dst = a.dst AND b.src <> p.s),
    need AS (SELECT pair_id, pattern_key, n, n_edges, list_transform(list_filter(string_split(pattern_key, ';'), lambda t: t[1] = '0'), lambda t: string_split(t, '>')[2]) AS x,
        list_transform(list_filter(string_split(pattern_key, ';'), lambda t: t[1] = '1'), lambda t: string_split(t, '>')[2]) AS y FROM expl),
    others AS (SELECT q.pair_id, q.pattern_key, t.other, count(*) AS c FROM need q JOIN reach t ON t.pair_id = q.pair_id AND list_has_all(t.l, q.x) AND list_has_all(t.r, q.y) GROUP BY ALL),
    posed AS (SELECT q.pair_id, q.pattern_key, q.n_edges, count(o.c) AS position FROM need q LEFT JOIN others o ON o.pair_id = q.pair_id AND o.pattern_key = q.pattern_key AND o.c > q.n GROUP BY ALL)"""
TOP_POSITION = _top_sql("position", "CAST(position AS DOUBLE)", _N3_POS).replace("FROM expl) WHERE", "FROM posed) WHERE")
query("topk_local_position", TOP_POSITION)(_rank_n3("local_position"))


@query("topk_position_bounded", TOP_POSITION)
def topk_position_bounded(spark, sf_dir):
    kb, pairs, expl = _n3(spark, sf_dir, "lineage")
    return R.bounded_position(kb, pairs, expl, TOP)


def _n3_lineage(spark, sf_dir):
    return _n3(spark, sf_dir, "lineage")


query("topk_size_local", TOP_POSITION)(_combined_of(_n3_lineage, ["size", "local_position"]))
query("topk_size_local_eager", TOP_POSITION)(_combined_of(_n3_lineage, ["size", "local_position"], lazy_secondary=False))


# --- judgements ----------------------------------------------------------------------------

_GRADE = f"CAST(CAST('0x' || substr(md5(concat_ws('|', j, pair_id, pattern_key)), 1, 8) AS BIGINT) % 3 AS INT)"  # noqa: F541
_RANKED = _top_sql("n DESC", "CAST(n AS DOUBLE)")
_JUDGED = f"{N3_SQL}, ranked AS ({_RANKED[len(N3_SQL) :]}), grades AS (SELECT pair_id, pattern_key, CAST(j AS INT) AS judge_id, {_GRADE} AS grade FROM expl, range(1, 11) t(j))"


@query("dcg_scores", f"""{_JUDGED}, most AS (SELECT pair_id, sum(2 / log2(rank + 1)) AS most FROM ranked GROUP BY pair_id)
    SELECT pair_id, judge_id, round(100 * sum(grade / log2(rank + 1)) / any_value(most), 6) AS score FROM ranked JOIN grades USING (pair_id, pattern_key) JOIN most USING (pair_id) GROUP BY pair_id, judge_id""")
def dcg_scores(spark, sf_dir):
    kb, pairs, expl = _n3(spark, sf_dir, "lineage")
    ranked = R.rank_full(kb, pairs, expl, "monocount", TOP)
    return judge.dcg_score(ranked, judge.stand_in_grades(expl.patterns), TOP).withColumn("score", F.round("score", 6))


@query("path_share_top5", f"""{_JUDGED}, liked AS (SELECT pair_id, pattern_key, avg(grade) AS g, row_number() OVER (PARTITION BY pair_id ORDER BY avg(grade) DESC, pattern_key) AS r FROM grades GROUP BY pair_id, pattern_key)
    SELECT pair_id, count(*) AS n_best, CAST(sum(CASE WHEN len(string_split(pattern_key, ';')) = 2 THEN 1 ELSE 0 END) AS BIGINT) AS n_paths FROM liked WHERE r <= 5 GROUP BY pair_id""")
def path_share_top5(spark, sf_dir):
    _, _, expl = _n3(spark, sf_dir, "lineage")
    return judge.path_share(expl.patterns, judge.stand_in_grades(expl.patterns), 5)


@query("path_share", f"""{_JUDGED}, liked AS (SELECT pair_id, pattern_key, avg(grade) AS g, row_number() OVER (PARTITION BY pair_id ORDER BY avg(grade) DESC, pattern_key) AS r FROM grades GROUP BY pair_id, pattern_key)
    SELECT pair_id, count(*) AS n_best, CAST(sum(CASE WHEN len(string_split(pattern_key, ';')) = 2 THEN 1 ELSE 0 END) AS BIGINT) AS n_paths FROM liked WHERE r <= 10 GROUP BY pair_id""")
def path_share(spark, sf_dir):
    _, _, expl = _n3(spark, sf_dir, "lineage")
    return judge.path_share(expl.patterns, judge.stand_in_grades(expl.patterns), 10)


@query("effectiveness_table")
def effectiveness_table(spark, sf_dir):
    """The eight rankings judged by the rule judge over five pairs; its numbers say nothing about people."""
    kb, pairs, expl = _n3(spark, sf_dir, "lineage")
    pairs = settle(pairs.orderBy("pair_id").limit(5))
    grades = judge.rule_grades(expl.patterns, kb.edges)
    out = None
    for m in ("size", "walk", "count", "monocount", "local_position", "global_position"):
        options = {"sample": 20, "kind": "user"} if m == "global_position" else {}
        s = judge.dcg_score(R.rank_full(kb, pairs, expl, m, TOP, **options), grades).withColumn("measure", F.lit(m))
        out = s if out is None else out.unionByName(s)
    for a, b in (("size", "monocount"), ("size", "local_position")):
        s = judge.dcg_score(R.rank_combined(kb, pairs, expl, [a, b], TOP), grades).withColumn("measure", F.lit(f"{a}+{b}"))
        out = out.unionByName(s)
    out = out.join(pairs.select("pair_id"), "pair_id", "left_semi")
    return judge.mean_scores(out.select("measure", "pair_id", "score"), [1, 2, 3, 4, 5]).select("measure", *[F.round(F.col(str(i)), 4).alias(f"p{i}") for i in range(1, 6)], F.round("avg", 4).alias("avg"))


# --- operators around the methods ------------------------------------------------------------

#: Three pairs as in the worked examples: two share their start and two their end.
TOY_UNTIL = UNTIL
TOY_PAIRS = ((11, 4), (11, 2), (7, 4))
TOY_SQL = EXPL5.replace(_edges_sql(), _edges_sql(TOY_UNTIL)).replace(PAIRS_SQL, f"pairs(pair_id, s, e) AS (VALUES {', '.join(f'({i}, {U + a}, {U + b})' for i, (a, b) in enumerate(TOY_PAIRS, 1))})")


@query("toy_explanations", TOY_SQL)
def toy_explanations(spark, sf_dir):
    """All explanations of up to five nodes of three given pairs of users over three days of events; a small job that any engine can redo."""
    kb = build_kb(spark, sf_dir, "activity", ts_to=TOY_UNTIL).pinned()
    pairs = spark.createDataFrame([(i, U + a, U + b) for i, (a, b) in enumerate(TOY_PAIRS, 1)], "pair_id long, start long, end long")
    return _expl_rows(engine.enumerate_explanations(kb, pairs, 5))


@query("decorate_n3")
def decorate_n3(spark, sf_dir):
    kb, pairs, expl = _n3(spark, sf_dir, "lineage")
    top = R.rank_full(kb, pairs, expl, "monocount", 2)
    own = expl.instances.join(top.select("pair_id", "pattern_key"), ["pair_id", "pattern_key"], "left_semi")
    return render.decorate(own, kb, ["signup"])


@query("describe_n3")
def describe_n3(spark, sf_dir):
    kb, pairs, expl = _n3(spark, sf_dir, "lineage")
    return render.describe(R.rank_full(kb, pairs, expl, "monocount", 3), expl.instances, kb).withColumn("examples", F.array_join("examples", " | "))


_GAP = """SELECT k, user_id, ts, lag(user_id) OVER w AS before, lag(ts) OVER w AS then_ts FROM
    (SELECT CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS BIGINT) AS k, user_id, ts FROM events) WINDOW w AS (PARTITION BY k ORDER BY ts, user_id)"""


@query("op_session_pairs", f"""SELECT {U} + least(before, user_id) AS "start", {U} + greatest(before, user_id) AS "end", count(*) AS sessions FROM ({_GAP})
    WHERE before <> user_id AND ts <= then_ts + INTERVAL 30 MINUTE GROUP BY ALL""")
def op_session_pairs(spark, sf_dir):
    return session_pairs(load(spark, sf_dir, "events"))


@query("op_latest_event_before", """SELECT user_id, max(ts) AS last_ts, arg_max(event_type, (ts, event_id)) AS last_type FROM events WHERE ts < TIMESTAMP '2024-01-10' GROUP BY user_id""")
def op_latest_event_before(spark, sf_dir):
    """As-of: each user's last event before a point in time."""
    own = load(spark, sf_dir, "events").filter(F.col("ts") < F.lit("2024-01-10").cast("timestamp"))
    return own.groupBy("user_id").agg(F.max("ts").alias("last_ts"), F.max_by("event_type", F.struct("ts", "event_id")).alias("last_type"))


@query("op_label_cube", """SELECT coalesce(event_type, '*') AS event_type, coalesce(d, '*') AS d, count(*) AS n FROM (SELECT event_type, strftime(ts, '%Y-%m-%d') AS d FROM events) GROUP BY CUBE (event_type, d)""")
def op_label_cube(spark, sf_dir):
    own = load(spark, sf_dir, "events").withColumn("d", F.date_format("ts", "yyyy-MM-dd"))
    return own.cube("event_type", "d").agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("event_type", F.lit("*")).alias("event_type"), F.coalesce("d", F.lit("*")).alias("d"), "n")


@query("op_tail_positions", f"""WITH {_edges_sql(None)}, ends AS ({_ENDS} WHERE a.rel = 'purchase' AND b.rel = 'purchase' GROUP BY ALL), d AS (SELECT s, n AS value, count(*) AS n_pairs FROM ends GROUP BY ALL)
    SELECT s AS "start", value, n_pairs, coalesce(CAST(sum(n_pairs) OVER (PARTITION BY s ORDER BY value DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS BIGINT), 0) AS position FROM d""")
def op_tail_positions(spark, sf_dir):
    """The position of every value of every start's distribution at once, by a running tail sum."""
    kb, _ = _setting(spark, sf_dir, None)
    key = spark.createDataFrame([("0>purchase>2;1>purchase>2",)], "pattern_key string")
    dist = M.local_distribution(kb, key, kb.entities.filter("kind = 'user'").select(F.col("eid").alias("start")), by_twins=True)
    w = Window.partitionBy("start").orderBy(F.desc("value")).rowsBetween(Window.unboundedPreceding, -1)
    return dist.select("start", "value", "n_pairs", F.coalesce(F.sum("n_pairs").over(w), F.lit(0)).alias("position"))


@query("op_related_labels", f"WITH {_edges_sql(None)} SELECT src, list_aggregate(list_sort(list(DISTINCT rel)), 'string_agg', ',') AS labels FROM edges GROUP BY src HAVING count(DISTINCT rel) >= 2")
def op_related_labels(spark, sf_dir):
    own = build_kb(spark, sf_dir, "activity").edges
    return own.groupBy("src").agg(F.sort_array(F.collect_set("rel")).alias("l")).filter(F.size("l") >= 2).select("src", F.array_join("l", ",").alias("labels"))


# --- streams -------------------------------------------------------------------------------


def _name(sf_dir: str, tag: str) -> str:
    return tag + "_" + "".join(c if c.isalnum() else "_" for c in sf_dir)


@query("stream_edges", f"WITH {_edges_sql(None)} SELECT src, rel, dst FROM edges")
def stream_edges(spark, sf_dir):
    own = stream.stream_edges(stream.read_events(spark, f"{sf_dir}/events.parquet"), "60 days")
    return stream.drain(own.select("src", "rel", "dst"), _name(sf_dir, "stream_edges"))


@query("stream_label_counts", "SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_label_counts(spark, sf_dir):
    own = stream.label_counts(stream.read_events(spark, f"{sf_dir}/events.parquet"))
    return stream.drain(own, _name(sf_dir, "stream_labels"), "complete").select(F.col("w_start").cast("timestamp_ntz").alias("day"), "event_type", "n")


@query("stream_sliding_counts", """SELECT w AS w_start, event_type, count(*) AS n FROM (SELECT event_type, unnest([date_trunc('day', ts) - INTERVAL 1 DAY, date_trunc('day', ts)]) AS w FROM events) GROUP BY ALL""")
def stream_sliding_counts(spark, sf_dir):
    own = stream.label_counts(stream.read_events(spark, f"{sf_dir}/events.parquet"), "2 days", "1 day")
    return stream.drain(own, _name(sf_dir, "stream_sliding"), "complete").select(F.col("w_start").cast("timestamp_ntz").alias("w_start"), "event_type", "n")


@query("stream_sessions", """WITH e AS (SELECT CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS BIGINT) AS k, ts FROM events),
    g AS (SELECT k, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY k ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM e),
    n AS (SELECT k, ts, sum(fresh) OVER (PARTITION BY k ORDER BY ts ROWS UNBOUNDED PRECEDING) AS i FROM g)
    SELECT k, min(ts) AS w_start, count(*) AS n_events FROM n GROUP BY k, i""")
def stream_sessions(spark, sf_dir):
    own = stream.session_users(stream.read_events(spark, f"{sf_dir}/events.parquet"), "30 minutes")
    return stream.drain(own, _name(sf_dir, "stream_sessions"), "complete").select("k", F.col("w_start").cast("timestamp_ntz").alias("w_start"), "n_events")


@query("stream_co_occurrence", f"SELECT k, CAST(sum(CASE WHEN before <> user_id THEN 1 ELSE 0 END) AS BIGINT) AS changes FROM ({_GAP}) GROUP BY k")
def stream_co_occurrence(spark, sf_dir):
    own = stream.co_occurrence(stream.read_events(spark, f"{sf_dir}/events.parquet"))
    return stream.drain(own, _name(sf_dir, "stream_pairs"), "update").select("k", "changes")


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Top-10 by size, then monocount, for one user pair of the smallest activity graph."""
    kb = build_kb(spark, sf_dir, "activity", ts_to="2024-01-06").pinned()
    pairs = spark.createDataFrame([(1, U + 11, U + 4)], "pair_id long, start long, end long")
    expl = engine.enumerate_explanations(kb, pairs, 5)
    return R.rank_combined(kb, pairs, expl, ["size", "monocount"], 10)
