"""Knowledge graphs: profiles over tables, traversal steps, degrees, summary, store."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import load, text_key, tidy

#: Entity numbers are kind * KIND + key.
KIND = 10**15
#: Labels whose fan-out is kept; others count as cheap, which changes the order of joins and no result.
MOST_LABELS = 20_000
#: Labels and ways, and different sets of them at a node, up to which paths are pruned by what may follow what; no result depends on it.
MOST_WAYS, MOST_MASKS = 62, 20_000
#: A node with more than this share of all steps, and more than HUB_STEPS, is a hub; its steps lie in HUB_PLACES places.
HUB_SHARE, HUB_STEPS, HUB_PLACES = 1 / 1024, 200_000, 64
KINDS = {
    k: i + 1
    for i, k in enumerate(
        "user key customer nation segment supplier region order part brand type document lang source grade page host vector label conversation role".split()
    )
}


def eid(kind: str, key: Column, text: bool = False) -> Column:
    return F.lit(KINDS[kind] * KIND) + (text_key(key) if text else key.cast("long"))


@dataclass
class KnowledgeGraph:
    """entities(eid, kind, name) and edges(src, rel, dst, directed); steps and degrees follow."""

    entities: DataFrame
    edges: DataFrame
    cache: dict = field(default_factory=dict)

    @property
    def steps(self) -> DataFrame:
        """(u, rel, dir, v): each edge readable from either end; dir is 1 along, -1 against, 0 undirected."""
        if "steps" not in self.cache:
            along = F.when(F.col("directed"), F.lit(1)).otherwise(F.lit(0))
            there = self.edges.select(F.col("src").alias("u"), "rel", along.cast("int").alias("dir"), F.col("dst").alias("v"))
            back = self.edges.select(F.col("dst").alias("u"), "rel", (-along).cast("int").alias("dir"), F.col("src").alias("v"))
            self.cache["steps"] = there.unionByName(back)
        return self.cache["steps"]

    @property
    def degrees(self) -> DataFrame:
        return self.cache.get("degrees", self._degrees())

    def _degrees(self) -> DataFrame:
        return self.steps.groupBy(F.col("u").alias("eid")).agg(F.count(F.lit(1)).alias("degree"))

    @property
    def fan_out(self) -> dict[tuple[str, int], float]:
        """Mean number of neighbours by label and direction, which orders joins; one row for each label and way."""
        if "fan_out" not in self.cache:
            rows = self.steps.groupBy("rel", "dir").agg((F.count(F.lit(1)) / F.approx_count_distinct("u")).alias("mean")).limit(MOST_LABELS).collect()
            self.cache["fan_out"] = {(r["rel"], r["dir"]): r["mean"] for r in rows}
        return self.cache["fan_out"]

    @property
    def follow(self) -> dict[tuple[str, int], set[tuple[str, int]]] | None:
        """The labels and ways of steps that some node allows behind a step of each label and way; None if there are too many to list.

        One value a node, and of these the different ones only; on a pinned graph the steps do not move for it.
        """
        if "follow" not in self.cache:
            ways = sorted(self.fan_out)
            self.cache["follow"] = None
            if len(ways) <= MOST_WAYS:
                bit = reduce(lambda c, i: c.when((F.col("rel") == ways[i][0]) & (F.col("dir") == ways[i][1]), F.lit(1 << i)), range(len(ways)), F).otherwise(F.lit(0)) if ways else F.lit(0)
                masks = self.steps.groupBy("u").agg(F.bit_or(bit.cast("long")).alias("m")).select("m").distinct().limit(MOST_MASKS + 1).collect()
                if len(masks) <= MOST_MASKS:
                    found: dict[tuple[str, int], set[tuple[str, int]]] = {}
                    for mask in (r["m"] for r in masks):
                        out = [w for i, w in enumerate(ways) if mask >> i & 1]
                        for rel, way in out:
                            found.setdefault((rel, -way), set()).update(out)
                    self.cache["follow"] = found
        return self.cache["follow"]

    def reach(self, rows: DataFrame, tip: str, ways: set[tuple[str, int]] | None = None) -> DataFrame:
        """``rows`` joined to the steps that begin at their column ``tip``, to those of the given labels and ways only.

        On a pinned graph the steps are partitioned by their first node already, so only ``rows`` move.  The
        steps of hubs lie in several places, and rows at a hub go to each of them.
        """
        hubs = self.cache.get("hubs")
        known = F.lit(True) if ways is None else reduce(lambda c, w: c | ((F.col("rel") == w[0]) & (F.col("dir") == w[1])), sorted(ways), F.lit(False))
        if not hubs:
            steps = self.steps.filter(known)
            return rows.join(steps, rows[tip] == steps["u"])
        places = F.when(F.col(tip).isin(hubs), F.sequence(F.lit(0), F.lit(HUB_PLACES - 1))).otherwise(F.array(F.lit(0)))
        rows = rows.withColumn("__place", F.explode(places))
        dealt = self.cache["dealt"].filter(known)
        return rows.join(dealt, (rows[tip] == dealt["u"]) & (rows["__place"] == dealt["place"])).drop("__place", "place")

    def persist(self) -> KnowledgeGraph:
        """Keep the steps for the many joins of one run, partitioned by their first node."""
        if "kept" not in self.cache:
            self.cache["steps"] = self.steps.repartition("u").persist()
            self.cache["kept"] = True
        return self

    def pinned(self) -> KnowledgeGraph:
        """Edges, steps and degrees written to the shared folder once, for runs of many joins that must survive lost executors.

        Steps are partitioned and sorted by their first node; the checkpoint keeps that, so later joins on it do
        not move the graph.  Nodes with a large share of all steps (a number bounded by ``1 / HUB_SHARE``) are hubs.
        """
        from ..plans.runs import settle

        if "pinned" not in self.cache:
            self.edges = settle(self.edges)
            self.cache.pop("steps", None)
            n = int(self.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
            steps = self.steps
            self.cache["steps"] = _dealt(steps, n, "u")
            self.cache["degrees"] = settle(self._degrees())
            if self.cache.get("ends"):  # the entities are the ends of the edges: no second reading of the tables for them
                self.entities = _named(self.cache["degrees"].select("eid"))
            total = self.cache["degrees"].agg(F.sum("degree")).first()[0] or 0
            if total * HUB_SHARE > HUB_STEPS:
                self.cache["hubs"] = [r["eid"] for r in self.cache["degrees"].filter(F.col("degree") > total * HUB_SHARE).collect()]
                place = F.when(F.col("u").isin(self.cache["hubs"]), F.pmod(F.xxhash64("v"), F.lit(HUB_PLACES)).cast("int")).otherwise(0)
                self.cache["dealt"] = _dealt(steps.withColumn("place", place), n, "u", "place")
            self.cache["pinned"] = True
        return self

    def unpersist(self) -> None:
        if self.cache.pop("kept", None):
            self.cache.pop("steps").unpersist()

    def without_hubs(self, max_degree: int) -> KnowledgeGraph:
        """Drop edges at entities above a degree: an explicit approximation, off by default."""
        hubs = self.degrees.filter(F.col("degree") > max_degree).select("eid")
        edges = self.edges.join(hubs, self.edges["src"] == hubs["eid"], "left_anti")
        return KnowledgeGraph(self.entities, edges.join(hubs, edges["dst"] == hubs["eid"], "left_anti"))

    def restricted(self, allow: list[str] | None = None, deny: list[str] | None = None) -> KnowledgeGraph:
        """Only some relationship labels; the filter reaches the scans."""
        edges = self.edges
        edges = edges.filter(F.col("rel").isin(allow)) if allow else edges
        edges = edges.filter(~F.col("rel").isin(deny)) if deny else edges
        return KnowledgeGraph(self.entities, edges)

    def summary(self) -> DataFrame:
        """kind x label counts with subtotals: edges and different sources and targets."""
        kind = F.floor(F.col("src") / KIND).cast("int")
        return (
            self.edges.withColumn("kind", kind)
            .rollup("kind", "rel")
            .agg(F.count(F.lit(1)).alias("n_edges"), F.countDistinct("src").alias("n_src"), F.countDistinct("dst").alias("n_dst"))
            .select(F.coalesce("kind", F.lit(-1)).alias("kind"), F.coalesce("rel", F.lit("*")).alias("rel"), "n_edges", "n_src", "n_dst")
        )

    def register(self, prefix: str = "kb") -> None:
        """Views for SQL: <prefix>_edges as a relation of (eid1, eid2, rel), <prefix>_steps, <prefix>_entities."""
        self.edges.select(F.col("src").alias("eid1"), F.col("dst").alias("eid2"), "rel").createOrReplaceTempView(f"{prefix}_edges")
        self.steps.createOrReplaceTempView(f"{prefix}_steps")
        self.entities.createOrReplaceTempView(f"{prefix}_entities")

    def write(self, path: str, buckets: int = 64) -> None:
        """Store: edges by a bucket of the label, steps in sorted ranges of their first node."""
        self.entities.write.mode("overwrite").parquet(f"{path}/entities")
        self.edges.withColumn("rel_bucket", F.pmod(F.xxhash64("rel"), F.lit(buckets)).cast("int")).write.mode("overwrite").partitionBy("rel_bucket").parquet(f"{path}/edges")
        self.steps.repartitionByRange("u").sortWithinPartitions("u", "rel").write.mode("overwrite").parquet(f"{path}/steps")

    def save_tables(self, prefix: str, buckets: int = 64) -> None:
        """Bucketed tables: joins on the first node then need no shuffle of the graph."""
        self.steps.write.mode("overwrite").bucketBy(buckets, "u").sortBy("u", "rel").saveAsTable(f"{prefix}_steps")
        self.edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src", "rel").saveAsTable(f"{prefix}_edges")
        self.entities.write.mode("overwrite").saveAsTable(f"{prefix}_entities")

    @classmethod
    def read(cls, spark: SparkSession, path: str) -> KnowledgeGraph:
        kb = cls(spark.read.parquet(f"{path}/entities"), spark.read.parquet(f"{path}/edges").drop("rel_bucket"))
        kb.cache["steps"] = spark.read.parquet(f"{path}/steps")
        return kb


def _dealt(steps: DataFrame, n: int, *by: str) -> DataFrame:
    """Settled rows that keep their partitioning: an adaptive plan would not tell the checkpoint about it."""
    from ..plans.runs import settle

    conf = steps.sparkSession.conf
    adaptive = conf.get("spark.sql.adaptive.enabled")
    conf.set("spark.sql.adaptive.enabled", "false")
    try:
        return settle(steps.repartition(n, *by).sortWithinPartitions(*by))
    finally:
        conf.set("spark.sql.adaptive.enabled", adaptive)


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _rule(df: DataFrame, src: Column, rel: Column, dst: Column, directed: bool = True) -> DataFrame:
    return df.select(src.alias("src"), rel.alias("rel"), dst.alias("dst"), F.lit(directed).alias("directed"))


def _ends(edges: DataFrame) -> DataFrame:
    return _named(edges.select(F.explode(F.array("src", "dst")).alias("eid")).distinct())


def _named(both: DataFrame) -> DataFrame:
    names = F.create_map(*(x for k, i in KINDS.items() for x in (F.lit(i), F.lit(k))))
    kind = names[F.floor(F.col("eid") / KIND).cast("int")]
    return both.select("eid", kind.alias("kind"), F.concat_ws(":", kind, (F.col("eid") % KIND).cast("string")).alias("name"))


def activity(spark: SparkSession, sf_dir: str, ts_to: str | None = None, ts_from: str | None = None) -> KnowledgeGraph:
    """user -event type-> key of the event; several labels between the same two kinds."""
    ev = load(spark, sf_dir, "events", ("ts", "user_id", "event_type", "props"))
    ev = ev.filter(F.col("ts") < F.lit(ts_to).cast("timestamp")) if ts_to else ev
    ev = ev.filter(F.col("ts") >= F.lit(ts_from).cast("timestamp")) if ts_from else ev
    edges = tidy(_rule(ev, eid("user", F.col("user_id")), F.col("event_type"), eid("key", F.get_json_object("props", "$.k"))))
    return KnowledgeGraph(_ends(edges), edges, {"ends": True})


def commerce(spark: SparkSession, sf_dir: str, split_labels: bool = False) -> KnowledgeGraph:
    """Customers, orders, parts, suppliers and their attributes; ``split_labels`` adds attribute values to labels."""
    t = {n: load(spark, sf_dir, n) for n in ("customer", "supplier", "nation", "region", "orders", "lineitem", "part")}
    placed = F.concat(F.lit("placed:"), F.col("o_orderpriority"), F.lit(":"), F.year("o_orderdate")) if split_labels else F.lit("placed")
    contains = F.concat(F.lit("contains:"), F.col("l_returnflag")) if split_labels else F.lit("contains")
    customer, order, part, supplier = (lambda c, k=k: eid(k, F.col(c)) for k in ("customer", "order", "part", "supplier"))
    nation = lambda c: eid("nation", F.col(c))
    text = lambda kind, c: eid(kind, F.col(c), text=True)
    edges = [
        _rule(t["customer"], customer("c_custkey"), F.lit("lives_in"), nation("c_nationkey")),
        _rule(t["customer"], customer("c_custkey"), F.lit("in_segment"), text("segment", "c_mktsegment")),
        _rule(t["supplier"], supplier("s_suppkey"), F.lit("based_in"), nation("s_nationkey")),
        _rule(t["nation"], nation("n_nationkey"), F.lit("in_region"), eid("region", F.col("n_regionkey"))),
        _rule(t["orders"], customer("o_custkey"), placed, order("o_orderkey")),
        _rule(t["lineitem"], order("l_orderkey"), contains, part("l_partkey")),
        _rule(t["lineitem"], supplier("l_suppkey"), F.lit("fills"), order("l_orderkey")),
        _rule(t["part"], part("p_partkey"), F.lit("has_brand"), text("brand", "p_brand")),
        _rule(t["part"], part("p_partkey"), F.lit("has_type"), text("type", "p_type")),
    ]
    edges = tidy(_union(edges))
    return KnowledgeGraph(_ends(edges), edges, {"ends": True})


#: Vectors of one label that are held against as many others in one task.
VECTOR_BLOCK = 4096


def similar_pairs(vectors: DataFrame, least: float) -> DataFrame:
    """(a, b): all pairs of vectors of one label with a cosine of at least ``least``; null labels and vectors have none.

    A label is cut into blocks by a hash of the id; two blocks meet in one task, which
    multiplies them and gives only the similar pairs, so no pair of a label is ever a row before it is known to count.
    """
    own = vectors.select("vec_id", "label", F.col("embedding").cast("array<double>").alias("e")).dropna()
    sizes = own.groupBy("label").agg(F.ceil(F.count(F.lit(1)) / VECTOR_BLOCK).cast("int").alias("blocks"))
    own = own.join(F.broadcast(sizes) if sizes.limit(100_001).count() <= 100_000 else sizes, "label")
    own = own.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.col("blocks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    dealt = own.select("label", "vec_id", "e", "block", other).select("label", "vec_id", "e", "block", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"))

    def meet(key, frame):
        import numpy as np
        import pandas as pd

        if not len(frame):
            return pd.DataFrame({"a": [], "b": []})
        e = np.stack([np.asarray(x) for x in frame["e"]])
        ids, block = frame["vec_id"].to_numpy(), frame["block"].to_numpy()
        left = np.flatnonzero(block == key[1])
        right = np.flatnonzero(block == key[2])
        size = np.sqrt((e * e).sum(axis=1))
        found = []
        for at in range(0, len(left), 512):
            rows = left[at : at + 512]
            x, y = np.nonzero((e[rows] @ e[right].T >= least * size[rows, None] * size[right]) & (ids[rows, None] < ids[right] if key[1] == key[2] else True))
            found.append(np.stack([ids[rows[x]], ids[right[y]]], axis=1))
        found = np.concatenate(found) if found else np.zeros((0, 2), dtype=np.int64)
        return pd.DataFrame({"a": found.min(axis=1), "b": found.max(axis=1)})

    return dealt.groupBy("label", "i", "j").applyInPandas(meet, "a long, b long")


def content(spark: SparkSession, sf_dir: str, similar: float = 0.5) -> KnowledgeGraph:
    """Documents, pages, vectors, conversations and their attributes; near copies and similar vectors are undirected.

    Copies of one text are joined to the one with the smallest id, not to each other, so a
    large group gives as many edges as it has members.  All vectors of a label are compared, block by block.
    """
    t = {n: load(spark, sf_dir, n) for n in ("documents", "labels", "pages", "embeddings", "conversations")}
    doc = lambda c="doc_id": eid("document", F.col(c))
    copies = t["documents"].select("doc_id", F.sha2("text", 256).alias("h"))
    first = copies.groupBy("h").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    copies = copies.join(first, "h").filter("doc_id <> first")
    host = F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1)
    near = similar_pairs(t["embeddings"], similar)
    edges = [
        _rule(t["documents"], doc(), F.lit("in_lang"), eid("lang", F.col("lang"), text=True)),
        _rule(t["documents"], doc(), F.lit("from_source"), eid("source", F.col("source"), text=True)),
        _rule(t["labels"], doc(), F.lit("graded"), eid("grade", F.col("quality"))),
        _rule(copies, doc(), F.lit("near_copy"), doc("first"), directed=False),
        _rule(t["pages"], eid("page", F.col("page_id")), F.lit("hosted_by"), F.lit(KINDS["host"] * KIND) + text_key(host)),
        _rule(t["embeddings"], eid("vector", F.col("vec_id")), F.lit("labelled"), eid("label", F.col("label"))),
        _rule(near, eid("vector", F.col("a")), F.lit("similar"), eid("vector", F.col("b")), directed=False),
        _rule(t["conversations"], eid("conversation", F.col("conv_id")), F.lit("has_role"), eid("role", F.col("role"), text=True)),
    ]
    edges = tidy(_union(edges))
    return KnowledgeGraph(_ends(edges), edges, {"ends": True})


#: A small graph with the shapes of the usual worked examples, in names of our own.
TOY = {
    "acts": "ann>f1 ann>f2 ann>f4 bob>f1 bob>f3 cy>f1 cy>f2 cy>f3 dee>f2 dee>f4",
    "makes": "ann>f1",
    "directs": "xia>f2 xia>f3 xia>f4 yul>f1",
    "mentors": "xia>bob",
    "in_guild": "dee>g1",
    "married": "ann~bob",
}


def toy_ids() -> dict[str, int]:
    names = sorted({n for pairs in TOY.values() for p in pairs.split() for n in p.replace("~", ">").split(">")})
    return {n: i + 1 for i, n in enumerate(names)}


def toy(spark: SparkSession, sf_dir: str | None = None) -> KnowledgeGraph:
    ids = toy_ids()
    rows = [(ids[a], rel, ids[b], "~" not in p) for rel, pairs in TOY.items() for p in pairs.split() for a, b in [p.replace("~", ">").split(">")]]
    edges = tidy(spark.createDataFrame(rows, "src long, rel string, dst long, directed boolean"))
    entities = spark.createDataFrame([(i, "toy", n) for n, i in ids.items()], "eid long, kind string, name string")
    return KnowledgeGraph(entities, edges)


PROFILES: dict[str, Callable[..., KnowledgeGraph]] = {"activity": activity, "commerce": commerce, "content": content, "toy": toy}


def build_kb(spark: SparkSession, sf_dir: str, profile: str, **params) -> KnowledgeGraph:
    return PROFILES[profile](spark, sf_dir, **params)
