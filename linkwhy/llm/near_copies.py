"""Operator 6 for the corpus pipeline: near copies by exact similarity of five-word shingles.

The covering masks of ``simhash`` find every pair whose fingerprints differ in up to three
bits.  Texts with a similarity of 0.8 differ in ten of 64 bits on average and in up to 20,
which would take 2**21 - 1 masks; so a second source of candidates, bands of minimum hashes,
stands beside the masks here.  Every candidate is verified on its whole set of shingles.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import blocks, document_words, joined, join_unique, settle_table, tidy
from .components import connected_components
from .simhash import links

#: Pairs of one set that are verified in one place.
SHARE = 64


@dataclass(frozen=True)
class Rules:
    """shingle: words of a shingle.  similarity: least Jaccard similarity of near copies.
    radius: bits that the covering masks bridge.  bands, rows: minimum hashes are compared in so
    many bands of so many; two texts of similarity s share no band with probability
    (1 - s**rows)**bands, 3e-6 at 0.8.  stars: rounds in which a text is held against one centre."""

    shingle: int = 5
    similarity: float = 0.8
    radius: int = 3
    bands: int = 24
    rows: int = 4
    stars: int = 2


def shingle_sets(texts: list[str | None], shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the word shingles of all texts and where each text begins (n + 1 offsets); a shorter text is one shingle."""
    words, at = document_words(texts)
    sizes = np.diff(at)
    count = np.where(sizes >= shingle, sizes - shingle + 1, np.minimum(sizes, 1))
    to = np.concatenate([[0], np.cumsum(count)])
    out = np.zeros(to[-1], dtype=np.uint64)
    if len(words) >= shingle:
        every = joined([words[i : len(words) - shingle + 1 + i] for i in range(shingle)])
        long = np.repeat(sizes >= shingle, count)
        place = np.repeat(at[:-1] - to[:-1], count) + np.arange(to[-1])
        out[long] = every[place[long]]
    for k in np.flatnonzero((sizes > 0) & (sizes < shingle)):
        out[to[k]] = joined([words[i : i + 1] for i in range(at[k], at[k + 1])])[0]
    return out, to


def _bands(hashes: np.ndarray, to: np.ndarray, rules: Rules) -> np.ndarray:
    """One key a band for each text that has shingles; the number of the band is part of the key."""
    begin = to[:-1][np.diff(to) > 0]
    turns = np.random.default_rng(1).integers(0, 1 << 63, rules.bands * rules.rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    least = [np.minimum.reduceat(hashes * a, begin) for a in turns] if len(begin) else [hashes[:0] for _ in turns]
    return np.stack([joined([*least[b * rules.rows : (b + 1) * rules.rows], np.full(len(begin), b, np.uint64)]) for b in range(rules.bands)], axis=1)


def sim_prints(hashes: np.ndarray, to: np.ndarray) -> np.ndarray:
    """64-bit SimHash of each text over its shingle hashes, repeats included; zero without shingles."""
    out = np.zeros(len(to) - 1, dtype=np.uint64)
    some = np.flatnonzero(np.diff(to) > 0)
    if len(some):
        counts = np.zeros((len(out), 64), dtype=np.int64)
        for at in range(0, len(hashes), 1 << 17):  # bounded memory for very long texts
            part = hashes[at : at + (1 << 17)]
            of = np.searchsorted(to, np.arange(at, at + len(part)), side="right") - 1
            begin = np.flatnonzero(np.r_[True, np.diff(of) != 0])
            bits = np.unpackbits(part.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
            counts[of[begin]] += np.add.reduceat(bits, begin, axis=0, dtype=np.int32)
        half = 2 * counts[some] > np.diff(to)[some, None]
        out[some] = np.packbits(half, axis=1).view(">u8").ravel()
    return out


def _prints(base: DataFrame, rules: Rules) -> DataFrame:
    """(id, th, fp, sim, bands): fp is a hash of the set of shingles; texts without words have fp zero and no bands."""

    def run(batches):
        import pyarrow as pa
        import xxhash

        for part in blocks(batches, "text"):
            hashes, to = shingle_sets(part.column(1).to_pylist(), rules.shingle)
            some = np.diff(to) > 0
            fp = np.zeros(len(some), dtype=np.uint64)
            for k in np.flatnonzero(some):
                fp[k] = xxhash.xxh64_intdigest(np.unique(hashes[to[k] : to[k + 1]]).tobytes(), 42)
            keys = _bands(hashes, to, rules).ravel().view(np.int64)
            ends = np.concatenate([[0], np.cumsum(some * rules.bands)]).astype(np.int32)
            columns = [part.column(0), part.column(2), pa.array(fp.view(np.int64)), pa.array(sim_prints(hashes, to).view(np.int64)), pa.ListArray.from_arrays(pa.array(ends), pa.array(keys))]
            yield pa.RecordBatch.from_arrays(columns, names=["id", "th", "fp", "sim", "bands"])

    return base.mapInArrow(tidy(run), f"id {base.schema['id'].dataType.simpleString()}, th long, fp long, sim long, bands array<long>")


def _sets(texts: DataFrame, rules: Rules) -> DataFrame:
    """(fp, shingles) of rows (fp, text)."""

    def run(batches):
        import pyarrow as pa

        for part in blocks(batches, "text"):
            hashes, to = shingle_sets(part.column(1).to_pylist(), rules.shingle)
            sets = [np.unique(hashes[a:b]).view(np.int64) for a, b in zip(to[:-1], to[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sets, pa.list_(pa.int64()))], names=["fp", "shingles"])

    return texts.mapInArrow(tidy(run), "fp long, shingles array<long>")


def _with_sets(pairs: DataFrame, sets: DataFrame, side: str, other: str, name: str) -> DataFrame:
    """The pairs with the set of one side; only sets of more than ``SHARE`` pairs are sent to several places."""
    parts = pairs.groupBy(side).agg((F.floor(F.count(F.lit(1)) / SHARE) + 1).cast("int").alias("parts"))
    many = sets.select(F.col("fp").alias(side), F.col("shingles").alias(name)).join(parts, side)
    many = many.withColumn("__part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts")
    own = join_unique(pairs, parts, [side], [other]).withColumn("__part", F.pmod(F.xxhash64(other), F.col("parts")).cast("int")).drop("parts")
    return own.join(many, [side, "__part"]).drop("__part")


def _similar(pairs: DataFrame, sets: DataFrame, rules: Rules) -> DataFrame:
    """The pairs (a, b) whose sets of shingles are similar enough."""
    own = _with_sets(_with_sets(pairs, sets, "b", "a", "y"), sets, "a", "b", "x")
    both = F.size(F.array_intersect("x", "y"))
    return settle_table(own.filter(both / (F.size("x") + F.size("y") - both) >= rules.similarity).select("a", "b"))


def _by_masks(nodes: DataFrame, rules: Rules) -> DataFrame:
    """Candidates (a, b) whose fingerprints are within the radius; equal fingerprints meet at their smallest node."""
    least = settle_table(nodes.groupBy("sim").agg(F.min("fp").alias("b"), F.count(F.lit(1)).alias("n")))
    same = join_unique(nodes.select("sim", "fp"), least.filter("n > 1").drop("n"), ["sim"], ["fp"]).filter("fp <> b").select(F.col("fp").alias("a"), "b")
    near = links(least.select(F.col("sim").alias("fp")), rules.radius)
    name = least.select("sim", F.col("b").alias("fp"))
    near = near.join(name.select(F.col("sim").alias("a"), F.col("fp").alias("x")), "a").join(name.select(F.col("sim").alias("b"), F.col("fp").alias("y")), "b")
    return same.unionByName(near.select(F.col("x").alias("a"), F.col("y").alias("b")))


def _open(members: DataFrame, found: DataFrame) -> DataFrame:
    """The members of those buckets that hold several components: (key, fp, score, root)."""
    placed = members.join(found, members["fp"] == found["node"], "left").select("key", "fp", "score", F.coalesce("root", "fp").alias("root"))
    parted = placed.groupBy("key").agg(F.min("root").alias("r"), F.max("root").alias("s")).filter("r <> s").select("key")
    return settle_table(join_unique(placed, parted, ["key"], ["fp"]))


def _grown(found: DataFrame | None, edges: DataFrame) -> DataFrame:
    """Components (node, root) of those found so far and more edges; what was found goes in as stars."""
    if found is not None:
        edges = edges.unionByName(found.select(F.col("node").alias("a"), F.col("root").alias("b")))
    return connected_components(edges)


def _centres(open_: DataFrame) -> DataFrame:
    """One candidate (a, b) for each node: the best-connected node of another component that it shares a bucket with."""
    heads = open_.groupBy("key", "root").agg(F.max(F.struct("score", "fp")).alias("head"))
    first = heads.groupBy("key").agg(F.max(F.struct("head", "root")).alias("f"))
    second = heads.join(first, "key").filter(F.col("root") != F.col("f.root")).groupBy("key").agg(F.max("head").alias("s"))
    tops = first.join(second, "key").select("key", "f", "s")
    met = join_unique(open_, tops, ["key"], ["fp"])
    centre = F.when(F.col("f.root") != F.col("root"), F.col("f.head")).otherwise(F.col("s"))
    return met.groupBy("fp").agg(F.max(centre).alias("c")).select(F.col("fp").alias("a"), F.col("c.fp").alias("b"))


def _by_prefix(open_: DataFrame, sets: DataFrame, rules: Rules) -> DataFrame:
    """Candidates (a, b) of different components in open buckets; none that could be similar is left out.

    Two sets can only share shingles that both components have.  With the shingles of a set in
    one order, those without a partner first and then by rising frequency, two sets that
    are similar enough share a shingle in the first (1 - similarity) of each, at places
    that leave room for the overlap they need.  So texts that only share a passage, and
    copies with many changes of their own, give no pair.
    """
    s = rules.similarity
    nodes = open_.select("fp", "root").distinct()
    tokens = settle_table(nodes.join(sets, "fp").select("fp", "root", F.size("shingles").alias("size"), F.explode("shingles").alias("token")))
    kinds = tokens.groupBy("token").agg(F.count(F.lit(1)).alias("df"), F.min("root").alias("r"), F.max("root").alias("t")).filter("r <> t").select("token", "df")
    shared = join_unique(tokens, kinds, ["token"], ["fp"])
    rows = shared.groupBy("fp", "root", "size").agg(F.sort_array(F.collect_list(F.struct("df", "token"))).alias("own"))
    alone = F.col("size") - F.size("own")
    slots = (F.col("size") - F.ceil(F.col("size") * s - 1e-9) + 1 - alone).cast("int")
    rows = rows.withColumn("alone", alone).withColumn("slots", slots).filter("slots > 0")
    heads = settle_table(rows.select("fp", "root", "size", "alone", F.posexplode(F.slice("own", F.lit(1), F.col("slots"))).alias("i", "t")).select("fp", "root", "size", (F.col("alone") + F.col("i")).alias("at"), "t.token"))
    x = heads.select("token", F.col("fp").alias("a"), F.col("root").alias("ra"), F.col("size").alias("na"), F.col("at").alias("ia"))
    y = heads.select("token", F.col("fp").alias("b"), F.col("root").alias("rb"), F.col("size").alias("nb"), F.col("at").alias("ib"))
    room = F.least(F.col("na") - F.col("ia"), F.col("nb") - F.col("ib")) >= (F.col("na") + F.col("nb")) * (s / (1 + s)) - 1e-6
    sizes = F.least("na", "nb") >= F.greatest("na", "nb") * s - 1e-9
    return x.join(y, "token").filter((F.col("a") > F.col("b")) & (F.col("ra") != F.col("rb")) & sizes & room).select("a", "b").distinct()


def one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: Rules = Rules()) -> DataFrame:
    """One document of each component of near copies, the one with the smallest id (null ids last), all columns kept.

    Texts with one set of shingles are one node.  A node is first held against its nearest
    fingerprints and against one well-connected node of its buckets, so that a large group
    of close copies costs a row a member; what is left apart in a bucket is compared by the
    prefixes of its sets.  All pairs of a bucket are settled.  Null and empty texts and texts without words
    form one component.  Rows repeated with one id and text are one document, of which one
    row stays.  An empty table gives no rows.
    """
    base = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).withColumn("th", F.xxhash64("text"))
    prints = settle_table(_prints(base, rules))
    nodes = settle_table(prints.groupBy("fp").agg(F.min(F.struct(F.col("id").isNull().alias("no"), "id", "th")).alias("k"), F.first("sim").alias("sim"), F.first("bands").alias("bands")))
    masked = settle_table(_by_masks(nodes.filter(F.size("bands") > 0).select("fp", "sim"), rules))

    keyed = nodes.select("fp", F.explode("bands").alias("key"))
    sizes = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    score = F.sum("n").over(Window.partitionBy("fp"))  # a row a band at most
    members = settle_table(join_unique(keyed, sizes, ["key"], ["fp"]).select("key", "fp", score.alias("score")))

    wanted = members.select("fp").unionByName(masked.select(F.explode(F.array("a", "b")).alias("fp"))).distinct()
    wanted = wanted.join(nodes, "fp").select("fp", F.col("k.id").alias("__id"), F.col("k.th").alias("__th"))
    texts = base.join(wanted, base["id"].eqNullSafe(wanted["__id"]) & (base["th"] == wanted["__th"])).select("fp", "text")
    sets = settle_table(_sets(texts, rules).dropDuplicates(["fp"]))

    open_ = members.withColumn("root", F.col("fp"))
    close, found = masked.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")), None
    for turn in range(rules.stars):
        near = _centres(open_) if turn else _centres(open_).unionByName(close)
        found = _grown(found, _similar(settle_table(near.distinct()), sets, rules))
        open_ = _open(members, found)
    roots = _grown(found, _similar(settle_table(_by_prefix(open_, sets, rules)), sets, rules))

    named = nodes.join(roots, nodes["fp"] == roots["node"], "left").select(F.coalesce("root", "fp").alias("root"), "k")
    kept = named.groupBy("root").agg(F.min("k").alias("k")).select(F.col("k.id").alias("__id"), F.col("k.th").alias("__th"))
    out = docs.withColumn("__h", F.xxhash64(text_col))
    out = out.join(kept, out[id_col].eqNullSafe(kept["__id"]) & (out["__h"] == kept["__th"]), "left_semi")
    repeated = prints.groupBy("id", "th").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    if not repeated.isEmpty():
        out = out.dropDuplicates([id_col, "__h"])
    return out.select(*docs.columns)
