"""Operator 6: SimHash near-duplicates by covering locality-sensitive hashing."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import settle, tidy
from .components import connected_components

SALTS = 16
#: Buckets up to this size are compared pair by pair; larger ones by shared centres (see ``links``).
PAIRWISE = 96


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """64-bit SimHash over word shingles (unsigned)."""
    import numpy as np
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    digest = xxhash.xxh64_intdigest
    whole = b" ".join(words)
    if len(words) <= shingle:
        return digest(whole, 42)
    sizes = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
    ends = np.cumsum(sizes + 1) - 1
    starts = (ends - sizes)[: len(words) - shingle + 1].tolist()
    ends = ends[shingle - 1 :].tolist()
    counts, n = np.zeros(64, dtype=np.int64), len(starts)
    for at in range(0, n, 1 << 14):  # bounded memory for very long texts
        hashes = [digest(whole[a:b], 42) for a, b in zip(starts[at : at + (1 << 14)], ends[at : at + (1 << 14)], strict=True)]
        planes = np.array(hashes, dtype=">u8").view(np.uint8).reshape(-1, 8)
        counts += np.unpackbits(planes, axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * counts > n).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, keep: str | None = None) -> DataFrame:
    """(id, th, fp): the fingerprint as a signed long; null and empty texts have zero.  th: the long column ``keep``."""
    base = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), (F.col(keep) if keep else F.lit(0).cast("long")).alias("th"))

    def run(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            found = np.fromiter((fingerprint(t.as_py(), shingle) for t in batch.column(1)), dtype=np.uint64, count=batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(found.view(np.int64))], names=["id", "th", "fp"])

    return base.mapInArrow(tidy(run), f"id {base.schema['id'].dataType.simpleString()}, th long, fp long")


def covering_masks(radius: int, bits: int = 64) -> list[int]:
    """Masks of which at least one misses any ``radius`` bit positions.

    Bit i gets a non-zero vector of radius + 1 bits; mask v keeps the bits whose vector
    has odd overlap with v.  Any ``radius`` vectors are orthogonal to some non-zero v, so
    two words that differ in at most ``radius`` bits agree under that mask.
    """
    n = (1 << (radius + 1)) - 1
    return [sum(1 << i for i in range(bits) if bin((i % n + 1) & v).count("1") % 2) for v in range(1, n + 1)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def links(fps: DataFrame, radius: int = 3, pairwise: int = PAIRWISE) -> DataFrame:
    """Edges (a, b) that connect all fingerprints within ``radius`` bits of each other, and no others.

    ``fps`` has distinct values in column fp.  Small buckets are compared pair by pair.
    In a larger bucket every fingerprint is sent to all words within ceil(radius / 2) bits
    of it (over the bits that the mask leaves free), and those within floor(radius / 2)
    bits found a centre there: whoever meets at a centre is linked to its smallest founder
    or, with odd radius, through it.  That costs a fixed number of rows for each member
    instead of all pairs, and connects the same fingerprints.
    """
    masks = covering_masks(radius)
    keyed = fps.select(
        "fp",
        F.explode(F.array(*(F.struct(F.lit(v).alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("key")) for v, m in enumerate(masks)))).alias("x"),
    ).select("fp", "x.t", "x.key")
    sizes = keyed.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    members = settle(keyed.join(sizes, ["t", "key"]))
    few = members.filter(F.col("n") <= pairwise).select("t", "key", "fp")
    near = F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= radius
    pairs = few.withColumnRenamed("fp", "a").join(few.withColumnRenamed("fp", "b"), ["t", "key"]).filter("a > b").filter(near).select("a", "b")
    many = members.filter(F.col("n") > pairwise).select("t", "fp")
    return pairs.unionByName(_by_centres(many, masks, radius)).distinct()


def _by_centres(many: DataFrame, masks: list[int], radius: int) -> DataFrame:
    """Links inside large buckets; see ``links``."""
    inner, outer = radius // 2, radius - radius // 2
    free = F.element_at(F.array(*(F.array(*(F.lit(_signed(1 << i)) for i in range(64) if not m >> i & 1)) for m in masks)), F.col("t") + 1)
    flips = F.array(F.struct(F.lit(0).cast("long").alias("flip"), F.lit(-1).alias("at"), F.lit(0).alias("d")))
    reach = many.withColumns({"free": free, "x": flips})
    for _ in range(outer):
        grown = F.flatten(F.transform(
            F.col("x"),
            lambda s: F.concat(
                F.array(s),
                F.filter(
                    F.transform(F.col("free"), lambda bit, i: F.struct(s["flip"].bitwiseXOR(bit).alias("flip"), i.cast("int").alias("at"), (s["d"] + 1).alias("d"))),
                    lambda c: c["at"] > s["at"],
                ),
            ),
        ))
        reach = reach.withColumn("x", F.array_distinct(grown))
    met = reach.select("t", "fp", F.explode("x").alias("x")).select("t", "fp", F.col("fp").bitwiseXOR(F.col("x.flip")).alias("centre"), F.col("x.d").alias("d"))
    founders = met.filter(F.col("d") <= inner).groupBy("t", "centre").agg(F.min("fp").alias("b"))
    return met.join(founders, ["t", "centre"]).filter("fp <> b").select(F.col("fp").alias("a"), "b")


def _named(docs: DataFrame, id_col: str, text_col: str, shingle: int, radius: int, salts: int) -> DataFrame:
    """(id, th, fp, root, component_id): each document with the smallest fingerprint and id of its component."""
    base = docs.select(F.col(id_col).alias("__id"), F.col(text_col).alias("__text"))
    prints = fingerprints(base.withColumn("__th", F.xxhash64("__text")), "__id", "__text", shingle, keep="__th")
    prints = settle(prints.withColumn("salt", F.pmod(F.xxhash64("id", "th"), F.lit(salts)).cast("int")))
    nodes = settle(prints.groupBy("fp", "salt").agg(F.min("id").alias("least")).groupBy("fp").agg(F.min("least").alias("least"), F.collect_set("salt").alias("salts")))
    roots = connected_components(links(nodes.select("fp"), radius))
    placed = nodes.join(roots, nodes["fp"] == roots["node"], "left").select("fp", "least", "salts", F.coalesce("root", "fp").alias("root"))
    ids = placed.groupBy("root").agg(F.min("least").alias("component_id"))
    named = placed.join(ids, "root").select("fp", "root", "component_id", F.explode("salts").alias("salt"))
    return prints.join(named, ["fp", "salt"])


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, radius: int = 3, salts: int = SALTS) -> DataFrame:
    """One row per document: id, fingerprint (16 hex digits), component_id (smallest id reachable).

    Null and empty texts have fingerprint zero and link like others.  Repeated rows each give
    a row; null ids form no component id of their own (the smallest non-null id of the
    component, or null).  An empty table gives no rows.  Equal fingerprints are one node, so
    copies cost nothing in the search; a fingerprint of a third of all rows is joined back
    in salted parts.  The covering masks lose no pair within the radius.
    """
    return _named(docs, id_col, text_col, shingle, radius, salts).select(
        F.col("id").alias(id_col),
        F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"),
        "component_id",
    )


def one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, radius: int = 3, salts: int = SALTS) -> DataFrame:
    """One document of each component, the one with the smallest id (null ids last), all columns kept.

    Documents without words form one component like others.  Rows repeated with one id and
    text are one document, of which one row stays.
    """
    named = settle(_named(docs, id_col, text_col, shingle, radius, salts).select("id", "th", "root"))
    first = named.groupBy("root").agg(F.min(F.struct(F.col("id").isNull().alias("no"), "id", "th")).alias("k"))
    kept = first.select(F.col("k.id").alias("__id"), F.col("k.th").alias("__th"))
    out = docs.withColumn("__h", F.xxhash64(text_col))
    out = out.join(kept, out[id_col].eqNullSafe(kept["__id"]) & (out["__h"] == kept["__th"]), "left_semi")
    repeated = named.groupBy("id", "th").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    if not repeated.isEmpty():
        out = out.dropDuplicates([id_col, "__h"])
    return out.select(*docs.columns)
