"""Operator 7: exact deduplication by skew-safe combining (DataFrame functions only)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_or_empty

#: A group of equal texts meets in this many salted parts before they are combined.
SALTS = 32


def salt_of(id_col: str, salts: int) -> Column:
    return F.pmod(F.xxhash64(F.col(id_col)), F.lit(salts)).cast("int")


def exact_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", salts: int = SALTS) -> DataFrame:
    """One row per document: id, keep_id, group_size, kept, text_sha256.

    Three stages, each grouping by the digest and the full text, so that equal digests of
    different texts never meet: (1) within a scan task (the partial aggregate), (2) the
    salted groups, (3) the winners of the salts.  A group holding a third of all rows
    reaches stage 3 as ``salts`` rows.  Documents then learn their class by digest, a second
    digest, length and salt; a class row is repeated only for salts that its group has.

    Null counts as the empty text, which is a text like others.  The largest id of a group
    stays; null ids lose to any other, and a group of null ids alone keeps null.  Rows
    repeated with one id count each in ``group_size`` and share ``kept``.  An empty table
    gives no rows; other columns are not read.
    """
    base = docs.select(
        F.col(id_col).alias("__id"),
        text_or_empty(text_col).alias("__text"),
        salt_of(id_col, salts).alias("__salt"),
    ).withColumns({"__sha": F.sha2(F.col("__text").cast("binary"), 256), "__xx": F.xxhash64("__text"), "__len": F.length("__text")})
    salted = base.groupBy("__sha", "__salt", "__text").agg(F.max("__id").alias("__keep"), F.count(F.lit(1)).alias("__n"))
    classes = (
        salted.groupBy("__sha", "__text")
        .agg(F.max("__keep").alias("keep_id"), F.sum("__n").alias("group_size"), F.collect_set("__salt").alias("__salts"))
        .select("__sha", F.xxhash64("__text").alias("__xx"), F.length("__text").alias("__len"), "keep_id", "group_size", F.explode("__salts").alias("__salt"))
    )
    return (
        base.drop("__text")
        .join(classes, ["__sha", "__xx", "__len", "__salt"])
        .select(
            F.col("__id").alias(id_col),
            "keep_id",
            "group_size",
            F.col("__id").eqNullSafe(F.col("keep_id")).alias("kept"),
            F.col("__sha").alias("text_sha256"),
        )
    )


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", salts: int = SALTS) -> DataFrame:
    """The documents that stay, with all their columns.

    A row stays if its id *and* its text are those of a class's winner, so one id with two texts is two
    documents.  Rows repeated with one id and text all stay; a null id stays only where its class has no other.
    """
    kept = exact_classes(docs, id_col, text_col, salts).filter("kept").select(F.col(id_col).alias("__keep"), F.col("text_sha256").alias("__kept_sha")).distinct()
    own = F.sha2(text_or_empty(text_col).cast("binary"), 256)
    return docs.join(kept, docs[id_col].eqNullSafe(kept["__keep"]) & (own == kept["__kept_sha"]), "left_semi")


ORACLE = """
SELECT doc_id,
       max(doc_id) OVER (PARTITION BY coalesce(text, '')) AS keep_id,
       count(*) OVER (PARTITION BY coalesce(text, '')) AS group_size,
       doc_id IS NOT DISTINCT FROM max(doc_id) OVER (PARTITION BY coalesce(text, '')) AS kept,
       sha256(coalesce(text, '')) AS text_sha256
FROM documents
"""
