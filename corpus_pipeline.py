"""From raw documents to token identifiers in five stages, each one operator of ``linkwhy.llm``.

Every stage takes (spark, docs, sf_dir), works on all that the one before it kept, and
returns a DataFrame, which is written as Parquet and read again as the next one's docs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkwhy.llm import codec, decontaminate, langid, line_dedup, near_copies
from linkwhy.llm.common import crc_mod, scratch, settle_table, table


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the byte network can tell."""
    return langid.accepted(docs, langid.fit(docs, crc_mod("doc_id", 4) != 2))


def line_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Records of recurring templates are cut out of the texts; the first of each stays.  n_chars, where there is one, follows."""
    out = line_dedup.drop_recurring(docs)
    if "n_chars" not in docs.columns:
        return out
    return out.withColumn("n_chars", F.coalesce(F.length("text").cast(docs.schema["n_chars"].dataType), F.col("n_chars")))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of texts with a five-word shingle similarity of 0.8 or more."""
    return near_copies.one_of_each(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item, edited or not."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def bpe_codec(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids, and whether decoding gave the text back."""
    return codec.encode_documents(docs, verify=True).select("doc_id", "n_tokens", "ids", "round_trip")


STAGES = [
    ("language ID", language_id),
    ("line dedup", line_dedup_stage),
    ("SimHash near-dedup", near_dedup),
    ("benchmark decontamination", decontamination),
    ("BPE encoding and decoding", bpe_codec),
]

#: The trained network and the byte-pair codec have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the last stage.  What a stage settles for itself is deleted when its output is written."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        with scratch():
            docs = settle_table(stage(spark, docs, sf_dir), keep=True)
    return STAGES[-1][1](spark, docs, sf_dir)
