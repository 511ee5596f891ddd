"""The registered queries ``opN_<name>``: each operator over its whole table, with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import codec, decontaminate, exact_dedup, langid, line_dedup, ngram_lm, secret_scan, simhash, token_count, toxicity
from .common import crc_mod, table

#: Categories of the given labels in chain order.
CATEGORIES = {"low_quality": "quality = 0", "toxic": "toxic = 1"}


def op1_token_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_count.count_tokens(table(spark, sf_dir, "documents"))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").withColumn("held_out", crc_mod("doc_id", 4) == 2)
    return langid.predict(docs, langid.fit(docs, ~F.col("held_out")), keep=("held_out",))


def op3_ngram_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").withColumn("held_out", crc_mod("doc_id", 5) == 1)
    return ngram_lm.score(docs, ngram_lm.fit(docs, ~F.col("held_out")), keep=("held_out",))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.drop_recurring(table(spark, sf_dir, "documents"), report=True)


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    chain = toxicity.fit(docs, table(spark, sf_dir, "labels"), CATEGORIES)
    return toxicity.predict(docs, chain, tuple(CATEGORIES))


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op7_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_classes(table(spark, sf_dir, "documents"))


def op8_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return codec.encode_documents(table(spark, sf_dir, "documents"), digests=True)


def op9_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan_documents(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_token_count, op2_language_id, op3_ngram_lm, op4_line_dedup, op5_toxicity, op6_simhash, op7_exact_dedup, op8_bpe_codec, op9_decontaminate, op10_secret_scan)}
ORACLES: dict[str, str] = {"op7_exact_dedup": exact_dedup.ORACLE}
