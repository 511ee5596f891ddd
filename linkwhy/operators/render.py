"""For the reader: decoration with attributes, and text with sample instances."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.kb import KnowledgeGraph


def decorate(instances: DataFrame, kb: KnowledgeGraph, rels: list[str]) -> DataFrame:
    """(pair_id, pattern_key, place, entity, rel, value): attribute edges at the bound entities of chosen patterns.

    Such edges are not essential to a pattern; they are attached afterwards, and entities
    without them keep a row with nulls.
    """
    at = instances.select("pair_id", "pattern_key", F.posexplode("binding").alias("place", "entity")).distinct()
    near = kb.steps.filter(F.col("rel").isin(rels)).select(F.col("u").alias("entity"), "rel", F.col("v").alias("value"))
    return at.join(near, "entity", "left").select("pair_id", "pattern_key", (F.col("place") + 2).alias("place"), "entity", "rel", "value")


def describe(ranked: DataFrame, instances: DataFrame, kb: KnowledgeGraph, examples: int = 3) -> DataFrame:
    """(pair_id, rank, pattern_key, examples): the chosen patterns with a few instances by name."""
    own = instances.join(ranked.select("pair_id", "pattern_key"), ["pair_id", "pattern_key"], "left_semi")
    few = own.withColumn("r", F.row_number().over(Window.partitionBy("pair_id", "pattern_key").orderBy("binding"))).filter(F.col("r") <= examples)
    named = few.select("pair_id", "pattern_key", "r", F.posexplode_outer("binding").alias("place", "eid")).join(kb.entities.select("eid", "name"), "eid", "left")
    line = named.groupBy("pair_id", "pattern_key", "r").agg(F.concat_ws(", ", F.transform(F.array_sort(F.collect_list(F.struct("place", "name"))), lambda s: F.concat((s["place"] + 2).cast("string"), F.lit("="), F.coalesce(s["name"], F.lit("?"))))).alias("line"))
    text = line.groupBy("pair_id", "pattern_key").agg(F.transform(F.array_sort(F.collect_list(F.struct("r", "line"))), lambda s: s["line"]).alias("examples"))
    return ranked.join(text, ["pair_id", "pattern_key"], "left").select("pair_id", "rank", "pattern_key", "examples")
