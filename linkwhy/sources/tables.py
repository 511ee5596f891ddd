"""Reading the given tables and edge lists of other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def load(spark: SparkSession, sf_dir: str, name: str, need: tuple[str, ...] = ()) -> DataFrame:
    """A given table; fails early if a needed column is missing."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    missing = set(need) - set(df.columns)
    if missing:
        raise ValueError(f"{name} lacks {sorted(missing)}")
    return df


EDGE_FIELDS = ("src", "rel", "dst", "directed")


def read_edges(spark: SparkSession, path: str, format: str = "csv", mapping: dict[str, str] | None = None, sep: str = ",", directed: bool = True) -> DataFrame:
    """Edges from delimited text, JSON lines, Parquet or ``subject predicate object`` text.

    ``mapping`` names the columns that hold src, rel, dst (and directed).  Identifiers that
    are no integers become 48-bit numbers of their text, as everywhere in the engine.
    """
    if format == "triples":
        part = F.split(F.trim("value"), r"\s+")
        raw = spark.read.text(path).select(*(F.get(part, i).alias(c) for i, c in enumerate(("src", "rel", "dst"))))  # shorter lines are no edges
    elif format == "csv":
        raw = spark.read.csv(path, header=True, sep=sep)
    elif format == "json":
        schema = ", ".join(f"`{(mapping or {}).get(c, c)}` string" for c in EDGE_FIELDS)
        raw = spark.read.schema(schema).json(path)
    else:
        raw = spark.read.format(format).load(path)
    names = {c: (mapping or {}).get(c, c) for c in EDGE_FIELDS}
    flag = F.coalesce(F.col(names["directed"]).cast("boolean"), F.lit(directed)) if names["directed"] in raw.columns else F.lit(directed)
    return tidy(raw.select(_identifier(raw, names["src"]).alias("src"), F.col(names["rel"]).cast("string").alias("rel"), _identifier(raw, names["dst"]).alias("dst"), flag.alias("directed")))


def _identifier(df: DataFrame, name: str):
    c = F.col(name)
    if isinstance(df.schema[name].dataType, T.IntegralType):
        return c.cast("long")
    return F.coalesce(F.when(c.rlike(r"^\s*[0-9]{1,18}\s*$"), F.trim(c).cast("long")), text_key(c))


def text_key(c):
    """A 48-bit number for a text: the same everywhere, without a global sort."""
    return F.conv(F.substring(F.md5(c.cast("string")), 1, 12), 16, 10).cast("long")


def tidy(edges: DataFrame) -> DataFrame:
    """Edge sets: no nulls, no loops, undirected edges once with the smaller end first."""
    swap = ~F.col("directed") & (F.col("src") > F.col("dst"))
    return (
        edges.dropna(subset=["src", "rel", "dst", "directed"])
        .filter("src <> dst")
        .select(F.when(swap, F.col("dst")).otherwise(F.col("src")).alias("src"), "rel", F.when(swap, F.col("src")).otherwise(F.col("dst")).alias("dst"), "directed")
        .distinct()
    )
