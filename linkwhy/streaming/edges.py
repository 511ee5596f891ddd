"""Streams of events around the engine; the explanation methods themselves are batch."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..plans.runs import delete_later, shared_dir
from ..sources.kb import eid


def read_events(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    """A file source over an event table (a folder of files, or one file of a folder); ts becomes an instant."""
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger)
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    if not place.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(place).isDirectory():
        reader, path = reader.option("pathGlobFilter", place.getName()), path.rpartition("/")[0]
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def stream_edges(events: DataFrame, delay: str = "1 day") -> DataFrame:
    """Events to graph edges, each once within the watermark; later ones are dropped."""
    own = events.select("ts", eid("user", F.col("user_id")).alias("src"), F.col("event_type").alias("rel"), eid("key", F.get_json_object("props", "$.k")).alias("dst")).filter("dst IS NOT NULL")
    return own.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["src", "rel", "dst"]).withColumn("directed", F.lit(True))


def label_counts(events: DataFrame, width: str = "1 day", slide: str | None = None, delay: str = "1 day") -> DataFrame:
    """Relationships by label in tumbling or sliding windows."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    out = events.withWatermark("ts", delay).groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return out.select(F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), "event_type", "n")


def session_users(events: DataFrame, gap: str = "30 minutes", delay: str = "1 day") -> DataFrame:
    """Sessions on a key: when, how many events, and how many users by approximation."""
    key = F.get_json_object("props", "$.k").cast("long")
    out = events.withColumn("k", key).withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "k").agg(F.count(F.lit(1)).alias("n_events"), F.approx_count_distinct("user_id").alias("n_users"))
    return out.select("k", F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), "n_events", "n_users")


def co_occurrence(events: DataFrame) -> DataFrame:
    """Running number of changes of user on each key, kept as state: (k, last_user, changes)."""
    own = events.select(F.get_json_object("props", "$.k").cast("long").alias("k"), "user_id", "ts").filter("k IS NOT NULL")

    def step(key, frames, state: GroupState):
        last, changes = state.get if state.exists else (-1, 0)
        for frame in frames:
            for user in frame.sort_values(["ts", "user_id"])["user_id"]:
                changes += int(last not in (-1, user))
                last = int(user)
        state.update((last, changes))
        yield pd.DataFrame({"k": [key[0]], "last_user": [last], "changes": [changes]})

    return own.groupBy("k").applyInPandasWithState(step, "k long, last_user long, changes long", "last_user long, changes long", "update", GroupStateTimeout.NoTimeout)


def drain(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there and return its rows (tests and reports).

    Rows of an append or update go to the shared folder, a folder a batch, so the driver holds none; an update gives all
    states of a key, as a memory table does.  A complete result is written anew by each batch, and the last one counts.
    """
    spark = df.sparkSession
    place = shared_dir(spark)

    def batch(rows: DataFrame, number: int) -> None:
        rows.write.mode("overwrite").parquet(f"{place}/rows/batch={number:09d}")

    query = df.writeStream.queryName(name).option("checkpointLocation", f"{place}/state").outputMode(mode).trigger(availableNow=True).foreachBatch(batch).start()
    query.awaitTermination()
    delete_later(spark, place)
    own = spark.read.schema(df.schema.add("batch", "long")).parquet(f"{place}/rows") if query.lastProgress else spark.createDataFrame([], df.schema.add("batch", "long"))
    if mode == "complete":
        last = own.agg(F.max("batch")).first()[0]
        own = own.filter(F.col("batch") == last)
    return own.drop("batch")


def explain_requests(requests: DataFrame, answer, sink: str):
    """Pairs stream in, explanations go out: ``answer(pairs) -> DataFrame`` runs on each small batch."""
    def batch(pairs: DataFrame, number: int) -> None:
        answer(pairs).withColumn("batch", F.lit(number)).write.mode("append").parquet(sink)

    return requests.writeStream.foreachBatch(batch).trigger(availableNow=True).start()


def late_rows(query) -> int:
    """Rows that a finished query dropped because they came behind the watermark."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in p["stateOperators"])
