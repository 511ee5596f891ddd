"""Cutting plans between rounds, and work counters."""

from __future__ import annotations

import contextlib
import tempfile
import uuid
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

#: Folders that the open ``scratch`` blocks will delete, innermost last.
_SCRATCH: list[list[tuple[SparkSession, str]]] = []


def shared_dir(spark: SparkSession) -> str:
    """A new folder below the cluster's ``spark.checkpoint.dir``; a local one only on a local master, as in tests."""
    context = spark.sparkContext
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        known = context._jsc.sc().getCheckpointDir()
        if known.isDefined():
            base = known.get()
        elif context.master.startswith("local"):
            base = "file://" + tempfile.mkdtemp(prefix="linkwhy-")
            context.setCheckpointDir(base)
        else:
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    return f"{base.rstrip('/')}/linkwhy-{uuid.uuid4().hex}"


def settle(df: DataFrame) -> DataFrame:
    """Write to the shared folder and go on from there: a lost executor costs one round."""
    spark = df.sparkSession
    if not spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(shared_dir(spark))
    out = df.checkpoint(eager=True)
    if _SCRATCH:
        place = out._jdf.queryExecution().logical().rdd().getCheckpointFile()
        if place.isDefined():
            delete_later(spark, place.get())
    return out


def delete_later(spark: SparkSession, path: str) -> None:
    """Hand a folder to the innermost open ``scratch`` block, if there is one."""
    if _SCRATCH:
        _SCRATCH[-1].append((spark, path))


@contextlib.contextmanager
def scratch():
    """Delete what was settled inside when the block ends; results must have been written or read by then."""
    _SCRATCH.append([])
    try:
        yield
    finally:
        for spark, path in _SCRATCH.pop():
            place = spark._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


@dataclass
class RunStats:
    """Machine-independent work of a run: named counters, by round where that helps."""

    counters: dict[str, int] = field(default_factory=dict)

    def add(self, name: str, n: int) -> None:
        self.counters[name] = self.counters.get(name, 0) + int(n)

    def rows(self) -> list[tuple[str, int]]:
        return sorted(self.counters.items())
