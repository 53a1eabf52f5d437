"""Cutting lineage between rounds, and counters that ride along.

Every round ends in one job: the new state is written as a table to the shared folder of
``spark.checkpoint.dir`` (one of our own only on a local master where none is set), and the
counters the loop decides on are observed on the same pass. A written table survives lost
executors, and its true size is known to the planner; a checkpoint would carry the estimate
of its plan along, which grows by a power with every self-join of every round. Edges are
written once, bucketed (``plans.layout``).

What a run has written is deleted when the run that owns it ends, but for the tables its
result reads (``Scratch``).
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share. A temporary one only where none is set and all runs in one process."""
    sc = spark.sparkContext
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        if not sc.getCheckpointDir():
            if not sc.master.startswith("local"):
                raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
            sc.setCheckpointDir(tempfile.mkdtemp(prefix="pointerforest-"))
        return sc.getCheckpointDir().rstrip("/")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(where)
    return where.rstrip("/")


def stored(df: DataFrame) -> DataFrame:
    """The table, written to the shared folder and read from there."""
    path = f"{shared_folder(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def keep(df: DataFrame, **counters: Column) -> tuple[DataFrame, dict[str, int]]:
    """Materialise ``df`` and return it with the values of the aggregate columns."""
    if not counters:
        return stored(df), {}
    seen = Observation()
    out = stored(df.observe(seen, *[c.alias(k) for k, c in counters.items()]))
    return out, {k: v or 0 for k, v in seen.get.items()}


def delete_folder(spark: SparkSession, path: str) -> None:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def forget(df: DataFrame) -> None:
    """Delete a stored table that nothing reads any more."""
    if path := getattr(df, "stored_at", None):
        delete_folder(df.sparkSession, path)


class Scratch:
    """Owner of the tables of one run: what is not kept for the result goes when the run ends."""

    def __init__(self):
        self._mine: list[DataFrame] = []

    def __enter__(self) -> Scratch:
        return self

    def keep(self, df: DataFrame, **counters: Column) -> tuple[DataFrame, dict[str, int]]:
        out, seen = keep(df, **counters)
        self._mine.append(out)
        return out, seen

    def own(self, df: DataFrame) -> DataFrame:
        """A stored table that another run left as its result: it goes with this one."""
        self._mine.append(df)
        return df

    def spare(self, df: DataFrame) -> DataFrame:
        """The caller's result reads this one: it stays."""
        self._mine = [x for x in self._mine if x is not df]
        return df

    def __exit__(self, *error) -> None:
        for df in self._mine:
            forget(df)
        self._mine = []
