"""Components and windows over edge and event streams."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..operators.accelerated import incremental
from ..plans.store import delete_folder, shared_folder


#: Rows of a file of a replayed table.
FILE_ROWS = 1_000_000


def as_stream(df: DataFrame, order: str, files: int, replay_first: bool = False) -> DataFrame:
    """A table as a stream of ``files`` micro-batches in the given order; the first can come again last.

    A batch is written as one file for every ``FILE_ROWS`` rows, and a trigger takes as many files.
    """
    spark = df.sparkSession
    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    edges = df.select(F.percentile_approx(F.col(order).cast("timestamp").cast("double"), [i / files for i in range(1, files)], 100_000)).first()[0] or []
    t = F.col(order).cast("timestamp").cast("double")
    part = sum((F.when(t >= e, 1).otherwise(0) for e in edges), F.lit(0))
    marked = df.withColumn("_part", part)
    each = max(1, df.count() // (files * FILE_ROWS))
    for k in [*range(files), *([0] if replay_first else [])]:
        marked.where(F.col("_part") == k).drop("_part").repartition(each).write.mode("append").parquet(folder)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", each).parquet(folder)


def run_now(stream: DataFrame, mode: str) -> DataFrame:
    """All that is there, as a table in the shared folder: the last batch's in mode ``complete``, those of all batches otherwise.

    Executors write each batch, so that nothing of it passes through the driver; a batch
    that comes again writes its own folder anew.
    """
    spark = stream.sparkSession
    where, out = (f"{shared_folder(spark)}/{kind}-{uuid.uuid4().hex}" for kind in ("progress", "batches"))
    written: list[str] = []

    def one(batch: DataFrame, k: int) -> None:
        path = f"{out}/v-{k}"
        batch.write.mode("overwrite").parquet(path)
        if mode == "complete":
            while written:
                delete_folder(spark, written.pop())
        written.append(path)

    stream.writeStream.foreachBatch(one).outputMode(mode).option("checkpointLocation", where).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(*written) if written else spark.createDataFrame([], stream.schema)


class LabelStore:
    """Labels (id, component) after each micro-batch, one folder a version, in shared storage.

    A version counts once its folder is marked as written in full; a batch that comes
    again after a restart starts from the version before it and writes its own anew.
    """

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def versions(self) -> list[int]:
        jvm, conf = self.spark.sparkContext._jvm, self.spark.sparkContext._jsc.hadoopConfiguration()
        p = jvm.org.apache.hadoop.fs.Path(self.path)
        fs = p.getFileSystem(conf)
        if not fs.exists(p):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(p)]
        return sorted(int(n[2:]) for n in names if n.startswith("v-") and fs.exists(jvm.org.apache.hadoop.fs.Path(f"{self.path}/{n}/_SUCCESS")))

    def read(self, before: int | None = None) -> DataFrame:
        """The newest labels, or those before a version; no rows if there are none."""
        some = [v for v in self.versions() if before is None or v < before]
        if not some:
            return self.spark.createDataFrame([], "id long, component long")
        return self.spark.read.schema("id long, component long").parquet(f"{self.path}/v-{some[-1]}")

    def write(self, labels: DataFrame, version: int, keep_last: int = 2) -> None:
        labels.write.mode("overwrite").parquet(f"{self.path}/v-{version}")
        for old in [v for v in self.versions() if v < version][: -keep_last or None]:
            delete_folder(self.spark, f"{self.path}/v-{old}")


def stream_components(edge_stream: DataFrame, store: str | None = None, progress: str | None = None) -> DataFrame:
    """Labels after all micro-batches that are there.

    A batch shrinks the components known so far to points and solves its own edges between
    them; edges of earlier batches are neither kept nor read again. ``store`` and
    ``progress``: folders to go on from after a restart (new ones by default).
    """
    spark: SparkSession = edge_stream.sparkSession
    labels = LabelStore(spark, store or f"{shared_folder(spark)}/labels-{uuid.uuid4().hex}")

    def one(batch: DataFrame, k: int) -> None:
        labels.write(incremental(labels.read(before=k), batch.select("src", "dst")), k)

    where = progress or f"{shared_folder(spark)}/progress-{uuid.uuid4().hex}"
    edge_stream.writeStream.foreachBatch(one).option("checkpointLocation", where).trigger(availableNow=True).start().awaitTermination()
    return labels.read()


def merged(parent: dict[int, int], a: int, b: int) -> None:
    """Joins the sets of ``a`` and ``b`` below the smaller root."""

    def find(x: int) -> int:
        parent.setdefault(x, x)
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    a, b = find(a), find(b)
    parent[max(a, b)] = min(a, b)


def stream_keyed_unionfind(edges: DataFrame, key: str) -> DataFrame:
    """(key, version, id, component) of one small graph per key, kept in the stream's state.

    Each batch that has edges of a key gives all its labels again under the next version.
    For graphs that fit a row: the state of a key is two lists of ids.
    """

    def update(k, frames, state):
        ids, up, version = state.get if state.exists else ([], [], 0)
        parent = dict(zip(ids, up, strict=True))
        for frame in frames:
            for a, b in zip(frame["src"].tolist(), frame["dst"].tolist(), strict=True):
                merged(parent, a, b)
        for x in list(parent):
            merged(parent, x, x)
        roots = {}
        for x in sorted(parent):  # parents are smaller, so they come first
            roots[x] = x if parent[x] == x else roots[parent[x]]
        state.update((list(roots), list(roots.values()), version + 1))
        yield pd.DataFrame({"key": k[0], "version": version + 1, "id": list(roots), "component": list(roots.values())})

    rows = edges.where("src IS NOT NULL AND dst IS NOT NULL").select(F.col(key).cast("long").alias("key"), "src", "dst")
    return rows.groupBy("key").applyInPandasWithState(update, "key long, version long, id long, component long", "ids array<long>, up array<long>, version long", "update", GroupStateTimeout.NoTimeout)


def newest(versions: DataFrame) -> DataFrame:
    """The labels of each key's last version, which names every vertex of the key again."""
    return versions.groupBy("key", "id").agg(F.max_by("component", "version").alias("component"))


def windowed_counts(events: DataFrame, width: str, slide: str | None = None, watermark: str | None = None) -> DataFrame:
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if watermark:
        timed = timed.withWatermark("ts", watermark)
    return timed.groupBy(F.window("ts", width, slide) if slide else F.window("ts", width)).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "n")


def session_counts(events: DataFrame, gap: str) -> DataFrame:
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "0 seconds")
    return timed.groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")
