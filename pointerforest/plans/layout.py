"""Edges on disk in the order products read them, so that no round moves them.

Symmetric edges are written once as a table bucketed by ``dst`` into as many buckets as the
session has shuffle partitions. The planner knows the layout of a bucketed scan, also under
adaptive execution (a checkpointed plan's is forgotten there), so a product shuffles the
vector to the edges and never the edges.

A vertex with very many edges would fill one bucket. Its edges are dealt to several, by a
``salt`` from the other end, and its entry of the vector is copied as often: the bucket key
is (dst, salt) then. At most one vertex per ``HUB_EDGES`` edges can be so, which bounds the table
of hubs; only a small one is broadcast.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import delete_folder, shared_folder, stored

#: Edges of one vertex that one bucket takes.
HUB_EDGES = 1 << 20
#: Rows (16 bytes each) of a vector or of the table of hubs that are broadcast at most.
BROADCAST_ROWS = 500_000


@dataclass
class Layout:
    """Symmetric distinct edges (src, dst[, salt]) bucketed by ``keys``."""

    edges: DataFrame
    keys: list[str]
    hubs: DataFrame | None
    n_hubs: int
    table: str
    path: str
    #: Vertices (id) with edges and without, and how many have none, once ``prepare`` knows them.
    joined: DataFrame | None = None
    alone: DataFrame | None = None
    n_alone: int = 0

    def entries(self, vector: DataFrame, value: str, *more: str, rows: int | None = None) -> DataFrame:
        """Entries of a vector (id, value) by the keys of the layout, hinted by their number."""
        out = vector.select(F.col("id").alias("dst"), F.col(value).alias("_v"), *more)
        if self.hubs is not None:
            hubs = F.broadcast(self.hubs) if self.n_hubs <= BROADCAST_ROWS else self.hubs
            copies = F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce("salts", F.lit(1)) - 1)).alias("salt")
            out = out.join(hubs, "dst", "left").select("dst", "_v", *more, copies)
        if rows is not None:
            # Entries are one per vertex and key, so a bucket's share of them fits a hash table; the edges just stream by.
            out = F.broadcast(out) if rows <= BROADCAST_ROWS else out.hint("shuffle_hash")
        return out

    def meet(self, vector: DataFrame, value: str, *more: str, rows: int | None = None) -> DataFrame:
        """Edges with the vector's ``value`` at ``dst`` as ``_v``."""
        return self.edges.join(self.entries(vector, value, *more, rows=rows), self.keys)

    def least_neighbour(self) -> DataFrame:
        """(src, mn): least neighbour of every vertex with edges, grouped where the edges are."""
        return self.edges.groupBy("dst").agg(F.min("src").alias("mn")).withColumnRenamed("dst", "src")

    def without(self, gone: DataFrame, rows: int) -> Layout:
        """The same layout without the edges at vertices ``gone`` (id), which have none to elsewhere."""
        out = self.entries(gone.withColumn("_x", F.lit(1)), "_x", rows=rows).drop("_v")
        return _write(self.edges.join(out, self.keys, "left_anti"), self.keys, self.hubs, self.n_hubs)

    def drop(self, *, hubs: bool = True) -> None:
        """Delete the table (and that of the hubs, which layouts made by ``without`` share)."""
        spark = self.edges.sparkSession
        spark.sql(f"DROP TABLE IF EXISTS {self.table}")
        delete_folder(spark, self.path)
        if hubs and self.hubs is not None:
            delete_folder(spark, self.hubs.stored_at)


def degrees(edges: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """(id, degree) of all vertices: one pass over the edges, one partial count per vertex.

    Ends of rows that are no edges (loops, one end missing) are vertices of degree 0;
    repeated edges count as often as they occur.
    """
    real = F.coalesce((F.col("src") != F.col("dst")).cast("long"), F.lit(0).cast("long"))
    ends = edges.select(F.inline(F.array(F.struct(F.col("src").alias("id"), real.alias("w")), F.struct(F.col("dst").alias("id"), real.alias("w")))))
    if vertices is not None:
        ends = ends.unionByName(vertices.select(F.col("id").cast("long").alias("id"), F.lit(0).cast("long").alias("w")))
    return ends.where("id IS NOT NULL").groupBy("id").agg(F.sum("w").alias("degree"))


def lay_out(edges: DataFrame, degree: DataFrame, n_hubs: int, *, hub_edges: int = HUB_EDGES, loops: bool = False, simple: bool = False) -> Layout:
    """Both orientations of the edges, each once, without loops and null ends: one shuffle.

    ``degree``: (id, degree) as ``degrees`` gives it, with ``n_hubs`` vertices beyond ``hub_edges``.
    ``loops``: one at every vertex, so that a product also passes on what each has itself.
    ``simple``: no edge is given twice, in either orientation, so that none has to be looked for.
    """
    both = F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))
    rows = edges.where("src <> dst").select(F.inline(both))
    if loops:
        rows = rows.unionByName(degree.select(F.col("id").alias("src"), F.col("id").alias("dst")))
    if not n_hubs:
        return _write(rows, ["dst"], None, 0, fresh=True, simple=simple)
    hubs = stored(degree.where(F.col("degree") > hub_edges).select(F.col("id").alias("dst"), F.ceil(F.col("degree") / hub_edges).alias("salts")))
    small = F.broadcast(hubs) if n_hubs <= BROADCAST_ROWS else hubs
    salt = F.pmod(F.xxhash64("src"), F.coalesce("salts", F.lit(1))).alias("salt")
    return _write(rows.join(small, "dst", "left").select("src", "dst", salt), ["dst", "salt"], hubs, n_hubs, fresh=True, simple=simple)


def _write(rows: DataFrame, keys: list[str], hubs: DataFrame | None, n_hubs: int, *, fresh: bool = False, simple: bool = False) -> Layout:
    spark = rows.sparkSession
    buckets = min(int(spark.conf.get("spark.sql.shuffle.partitions")), int(spark.conf.get("spark.sql.sources.bucketing.maxBuckets")))
    name = f"edges_{uuid.uuid4().hex}"
    path = f"{shared_folder(spark)}/{name}"
    if fresh:  # equal edges meet in one partition, so that the distinct needs no shuffle of its own
        rows = rows.repartition(buckets, *keys)
        rows = rows if simple else rows.distinct()
    rows.write.bucketBy(buckets, *keys).sortBy("dst", "src").option("path", path).saveAsTable(name)
    return Layout(spark.table(name), keys, hubs, n_hubs, name, path)
