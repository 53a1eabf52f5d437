"""Vector primitives over (id, value) tables: product, assign, extract, element-wise.

A vector of the paper is a column; a product with the adjacency pattern on the
(take second, minimum) semiring is a join on ``dst`` and a partial minimum by
``src``; assign with minimum is an aggregation by target (partial minima absorb hot
targets before the shuffle); extract is a self-join.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.layout import BROADCAST_ROWS, Layout


def at_edges(edges: DataFrame | Layout, vector: DataFrame, value: str, *more: str, rows: int | None = None) -> DataFrame:
    """Edges with the vector's value at ``dst`` as ``_v``; laid-out edges stay where they are.

    ``rows``: known number of entries; few are broadcast.
    """
    if isinstance(edges, Layout):
        return edges.meet(vector, value, *more, rows=rows)
    entries = vector.select(F.col("id").alias("dst"), F.col(value).alias("_v"), *more)
    return edges.join(F.broadcast(entries) if rows is not None and rows <= BROADCAST_ROWS else entries, "dst")


def neighbour_min(edges: DataFrame | Layout, vector: DataFrame, value: str = "gf", *, rows: int | None = None) -> DataFrame:
    """(src, mn): least value among the neighbours that the vector has an entry for."""
    return at_edges(edges, vector, value, rows=rows).groupBy("src").agg(F.min("_v").alias("mn"))


def grid_neighbour_min(edges: DataFrame | Layout, vector: DataFrame, value: str, rows: int, columns: int) -> DataFrame:
    """The dense product over a grid of blocks: entries are copied to ``rows`` row blocks
    and partial minima come from ``columns`` column blocks, so a block talks to its row and column only.

    An ablation: blocks are formed anew in every product, unlike the stored layout.
    """
    edges = edges.edges if isinstance(edges, Layout) else edges
    r, c = F.pmod(F.xxhash64("src"), F.lit(rows)).alias("r"), F.pmod(F.xxhash64("dst"), F.lit(columns)).alias("c")
    blocks = edges.select("src", "dst", r, c)
    entries = vector.select(F.col("id").alias("dst"), F.col(value).alias("_v"), F.pmod(F.xxhash64("id"), F.lit(columns)).alias("c"), F.explode(F.array(*[F.lit(i).cast("long") for i in range(rows)])).alias("r"))
    partial = blocks.join(entries, ["r", "c", "dst"]).groupBy("r", "c", "src").agg(F.min("_v").alias("mn"))
    return partial.groupBy("src").agg(F.min("mn").alias("mn"))


def accumulate(state: DataFrame, product: DataFrame) -> DataFrame:
    """Minimum of the accumulated ``mngf`` and a new product."""
    return state.join(product.withColumnRenamed("src", "id"), "id", "left").withColumn("mngf", F.least("mngf", "mn")).drop("mn")


def scatter_min(rows: DataFrame, index: str, value: str) -> DataFrame:
    """(id, value): least value sent to each target; hot targets combine before the shuffle."""
    return rows.groupBy(F.col(index).alias("id")).agg(F.min(value).alias(value))


def ewise_min(df: DataFrame, out: str, *columns: str) -> DataFrame:
    return df.withColumn(out, F.least(*columns))


def ewise_changed(df: DataFrame, new: str, old: str) -> DataFrame:
    """Entries whose value differs: the sparse vector of changes."""
    return df.where(F.col(new) != F.col(old))


def gather(state: DataFrame, index: str, out: str, *, value: str = "f", hot: int = 0) -> DataFrame:
    """Add ``out`` = value of the vertex that ``index`` names.

    ``hot``: that many most-wanted vertices (at most 1,000) are looked up in a
    broadcast table instead of through the shuffle, so that the root of a giant
    component is not asked by everybody in one task.
    """
    parents = state.select(F.col("id").alias("_p"), F.col(value).alias(out))
    if not hot:
        return state.join(parents, state[index] == parents["_p"]).drop("_p")
    wanted = state.groupBy(index).count().orderBy(F.desc("count"), index).limit(min(hot, 1000)).select(F.col(index).alias("_p"))
    top = F.broadcast(parents.join(F.broadcast(wanted), "_p"))
    marked = state.join(top, state[index] == top["_p"], "left")
    warm = marked.where("_p IS NOT NULL").drop("_p")
    cold = marked.where("_p IS NULL").drop("_p", out)
    return warm.unionByName(cold.join(parents, cold[index] == parents["_p"]).drop("_p"))
