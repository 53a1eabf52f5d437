"""Edges and vertices: hygiene, identity, and builders that turn tables into graphs.

Vertices have ``id BIGINT``; edges have ``src BIGINT, dst BIGINT``, symmetric,
distinct and without loops once ``symmetrize`` has seen them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def pairs(df: DataFrame, src: Column | str, dst: Column | str) -> DataFrame:
    col = lambda c: F.col(c) if isinstance(c, str) else c
    return df.select(col(src).cast("long").alias("src"), col(dst).cast("long").alias("dst"))


def drop_bad(edges: DataFrame) -> DataFrame:
    """Without loops and null ends (``<>`` is not true for a null)."""
    return edges.where(F.col("src") != F.col("dst"))


def symmetrize(edges: DataFrame) -> DataFrame:
    """Both orientations, each once. One pass over the input, one shuffle."""
    both = F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return drop_bad(edges).select(F.inline(both)).distinct()


def canonical(edges: DataFrame) -> DataFrame:
    """Each undirected edge once, smaller end first."""
    return drop_bad(edges).select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()


def vertices_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("id")).where("id IS NOT NULL").distinct()


def isolated(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    return vertices.join(edges, vertices["id"] == edges["src"], "left_anti")


def bipartite(df: DataFrame, left: str, right: str) -> DataFrame:
    """Edges between two key spaces: even numbers to the left, odd to the right."""
    return pairs(df, F.col(left).cast("long") * 2, F.col(right).cast("long") * 2 + 1).distinct()


def chain(df: DataFrame, key: str, group: list[str], order: list[str], gap: Column | None = None) -> DataFrame:
    """Each row to the next of its group; ``gap`` is a condition on (a, b) rows named this/next."""
    w = Window.partitionBy(*group).orderBy(*order)
    cols = [F.lead(key).over(w).alias("dst")] + [F.lead(c).over(w).alias(f"next_{c}") for c in order]
    out = df.select(F.col(key).alias("src"), *order, *cols).where("dst IS NOT NULL")
    return pairs(out.where(gap) if gap is not None else out, "src", "dst")


def shared_value(df: DataFrame, key: str, value: Column | str) -> DataFrame:
    """A star per value: every key to the smallest key with that value (never all pairs)."""
    rows = df.select(F.col(key).cast("long").alias("src"), (F.col(value) if isinstance(value, str) else value).alias("value")).where("value IS NOT NULL").distinct()
    least = rows.groupBy("value").agg(F.min("src").alias("dst"))
    return drop_bad(rows.join(least, "value").select("src", "dst")).distinct()


def similar_vectors(df: DataFrame, key: str, vector: str, least_cosine: float, block: int | None = None) -> DataFrame:
    """Pairs of vectors with a cosine of at least ``least_cosine``; no pair is left out.

    Without ``block`` every pair is a row of a join (a bounded table only). With it,
    vectors are dealt to blocks of about that many by the hash of their key, and a task
    compares two blocks by matrix products, so that only the pairs found become rows.
    """
    if block:
        short = dict(df.dtypes)[vector] == "array<float>"
        return _similar_by_blocks(df.select(F.col(key).cast("long").alias("id"), F.col(vector).cast("array<float>" if short else "array<double>").alias("v")), least_cosine, block)
    unit = df.select(F.col(key).cast("long").alias("id"), F.transform(vector, lambda x: x.cast("double")).alias("v"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    a, b = unit.select(F.col("id").alias("src"), F.col("v").alias("a")), unit.select(F.col("id").alias("dst"), F.col("v").alias("b"))
    both = a.join(b, F.col("src") < F.col("dst"))
    cosine = dot(F.col("a"), F.col("b")) / F.sqrt(dot(F.col("a"), F.col("a")) * dot(F.col("b"), F.col("b")))
    return both.where(F.round(cosine, 6) >= least_cosine).select("src", "dst")


def _similar_by_blocks(rows: DataFrame, least_cosine: float, block: int) -> DataFrame:
    rows = rows.where("id IS NOT NULL AND v IS NOT NULL")
    blocks = max(4, -(-rows.count() // block))  # some tasks for small tables too
    mine, other = F.pmod(F.xxhash64("id"), F.lit(blocks)), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long")))
    dealt = rows.select("id", "v", mine.alias("mine"), other.alias("other")).withColumn("i", F.least("mine", "other")).withColumn("j", F.greatest("mine", "other"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches))
        ids, side = table["id"].to_numpy(), table["mine"].to_numpy()
        v = table["v"].combine_chunks().flatten().to_numpy().astype(np.float64).reshape(len(ids), -1)
        norm = np.sqrt((v * v).sum(axis=1))
        some = norm > 0
        ids, side, v = ids[some], side[some], v[some] / norm[some, None]
        if not len(ids):
            return
        first = side == side.min()
        a, b = np.flatnonzero(first), np.flatnonzero(~first)
        b = b if table["i"][0] != table["j"][0] else a
        for at in range(0, len(a), 512):
            part = a[at : at + 512]
            x, y = np.nonzero((np.round(v[part] @ v[b].T, 6) >= least_cosine) & (True if b is not a else ids[part][:, None] < ids[b][None, :]))
            p, q = ids[part[x]], ids[b[y]]
            for k in range(0, len(p), 1 << 20):
                u, w = p[k : k + (1 << 20)], q[k : k + (1 << 20)]
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(u, w)), pa.array(np.maximum(u, w))], names=["src", "dst"])

    return dealt.select("i", "j", "mine", "id", "v").groupBy("i", "j").applyInArrow(run, "src long, dst long")


def near_in_time(df: DataFrame, key: str, ts: str, seconds: int, group: list[str]) -> DataFrame:
    """Pairs of one group at most ``seconds`` apart: equi-join on time buckets, then the exact test."""
    t = F.unix_timestamp(F.col(ts).cast("timestamp"))
    rows = df.select(F.col(key).cast("long").alias("k"), t.alias("t"), *group)
    b = F.floor(F.col("t") / seconds)
    left = rows.select(F.col("k").alias("src"), F.col("t").alias("t1"), *group, b.alias("bucket"))
    right = rows.select(F.col("k").alias("dst"), F.col("t").alias("t2"), *group, F.explode(F.array(b - 1, b, b + 1)).alias("bucket"))
    close = left.join(right, [*group, "bucket"]).where((F.abs(F.col("t1") - F.col("t2")) <= seconds) & (F.col("src") < F.col("dst")))
    return close.select("src", "dst")


def last_before(df: DataFrame, key: str, ts: str, group: list[str], is_left: Column, is_right: Column) -> DataFrame:
    """As-of join: each left row to the latest earlier right row of its group, by one sort."""
    w = Window.partitionBy(*group).orderBy(ts, key).rowsBetween(Window.unboundedPreceding, -1)
    seen = F.last(F.when(is_right, F.col(key)), ignorenulls=True).over(w)
    return pairs(df.select(F.col(key).alias("src"), seen.alias("dst"), is_left.alias("l")).where("l AND dst IS NOT NULL"), "src", "dst")


def index_vertices(df: DataFrame, column: str, mode: str = "dense") -> DataFrame:
    """Natural key to id. ``dense``: rank 0, 1, ... by range partitions and their counts, without a global window.
    ``hash``: xxhash64; two keys with one hash are an error, as they would be one vertex."""
    from ..plans.store import keep

    if mode not in ("dense", "hash"):
        raise ValueError("mode is dense or hash")
    keys = df.select(F.col(column).alias("key")).where("key IS NOT NULL").distinct()
    if mode == "hash":
        return checked_ids(keep(keys.select("key", F.xxhash64("key").alias("id")))[0])
    part, _ = keep(keys.repartitionByRange("key").withColumn("part", F.spark_partition_id()))
    sizes = {r["part"]: r["n"] for r in part.groupBy("part").agg(F.count(F.lit(1)).alias("n")).collect()}  # one row per partition
    base, at = [], 0
    for p in range(max(sizes, default=-1) + 1):
        base.append(at)
        at += sizes.get(p, 0)
    inside = F.row_number().over(Window.partitionBy("part").orderBy("key"))
    return part.select("key", (inside - 1 + F.element_at(F.array(*[F.lit(b).cast("long") for b in base] or [F.lit(0)]), F.col("part") + 1)).cast("long").alias("id"))


def checked_ids(mapping: DataFrame) -> DataFrame:
    """The mapping (key, id) itself, if no id stands for two keys; otherwise an error that names some."""
    twice = mapping.groupBy("id").agg(F.count(F.lit(1)).alias("n"), F.min("key").alias("a"), F.max("key").alias("b")).where("n > 1").limit(3).collect()
    if twice:
        raise ValueError(f"keys share an id: {[(r['a'], r['b']) for r in twice]}; use mode='dense'")
    return mapping


def relabel(edges: DataFrame, mapping: DataFrame) -> DataFrame:
    """Edges with ids replaced through (id, new_id)."""
    a, b = mapping.select(F.col("id").alias("src"), F.col("new_id").alias("s")), mapping.select(F.col("id").alias("dst"), F.col("new_id").alias("d"))
    return edges.join(a, "src").join(b, "dst").select(F.col("s").alias("src"), F.col("d").alias("dst"))


def contract(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """Edges between components of ``labels``, each once, loops dropped."""
    a, b = labels.select(F.col("id").alias("src"), F.col("component").alias("s")), labels.select(F.col("id").alias("dst"), F.col("component").alias("d"))
    out = edges.join(a, "src").join(b, "dst").select(F.col("s").alias("src"), F.col("d").alias("dst"))
    return drop_bad(out).distinct()
