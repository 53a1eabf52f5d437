"""The experiments: rounds, speed, density, parts of a round, sparsity, scale.

Wall-clock columns have no SQL; ``repeat`` runs give their median. Every run goes over the
whole tables.
"""

from __future__ import annotations

import statistics
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import accelerated as A
from ..operators import baselines as B
from ..operators import edges as E
from ..operators import reports as R
from ..operators import vectors as V
from ..plans.store import Scratch, forget
from .graphs import GRAPHS
from .queries import add, graph, read, run

#: Graphs of the speed comparison on one machine, and of the parts of a round.
SIX = ("partsupp", "orderpart46", "custorder", "eventchain", "docline", "pagehref")
FOUR = ("orderpart", "partsupp", "eventchain", "docline")


def timed(work, repeat: int = 1):
    """(median seconds, last result) of ``repeat`` runs."""
    seconds, out = [], None
    for _ in range(repeat):
        began = time.monotonic()
        out = work()
        seconds.append(time.monotonic() - began)
    return statistics.median(seconds), out


@add("exp_ladder_all_graphs")
def ladder_all(spark, d):
    """Rounds of the first level (slots written by an arbitrary but fixed edge) and of the last on every graph, and what
    the last saves. All levels on four graphs: ``iterations_ladder``; the rival's (half its products): ``exp_rival_speed``."""
    found = A.rounds_of([graph(spark, d, k) for k in GRAPHS], [{"level": 1, "tie": "hash"}, {}])
    rows = [(k, *counts) for k, counts in zip(GRAPHS, found, strict=True)]
    out = spark.createDataFrame(rows, "graph string, first int, last int")
    return out.select("*", (1 - F.col("last") / F.col("first")).alias("saved"))


@add("exp_ladder_ties")
def ladder_ties(spark, d):
    """Rounds of the first two levels under each rule of which edge writes a slot."""
    keys, settings = ("orderpart46", "pagehref"), [(level, t) for level in (1, 2) for t in A.TIES]
    found = A.rounds_of([graph(spark, d, k) for k in keys], [{"level": level, "tie": t} for level, t in settings])
    rows = [(k, level, t, n) for k, counts in zip(keys, found, strict=True) for (level, t), n in zip(settings, counts, strict=True)]
    return spark.createDataFrame(rows, "graph string, level int, tie string, iterations int")


def against_rival(spark: SparkSession, d: str, key: str, edges: DataFrame | None = None, repeat: int = 1) -> tuple:
    """(seconds of the accelerated method, of the rival, products of both, records shuffled by both).

    Both start from one and the same layout: it is made once, and its seconds and records count for both.
    ``edges``: stored ones instead of the graph's, which are stored here, as the layout reads them twice.
    """
    given, vertices = graph(spark, d, key)
    out = []
    with Scratch() as scratch:
        since = R.shuffled(spark)[2]
        laid_s, laid = timed(lambda: A.prepare(scratch.keep(given)[0] if edges is None else edges, vertices, scratch))
        laid_rows, _, since = R.shuffled(spark, since)
        try:
            for rounds in (A.rounds_on, B.star_hooking_on):
                seconds, result = timed(lambda f=rounds: f(*laid), repeat)
                rows, _, since = R.shuffled(spark, since)
                out.append((laid_s + seconds, sum(t["products"] for t in result.trace), laid_rows + rows // repeat))
                forget(result.labels)
        finally:
            laid[0].drop()
    (a, pa, ra), (b, pb, rb) = out
    return a, b, b / a, pa, pb, ra, rb


_SPEED = "accelerated_s double, rival_s double, speedup double, accelerated_products int, rival_products int, accelerated_rows_shuffled long, rival_rows_shuffled long"


@add("exp_rival_speed")
def rival_speed(spark, d, repeat: int = 1):
    """Seconds, products and rows shuffled of the accelerated method and of the rival on six graphs."""
    return spark.createDataFrame([(k, *against_rival(spark, d, k, repeat=repeat)) for k in SIX], f"graph string, {_SPEED}")


@add("exp_density_speed")
def density_speed(spark, d, repeat: int = 1):
    """The same on one table with edges from few to many: speed-up by density."""
    rows, n = [], GRAPHS["orderpart"].vertices(spark, d).count()
    with Scratch() as scratch:
        # Distinct edges with the greatest quantity of theirs: the edges of every bound are among them.
        best = read(spark, d, "lineitem").groupBy("l_orderkey", "l_partkey").agg(F.max("l_quantity").alias("most"))
        best, _ = scratch.keep(best)
        for least in (1, 46, 50):
            edges, seen = scratch.keep(E.bipartite(best.where(F.col("most") >= least), "l_orderkey", "l_partkey"), m=F.count(F.lit(1)))
            rows.append((least, 2 * seen["m"] / n, *against_rival(spark, d, "orderpart", edges, repeat)))
    return spark.createDataFrame(rows, f"least int, density double, {_SPEED}")


def parts_of_rounds(spark: SparkSession, d: str, key: str, threshold: float = A.SPARSE_THRESHOLD) -> list[tuple]:
    """Per round: changed entries, share, kind of product, seconds of product, hooking and grandparent step (each written by itself)."""
    edges, vertices = graph(spark, d, key)
    o, out = A.Options(sparse_threshold=threshold), []
    with Scratch() as scratch:
        layout, ids, n = A.prepare(edges, vertices, scratch)
        try:
            state, _ = scratch.keep(A.start_state(ids, None, 0).withColumn("gf_prev", F.lit(-1).cast("long")))
            changed = n
            for k in range(1, o.max_iter):
                t = [time.monotonic()]
                product, kind = A.product_of(layout, state, o, k == 1, changed, n, 0)
                product, _ = scratch.keep(product)
                t.append(time.monotonic())
                hooked, _ = scratch.keep(A.round_of_minima(product, state, o))
                t.append(time.monotonic())
                state, seen = scratch.keep(V.gather(hooked, "f", "gf"), c=F.count_if(F.col("gf") != F.col("gf_prev")))
                t.append(time.monotonic())
                out.append((key, threshold, k, kind, changed / n if n else 0.0, seen["c"], *(b - a for a, b in zip(t, t[1:], strict=False))))
                changed = seen["c"]
                if not changed:
                    break
        finally:
            layout.drop()
    return out


_PARTS = "graph string, threshold double, iteration int, product string, frontier double, changed_gf long, product_s double, hooking_s double, grandparent_s double"


@add("runtime_breakdown")
def breakdown(spark, d):
    """Seconds of product, hooking and grandparent step of each round on four graphs."""
    return spark.createDataFrame([r for k in FOUR for r in parts_of_rounds(spark, d, k)], _PARTS)


@add("exp_sparsity_sweep")
def sparsity(spark, d):
    """The share of changed grandparents a product starts from, and its time, by the threshold of the sparse product."""
    return spark.createDataFrame([r for t in (0.0, 0.01, 0.1, 1.0) for r in parts_of_rounds(spark, d, "orderpart46", t)], _PARTS)


@add("exp_partitions")
def partitions(spark, d, counts: tuple[int, ...] = (4, 16, 64)):
    """Seconds and rounds over shuffle partitions (= buckets of edges); cores are varied by ``bench.py``."""
    was, rows = spark.conf.get("spark.sql.shuffle.partitions"), []
    try:
        for n in counts:
            spark.conf.set("spark.sql.shuffle.partitions", n)
            seconds, result = timed(lambda: run(spark, d, "pagehref"))
            rows.append((n, result.iterations, seconds))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", was)
    return spark.createDataFrame(rows, "partitions int, iterations int, seconds double")


def replicated(edges: DataFrame, vertices: DataFrame, copies: int) -> tuple[DataFrame, DataFrame]:
    """A graph side by side with itself: ids of copy c of ``copies`` are id * copies + c."""
    c = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(copies - 1).cast("long"))).alias("c")
    moved = lambda x: (F.col(x) * copies + F.col("c")).alias(x)
    return edges.select("src", "dst", c).select(moved("src"), moved("dst")), vertices.select("id", c).select(moved("id"))


_COPIES_SQL = "SELECT {0} FROM ({1}), range(0, {2}) t(c)"


def _replicated_sql(copies: int) -> str:
    from . import oracles as O  # noqa: N812

    g = GRAPHS["orderpart46"]
    edges = _COPIES_SQL.format(f"src * {copies} + c AS src, dst * {copies} + c AS dst", g.edge_sql, copies)
    return O.labelled(edges, _COPIES_SQL.format(f"id * {copies} + c AS id", g.vertex_sql, copies))


@add("cc_replicated", _replicated_sql(4))
def cc_replicated(spark, d, copies: int = 4):
    """The largest workload: disjoint shifted copies of one graph."""
    return A.connected_components(*replicated(*graph(spark, d, "orderpart46"), copies)).labels


@add("exp_replicated_scale")
def replicated_scale(spark, d):
    """Rounds and seconds while the graph grows by copies: rounds stay, seconds follow the edges.

    The graph itself is made once: its distinct edges and its vertices are stored, and every size reads its copies off
    them. Each size then counts its degrees, lays its edges out and does its rounds in full, which are the seconds.
    """
    rows = []
    with Scratch() as scratch:
        edges, vertices = graph(spark, d, "orderpart")
        edges, seen = scratch.keep(edges, m=F.count(F.lit(1)))
        vertices, _ = scratch.keep(vertices)
        for copies in (1, 4, 8):
            seconds, result = timed(lambda k=copies: A.connected_components(*replicated(edges, vertices, k), simple=True))
            rows.append((copies, seen["m"] * copies, result.iterations, seconds))
            forget(result.labels)
    return spark.createDataFrame(rows, "copies int, edges long, iterations int, seconds double")


_HEIGHT_SQL = "WITH RECURSIVE t AS MATERIALIZED (SELECT o_orderkey AS id, coalesce(lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey), o_orderkey) AS f FROM orders), up(id, h) AS (SELECT id, 0 FROM t WHERE f = id UNION ALL SELECT t.id, h + 1 FROM up JOIN t ON t.f = up.id AND t.id <> t.f) SELECT CAST(max(h) AS INT) AS height FROM up"


@add("op_forest_height", _HEIGHT_SQL)
def height(spark, d):
    """Height of the forest of each customer's orders, one below the other."""
    from .queries import _chains

    return spark.createDataFrame([(R.forest_height(_chains(spark, d)),)], "height int")


@add("exp_tree_height")
def heights(spark, d):
    """Tallest tree after each round, by the ancestor that is hooked to: higher targets, shorter trees."""
    rows, depths = [], (1, 2, 3)
    see = lambda _, s, state, k: rows.append((depths[s], k, R.forest_height(state)))
    A.rounds_of([graph(spark, d, "orderpart46")], [{"hook_depth": depth, "stop": "f"} for depth in depths], see)
    return spark.createDataFrame(sorted(rows), "hook_depth int, iteration int, height int")


