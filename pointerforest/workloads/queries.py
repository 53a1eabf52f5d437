"""All registered queries of the graph side, each with the SQL that checks it (or none)."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import udfs
from ..operators import accelerated as A
from ..operators import baselines as B
from ..operators import edges as E
from ..operators import reports as R
from ..operators import vectors as V
from ..plans.store import Scratch, keep, shared_folder
from ..sources import edges as S
from ..streaming import components as T
from . import oracles as O
from .graphs import GRAPHS

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def add(name: str, sql: str | None = None):
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


def read(spark: SparkSession, d: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{table}.parquet")


def graph(spark: SparkSession, d: str, key: str) -> tuple[DataFrame, DataFrame]:
    g = GRAPHS[key]
    return g.edges(spark, d), g.vertices(spark, d)


def run(spark: SparkSession, d: str, key: str, **options) -> A.Run:
    edges, vertices = graph(spark, d, key)
    return A.connected_components(edges, vertices, **options)


def _labels(key: str, **options) -> Query:
    return lambda spark, d: run(spark, d, key, **options).labels


# Methods, levels, variants and baselines: labels against keyed recursion.
for _k in GRAPHS:
    add(f"cc_accel_{_k}", O.cc(_k))(_labels(_k))
for _l in (1, 2, 3, 4):
    add(f"cc_level{_l}_orderpart46", O.cc("orderpart46"))(_labels("orderpart46", level=_l))
for _name, _key, _options in [
    ("cc_shb_orderpart46", "orderpart46", {"method": "star_hooking"}),
    ("cc_shb_custorder", "custorder", {"method": "star_hooking"}),
    ("cc_shb_noprune", "orderpart46", {"method": "star_hooking", "prune_converged": False}),
    ("cc_svfull_orderpart46", "orderpart46", {"method": "sv_full", "final_shortcut": False}),
    ("cc_svfull_lastshortcut", "orderpart46", {"method": "sv_full", "final_shortcut": True}),
    ("cc_labelprop_chain", "eventchain", {"method": "label_propagation", "local": True}),
    ("cc_bfs_nation", "nationregion", {"method": "bfs"}),
    ("cc_hybrid_orderpart", "orderpart", {"method": "hybrid"}),
    ("cc_level1_tie_max", "orderpart46", {"level": 1, "tie": "max"}),
    ("cc_level1_tie_hash", "orderpart46", {"level": 1, "tie": "hash"}),
    ("cc_level2_tie_hash", "orderpart46", {"level": 2, "tie": "hash"}),
    ("cc_hub_layout", "userk", {"hub_edges": 16}),
    ("cc_hookdepth1", "orderpart46", {"hook_depth": 1}),
    ("cc_hookdepth3", "orderpart46", {"hook_depth": 3}),
    ("cc_extra_shortcut", "orderpart46", {"extra_shortcut": True, "stop": "f"}),
    ("cc_product_dense", "orderpart46", {"product": "dense"}),
    ("cc_product_sparse", "orderpart46", {"product": "sparse"}),
    ("cc_product_auto", "orderpart46", {"product": "auto"}),
    ("cc_gather_hotbroadcast", "orderpart", {"gather": "hot"}),
    ("cc_gather_plain", "orderpart", {"gather": "plain"}),
    ("cc_grid2d", "orderpart", {"grid": (2, 3), "product": "dense"}),
]:
    add(_name, O.cc(_key))(_labels(_key, **_options))


def _halves(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    edges, vertices = graph(spark, d, "orderpart46")
    return edges.where("src % 4 = 0"), edges, vertices


@add("cc_warm_start", O.cc("orderpart46"))
def warm_start(spark, d):
    first, edges, vertices = _halves(spark, d)
    return A.connected_components(edges, vertices, init=A.connected_components(first, vertices).labels).labels


@add("cc_incremental_two_batches", O.cc("orderpart46"))
def incremental(spark, d):
    """Old components shrink to points; only the new edges between them are solved, then the labels compose."""
    first, edges, vertices = _halves(spark, d)
    old = A.connected_components(first, vertices).labels
    return A.incremental(old, edges.where("src % 4 <> 0"), vertices)


_GROUP_ROWS = "SELECT DISTINCT CAST(n_regionkey AS BIGINT) AS grp, o_custkey * 2 AS src, l_partkey * 2 + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey"


@add("cc_by_group", f"WITH RECURSIVE r AS MATERIALIZED ({_GROUP_ROWS}), {O.base('SELECT grp * 1000000000 + src AS src, grp * 1000000000 + dst AS dst FROM r', 'SELECT CAST(0 AS BIGINT) AS id WHERE false')}, {O._CC} SELECT CAST(id // 1000000000 AS BIGINT) AS grp, id % 1000000000 AS id, comp % 1000000000 AS component FROM cc")
def by_group(spark, d):
    """What customers of one region bought, one graph a region."""
    lines = read(spark, d, "lineitem").select("l_orderkey", "l_partkey")
    people = read(spark, d, "customer").join(read(spark, d, "nation"), F.col("n_nationkey") == F.col("c_nationkey")).select("c_custkey", "n_regionkey")
    orders = read(spark, d, "orders").select("o_orderkey", "o_custkey").join(people, F.col("c_custkey") == F.col("o_custkey"))
    rows = orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).selectExpr("CAST(n_regionkey AS BIGINT) AS grp", "o_custkey * 2 AS src", "l_partkey * 2 + 1 AS dst")
    return A.components_by_group(rows, "grp", 1_000_000_000)


# Trajectories: the same forest after the same round.
def _state(key: str, level: int, k: int) -> Query:
    def query(spark, d):
        seen = {}
        edges, vertices = graph(spark, d, key)
        try:
            A.connected_components(edges, vertices, level=level, max_iter=k, on_round=lambda s, i: seen.__setitem__(i, s))
        except A.NotConverged:
            pass
        return seen[max(seen)].select("id", "f", "gf")

    return query


for _l in (1, 2, 3, 4, 5):
    add(f"round1_state_L{_l}", O.state_after("orderpart46", _l, 1))(_state("orderpart46", _l, 1))
add("round2_state_L5", O.state_after("orderpart46", 5, 2))(_state("orderpart46", 5, 2))


def _trace(spark: SparkSession, d: str, key: str, level: int) -> list[tuple]:
    return [(t["iteration"], t["changed_gf"], t["changed_f"], t["roots"], t["frontier_fraction"]) for t in run(spark, d, key, level=level).trace]


def _changed(key: str, level: int) -> Query:
    return lambda spark, d: spark.createDataFrame([t[:3] for t in _trace(spark, d, key, level)], "iteration int, changed_gf long, changed_f long")


for _l in (1, 2, 3, 4, 5):
    add(f"trace_changed_L{_l}", O.changes("orderpart46", _l))(_changed("orderpart46", _l))
add("trace_changed_L5_eventchain", O.changes("eventchain", 5))(_changed("eventchain", 5))

_LADDER_GRAPHS, _LEVELS = ("orderpart46", "custorder", "eventchain", "pagehref"), (1, 2, 3, 4, 5)
_LADDER = [(g, level) for g in _LADDER_GRAPHS for level in _LEVELS]
_LADDER_SQL = " UNION ALL ".join(f"SELECT * FROM ({O.iterations(g, level)})" for g, level in _LADDER)


def _ladder(spark: SparkSession, d: str) -> DataFrame:
    found = A.rounds_of([graph(spark, d, g) for g in _LADDER_GRAPHS], [{"level": level} for level in _LEVELS])
    rows = [(g, level, n) for g, counts in zip(_LADDER_GRAPHS, found, strict=True) for level, n in zip(_LEVELS, counts, strict=True)]
    return spark.createDataFrame(rows, "graph string, level int, iterations int")


add("iterations_ladder", _LADDER_SQL)(_ladder)


@add("iteration_reduction", f"WITH l AS ({_LADDER_SQL}), r AS (SELECT graph, 1 - max(iterations) FILTER (level = 5) / max(iterations) FILTER (level = 1) AS x FROM l GROUP BY graph) SELECT round(avg(x), 6) AS mean, round(min(x), 6) AS least, round(max(x), 6) AS most FROM r")
def reduction(spark, d):
    rows = _ladder(spark, d).groupBy("graph").agg(F.max(F.when(F.col("level") == 5, F.col("iterations"))).alias("a"), F.max(F.when(F.col("level") == 1, F.col("iterations"))).alias("b"))
    x = 1 - F.col("a") / F.col("b")
    return rows.agg(F.round(F.avg(x), 6).alias("mean"), F.round(F.min(x), 6).alias("least"), F.round(F.max(x), 6).alias("most"))


@add("iteration_ratio_to_rival")
def ratio_to_rival(spark, d):
    """Rounds of the base level and of the final one over those of star hooking (whose ties are ours)."""
    keys = ("orderpart46", "pagehref")
    found = A.rounds_of([graph(spark, d, g) for g in keys], [{"level": 1}, {}, {"method": "star_hooking"}])
    rows = [(g, *counts) for g, counts in zip(keys, found, strict=True)]
    return spark.createDataFrame([(g, a, b, c, a / c, b / c) for g, a, b, c in rows], "graph string, base int, final int, rival int, base_ratio double, final_ratio double")


@add("converged_early")
def converged_early(spark, d):
    """Share of vertices that star hooking retires, round by round."""
    return spark.createDataFrame([(t["iteration"], t["roots"], t["inactive_fraction"]) for t in run(spark, d, "custpart", method="star_hooking").trace], "iteration int, roots long, inactive_fraction double")


@add("roots_per_round", O.trajectory("orderpart46", 5, "SELECT CAST(k AS INT) AS iteration, CAST(count(*) FILTER (f = id) AS BIGINT) AS roots FROM st WHERE k > 0 GROUP BY k"))
def roots_per_round(spark, d):
    return spark.createDataFrame([(t[0], t[3]) for t in _trace(spark, d, "orderpart46", 5)], "iteration int, roots long")


@add("frontier_fraction", O.trajectory("orderpart46", 5, "SELECT CAST(k AS INT) AS iteration, round(avg(cg), 6) AS fraction FROM st WHERE k > 0 GROUP BY k"))
def frontier(spark, d):
    rows = spark.createDataFrame([(t[0], t[4]) for t in _trace(spark, d, "orderpart46", 5)], "iteration int, fraction double")
    return rows.select("iteration", F.round("fraction", 6).alias("fraction"))


@add("first_correct_round", O.trajectory("orderpart46", 5, "SELECT CAST(min(k) AS INT) AS iteration FROM (SELECT k FROM st WHERE k > 0 GROUP BY k HAVING count(DISTINCT f) = (SELECT count(DISTINCT f) FROM st WHERE k = (SELECT max(k) FROM st)) AND bool_and(f = gf))"))
def first_correct(spark, d):
    """The round after which every tree is a finished star: all that follows only finds that out."""
    trace, flat = [], {}
    edges, vertices = graph(spark, d, "orderpart46")
    r = A.connected_components(edges, vertices, on_round=lambda s, k: (trace.append(k), flat.__setitem__(k, s.agg(F.countDistinct("f").alias("n"), F.bool_and(F.col("f") == F.col("gf")).alias("star")).first())))
    last = flat[r.iterations]["n"]
    return spark.createDataFrame([(min(k for k in trace if flat[k]["star"] and flat[k]["n"] == last),)], "iteration int")


_PATH_SQL = "SELECT (a.event_id * 7919) % m AS src, (b.event_id * 7919) % m AS dst FROM events a JOIN events b ON b.event_id = a.event_id + 1 CROSS JOIN (SELECT n + CAST(n % 7919 = 0 AS BIGINT) AS m FROM (SELECT max(event_id) + 1 AS n FROM events))"


def _path_iterations(level: int, path: str = _PATH_SQL) -> str:
    sql = O.trajectory("eventpath", level, "SELECT k FROM st").replace(O.base(GRAPHS["eventpath"].edge_sql, GRAPHS["eventpath"].vertex_sql), O.base(path, "SELECT 0 AS id WHERE false"))
    return f"SELECT CAST({level} AS INT) AS level, (SELECT CAST(max(k) AS INT) FROM ({sql})) AS iterations"


def mixed_path(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """Edges with ids moved by (id * 7919) mod m, one-to-one: m is beyond all ids and no multiple of the prime 7919."""
    m = (ids.agg(F.max("id")).first()[0] or 0) + 1
    m += m % 7919 == 0
    return edges.selectExpr(f"(src * 7919) % {m} AS src", f"(dst * 7919) % {m} AS dst")


@add("order_permuted_vs_natural", " UNION ALL ".join(_path_iterations(level) for level in (1, 4, 5)))
def permuted(spark, d):
    """Rounds on the whole event path with mixed ids: the ordering is part of the input."""
    edges, vertices = graph(spark, d, "eventpath")
    edges = mixed_path(edges, vertices)
    levels = (1, 4, 5)
    found = A.rounds_of([(edges, None)], [{"level": level} for level in levels])[0]
    return spark.createDataFrame(list(zip(levels, found, strict=True)), "level int, iterations int")


# Primitives on the forest of orders: parent = least order of the customer, or the one before.
_STARS_SQL = "SELECT o_orderkey AS id, min(o_orderkey) OVER (PARTITION BY o_custkey) AS f FROM orders"
_CHAINS_SQL = "SELECT o_orderkey AS id, coalesce(lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey), o_orderkey) AS f FROM orders"


def _stars(spark, d):
    return read(spark, d, "orders").select(F.col("o_orderkey").alias("id"), F.min("o_orderkey").over(Window.partitionBy("o_custkey")).alias("f"))


def _chains(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return read(spark, d, "orders").select(F.col("o_orderkey").alias("id"), F.coalesce(F.lag("o_orderkey").over(w), "o_orderkey").alias("f"))


def _sym(key: str) -> str:
    g = GRAPHS[key]
    return O.base(g.edge_sql, g.vertex_sql)


def _symmetric(spark, d, key):
    return E.symmetrize(GRAPHS[key].edges(spark, d))


@add("op_neighbour_min", f"WITH {_sym('orderpart')} SELECT src, min(dst) AS mn FROM e GROUP BY src")
def op_neighbour_min(spark, d):
    edges = _symmetric(spark, d, "orderpart")
    return V.neighbour_min(edges, E.vertices_of(edges).withColumn("gf", F.col("id")))


@add("op_neighbour_min_accum", f"WITH {_sym('orderpart')} SELECT v.id, least(v.id, min(e.dst)) AS mngf FROM v LEFT JOIN e ON e.src = v.id GROUP BY v.id")
def op_accumulate(spark, d):
    edges, vertices = _symmetric(spark, d, "orderpart"), GRAPHS["orderpart"].vertices(spark, d)
    return V.accumulate(vertices.withColumn("mngf", F.col("id")), V.neighbour_min(edges, vertices, "id"))


@add("op_grid_neighbour_min", f"WITH {_sym('orderpart')} SELECT src, min(dst) AS mn FROM e GROUP BY src")
def op_grid(spark, d):
    return V.grid_neighbour_min(_symmetric(spark, d, "orderpart"), GRAPHS["orderpart"].vertices(spark, d), "id", 2, 3)


@add("op_delta_product", f"WITH {_sym('orderpart')} SELECT src, min(dst) AS mn FROM e WHERE dst % 10 = 3 GROUP BY src")
def op_delta(spark, d):
    changed = GRAPHS["orderpart"].vertices(spark, d).where("id % 10 = 3").withColumn("gf", F.col("id"))
    return V.neighbour_min(_symmetric(spark, d, "orderpart"), changed, rows=2000)


@add("op_scatter_min", f"SELECT f AS id, min(id % 997) AS v FROM ({_STARS_SQL}) GROUP BY f")
def op_scatter(spark, d):
    return V.scatter_min(_stars(spark, d).withColumn("v", F.col("id") % 997), "f", "v")


@add("op_gather", f"WITH t AS ({_CHAINS_SQL}) SELECT t.id, t.f, p.f AS gf FROM t JOIN t p ON p.id = t.f")
def op_gather(spark, d):
    return V.gather(_chains(spark, d), "f", "gf").select("id", "f", "gf")


@add("op_gather_hot", f"WITH t AS ({_STARS_SQL}) SELECT t.id, t.f, p.f AS gf FROM t JOIN t p ON p.id = t.f")
def op_gather_hot(spark, d):
    return V.gather(_stars(spark, d), "f", "gf", hot=16).select("id", "f", "gf")


@add("op_shortcut", f"WITH t AS ({_CHAINS_SQL}) SELECT t.id, least(t.f, p.f) AS f FROM t JOIN t p ON p.id = t.f")
def op_shortcut(spark, d):
    return V.ewise_min(V.gather(_chains(spark, d), "f", "gf"), "f", "f", "gf").select("id", "f")


@add("op_ewise_min", f"SELECT id, least(f, id % 1000) AS m FROM ({_CHAINS_SQL})")
def op_ewise_min(spark, d):
    return V.ewise_min(_chains(spark, d).withColumn("x", F.col("id") % 1000), "m", "f", "x").select("id", "m")


@add("op_ewise_changed", f"WITH t AS ({_CHAINS_SQL}) SELECT t.id, p.f AS gf FROM t JOIN t p ON p.id = t.f WHERE p.f <> t.f")
def op_changed(spark, d):
    return V.ewise_changed(V.gather(_chains(spark, d), "f", "gf"), "gf", "f").select("id", "gf")


@add("op_reduce_sum", f"WITH t AS ({_CHAINS_SQL}) SELECT CAST(sum(CASE WHEN p.f <> t.f THEN 1 ELSE 0 END) AS BIGINT) AS changed FROM t JOIN t p ON p.id = t.f")
def op_reduce(spark, d):
    return V.gather(_chains(spark, d), "f", "gf").agg(F.count_if(F.col("gf") != F.col("f")).alias("changed"))


@add("op_nrows", "SELECT count(*) AS n FROM orders")
def op_nrows(spark, d):
    return _chains(spark, d).agg(F.count(F.lit(1)).alias("n"))


_TREE_SQL = f"WITH c AS ({_CHAINS_SQL}), t AS (SELECT c.id, CASE WHEN c.id % 3 = 0 THEN s.f ELSE c.f END AS f FROM c JOIN ({_STARS_SQL}) s ON s.id = c.id), g AS (SELECT t.id, t.f, p.f AS gf FROM t JOIN t p ON p.id = t.f)"


def _mixed(spark, d):
    t = _chains(spark, d).join(_stars(spark, d).select("id", F.col("f").alias("s")), "id").select("id", F.when(F.col("id") % 3 == 0, F.col("s")).otherwise(F.col("f")).alias("f"))
    return V.gather(t, "f", "gf").select("id", "f", "gf")


@add("op_mark_stars", _TREE_SQL + ", bad AS (SELECT id FROM g WHERE f <> gf UNION SELECT gf FROM g WHERE f <> gf), s AS (SELECT g.id, g.f, g.id NOT IN (SELECT id FROM bad) AS s0 FROM g) SELECT a.id, a.s0 AND b.s0 AS star FROM s a JOIN s b ON b.id = a.f")
def op_mark_stars(spark, d):
    return B.mark_stars(_mixed(spark, d)).select("id", "star")


def _singletons(spark, d, key="orderpart46"):
    v = GRAPHS[key].vertices(spark, d)
    return v.select("id", F.col("id").alias("f"), F.col("id").alias("gf"), F.lit(True).alias("star"))


@add("op_hook_conditional", f"WITH {_sym('orderpart46')} SELECT src AS id, min(dst) AS value FROM e GROUP BY src HAVING min(dst) < src")
def op_hook_conditional(spark, d):
    return B.hook_conditional(_symmetric(spark, d, "orderpart46"), _singletons(spark, d), only_stars=True).select("id", "value")


@add("op_hook_unconditional", f"WITH {_sym('orderpart46')}, h AS (SELECT src AS id, min(dst) AS value FROM e GROUP BY src HAVING min(dst) < src) SELECT src AS id, min(dst) AS value FROM e WHERE src NOT IN (SELECT id FROM h WHERE id % 5 = 0) GROUP BY src")
def op_hook_unconditional(spark, d):
    edges, state = _symmetric(spark, d, "orderpart46"), _singletons(spark, d)
    hooked = B.hook_conditional(edges, state, only_stars=True).where("id % 5 = 0").select("id")
    return B.hook_unconditional(edges, state, hooked).select("id", "value")


@add("op_stochastic", O.trajectory("orderpart46", 3, "SELECT id, f FROM st WHERE k = 2", rounds=2))
def op_stochastic(spark, d):
    return _state("orderpart46", 3, 2)(spark, d).select("id", "f")


@add("op_aggressive", O.trajectory("orderpart46", 4, "SELECT id, f FROM st WHERE k = 2", rounds=2))
def op_aggressive(spark, d):
    return _state("orderpart46", 4, 2)(spark, d).select("id", "f")


# Graph statistics and reports.
_STATS = "SELECT '{0}' AS graph, (SELECT count(*) FROM v) AS n, (SELECT count(*) FROM e) AS directed_edges, round((SELECT count(*) FROM e) / (SELECT count(*) FROM v), 6) AS density, count(*) AS components, max(n) AS largest, count(*) FILTER (n = 1) AS isolated FROM (SELECT comp, count(*) AS n FROM cc GROUP BY comp)"
_STAT_GRAPHS = tuple(GRAPHS)


def stats_of(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Statistics of one graph. Its edges are made once and written, as degrees, layout and the count of edges all read them."""
    with Scratch() as scratch:
        edges, _ = scratch.keep(edges)
        labels = scratch.own(A.connected_components(edges, vertices).labels)
        return keep(R.graph_stats(E.symmetrize(edges), vertices, labels))[0]


@add("graph_stats", " UNION ALL ".join(f"SELECT * FROM ({O.labelled(GRAPHS[k].edge_sql, GRAPHS[k].vertex_sql, _STATS.format(k))})" for k in _STAT_GRAPHS))
def graph_stats(spark, d):
    def one(k):
        return stats_of(*graph(spark, d, k)).select(F.lit(k).alias("graph"), "*")

    return reduce(DataFrame.unionByName, A.side_by_side([lambda k=k: one(k) for k in _STAT_GRAPHS]))


@add("degree_hist", f"WITH {_sym('orderpart')} SELECT degree, count(*) AS vertices FROM (SELECT src, count(*) AS degree FROM e GROUP BY src) GROUP BY degree")
def degree_hist(spark, d):
    return R.degree_histogram(_symmetric(spark, d, "orderpart"))


_DENSITY = (1, 26, 46, 50)


def _dense_sql(q: int) -> str:
    g = GRAPHS["orderpart"]
    return O.labelled(g.edge_sql.replace("WHERE true", f"WHERE l_quantity >= {q}"), g.vertex_sql, f"SELECT CAST({q} AS INT) AS least, round((SELECT count(*) FROM e) / (SELECT count(*) FROM v), 6) AS density, count(DISTINCT comp) AS components FROM cc")


@add("density_ladder", " UNION ALL ".join(f"SELECT * FROM ({_dense_sql(q)})" for q in _DENSITY))
def density_ladder(spark, d):
    """One table, edges from few to many: density and components."""

    def one(q):
        edges = E.bipartite(read(spark, d, "lineitem").where(F.col("l_quantity") >= q), "l_orderkey", "l_partkey")
        vertices = GRAPHS["orderpart"].vertices(spark, d)
        stats = R.graph_stats(E.symmetrize(edges), vertices, A.connected_components(edges, vertices).labels)
        return stats.select(F.lit(q).alias("least"), "density", "components")

    return reduce(DataFrame.unionByName, map(one, _DENSITY))


_G3 = "orderpart46"


def _report(name: str, select: str):
    return add(name, O.cc(_G3, select))


@_report("component_sizes", "SELECT comp AS component, count(*) AS n FROM cc GROUP BY comp")
def component_sizes(spark, d):
    return R.component_sizes(run(spark, d, _G3).labels)


@_report("component_size_hist", "SELECT n, count(*) AS components FROM (SELECT comp, count(*) AS n FROM cc GROUP BY comp) GROUP BY n")
def size_hist(spark, d):
    return R.size_histogram(run(spark, d, _G3).labels)


@_report("topk_components", "SELECT comp AS component, count(*) AS n FROM cc GROUP BY comp ORDER BY n DESC, component LIMIT 10")
def topk(spark, d):
    return R.top_components(run(spark, d, _G3).labels, 10)


@_report("largest_component_share", "SELECT round(max(n) / sum(n), 6) AS share FROM (SELECT count(*) AS n FROM cc GROUP BY comp)")
def largest_share(spark, d):
    return R.giant_share(run(spark, d, _G3).labels)


def _with_attributes(spark, d):
    """Component size class by side of the graph and order priority."""
    labels = run(spark, d, _G3).labels
    sizes = labels.join(R.component_sizes(labels), "component")
    orders = read(spark, d, "orders").select((F.col("o_orderkey") * 2).alias("id"), F.col("o_orderpriority").alias("priority"))
    return sizes.join(orders, "id", "left").select(F.when(F.col("id") % 2 == 0, "order").otherwise("part").alias("side"), F.coalesce("priority", F.lit("-")).alias("priority"), "component")


_ATTRIBUTES = "a AS (SELECT CASE WHEN id % 2 = 0 THEN 'order' ELSE 'part' END AS side, coalesce(o_orderpriority, '-') AS priority, comp AS component FROM cc LEFT JOIN orders ON o_orderkey * 2 = id)"


def _attribute_sql(group: str, columns: str) -> str:
    g = GRAPHS[_G3]
    return f"WITH RECURSIVE {O.base(g.edge_sql, g.vertex_sql)}, {O._CC}, {_ATTRIBUTES} SELECT {columns} FROM a GROUP BY {group}"


_REPORT_COLUMNS = "side, priority, count(*) AS vertices, count(DISTINCT component) AS components"


def _count(df):
    return df.agg(F.count(F.lit(1)).alias("vertices"), F.countDistinct("component").alias("components"))


@add("component_rollup", _attribute_sql("ROLLUP (side, priority)", _REPORT_COLUMNS))
def component_rollup(spark, d):
    return _count(_with_attributes(spark, d).rollup("side", "priority"))


@add("component_cube", _attribute_sql("CUBE (side, priority)", _REPORT_COLUMNS))
def component_cube(spark, d):
    return _count(_with_attributes(spark, d).cube("side", "priority"))


@add("component_grouping_sets", _attribute_sql("GROUPING SETS ((side), (priority), ())", _REPORT_COLUMNS))
def component_grouping_sets(spark, d):
    return _count(_with_attributes(spark, d).groupingSets([["side"], ["priority"], []], "side", "priority"))


@_report("component_rank_window", "SELECT id, comp AS component, CAST(row_number() OVER w AS INT) AS rank FROM cc WINDOW w AS (PARTITION BY comp ORDER BY id)")
def rank_window(spark, d):
    return R.rank_members(run(spark, d, _G3).labels, [F.col("id")]).select("id", "component", "rank")


@_report("component_running_total", "SELECT id, CAST(sum(id) OVER (PARTITION BY comp ORDER BY id) AS BIGINT) AS running FROM cc")
def running_total(spark, d):
    return R.rank_members(run(spark, d, _G3).labels, [F.col("id")]).select("id", "running")


@_report("component_ntile", "SELECT id, CAST(ntile(4) OVER (PARTITION BY comp ORDER BY id) AS INT) AS quartile FROM cc")
def ntile(spark, d):
    return R.rank_members(run(spark, d, _G3).labels, [F.col("id")]).select("id", "quartile")


@_report("same_component_pairs", "SELECT id, comp AS representative, CAST(count(*) OVER (PARTITION BY comp) - 1 AS BIGINT) AS partners FROM cc")
def same_component_pairs(spark, d):
    """All pairs of all vertices in linear size: two of them pair up if their representative is the same."""
    labels, _ = keep(run(spark, d, _G3).labels)
    sizes = R.component_sizes(labels).select("component", (F.col("n") - 1).alias("partners"))
    return labels.join(sizes, "component").select("id", F.col("component").alias("representative"), "partners")


@_report("semi_in_giant", "SELECT id FROM cc WHERE comp = (SELECT comp FROM cc GROUP BY comp ORDER BY count(*) DESC, comp LIMIT 1)")
def semi_in_giant(spark, d):
    labels = run(spark, d, _G3).labels
    return labels.join(F.broadcast(R.top_components(labels, 1)), "component", "left_semi").select("id")


@add("anti_isolated", f"WITH {_sym(_G3)} SELECT id FROM v WHERE id NOT IN (SELECT src FROM e)")
def anti_isolated(spark, d):
    edges, vertices = graph(spark, d, _G3)
    return E.isolated(vertices, E.symmetrize(edges))


@add("validate_labels", "SELECT CAST(0 AS BIGINT) AS violations")
def validate(spark, d):
    edges, vertices = graph(spark, d, _G3)
    return R.validate_labels(A.connected_components(edges, vertices).labels, E.symmetrize(edges)).agg(F.count(F.lit(1)).alias("violations"))


@add("methods_agree", "SELECT CAST(0 AS BIGINT) AS differences")
def methods_agree(spark, d):
    a, b = run(spark, d, _G3).labels, run(spark, d, _G3, method="star_hooking").labels
    return R.same_partition(a, b).agg(F.count(F.lit(1)).alias("differences"))


# Edge operators.
def _edge(name: str, key: str):
    g = GRAPHS[key]
    if name not in QUERIES:
        add(name, f"SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM ({g.edge_sql})")(lambda spark, d: g.edges(spark, d).select("src", "dst"))


for _name, _key in [("edges_lead_chain", "eventchain"), ("edges_session_gap", "eventsession"), ("edges_href", "pagehref"), ("edges_host", "pagehost"), ("edges_shared_line", "docline"), ("edges_exact_text", "docexact"), ("edges_props_json", "userk"), ("edges_cosine", "cosine4")]:
    _edge(_name, _key)

for _name, _word in [("edges_union", "UNION"), ("edges_intersect", "INTERSECT"), ("edges_except", "EXCEPT")]:
    add(_name, f"SELECT * FROM ({GRAPHS['orderpart46'].edge_sql}) {_word} SELECT * FROM ({GRAPHS['orderpart50'].edge_sql})")(
        lambda spark, d, w=_word: {"UNION": lambda a, b: a.union(b).distinct(), "INTERSECT": DataFrame.intersect, "EXCEPT": DataFrame.subtract}[w](GRAPHS["orderpart46"].edges(spark, d), GRAPHS["orderpart50"].edges(spark, d))
    )

_DOC_STARS = "SELECT doc_id AS src, min(doc_id) OVER (PARTITION BY text) AS dst FROM documents"


def _doc_stars(spark, d):
    """Every document to the smallest with the same text, itself included (never all pairs of copies)."""
    rows = read(spark, d, "documents").select(F.col("doc_id").alias("src"), F.sha2("text", 256).alias("t"))
    return rows.join(rows.groupBy("t").agg(F.min("src").alias("dst")), "t").select("src", "dst")


add("edges_symmetrize", f"SELECT src, dst FROM ({_DOC_STARS}) WHERE src <> dst UNION SELECT dst, src FROM ({_DOC_STARS}) WHERE src <> dst")(lambda s, d: E.symmetrize(_doc_stars(s, d)))
add("edges_canonical", f"SELECT DISTINCT least(src, dst) AS src, greatest(src, dst) AS dst FROM ({_DOC_STARS}) WHERE src <> dst")(lambda s, d: E.canonical(_doc_stars(s, d)))
add("edges_selfloop_drop", f"SELECT src, dst FROM ({_DOC_STARS}) WHERE src <> dst")(lambda s, d: E.drop_bad(_doc_stars(s, d)))
add("edges_dedup", f"SELECT DISTINCT src, dst FROM ({_DOC_STARS})")(lambda s, d: _doc_stars(s, d).unionByName(_doc_stars(s, d)).distinct())
add("edges_range_join", "SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND abs(date_diff('second', date_trunc('second', a.ts), date_trunc('second', b.ts))) <= 1800 AND a.event_id < b.event_id")(
    lambda s, d: E.near_in_time(read(s, d, "events"), "event_id", "ts", 1800, ["user_id"])
)
add("edges_asof", "SELECT a.event_id AS src, b.event_id AS dst FROM (SELECT * FROM events WHERE event_type = 'purchase') a ASOF JOIN (SELECT * FROM events WHERE event_type = 'view') b ON a.user_id = b.user_id AND a.ts > b.ts")(
    lambda s, d: E.last_before(read(s, d, "events"), "event_id", "ts", ["user_id"], F.col("event_type") == "purchase", F.col("event_type") == "view")
)
add("index_vertices_dense", "SELECT url AS key, CAST(row_number() OVER (ORDER BY url) - 1 AS BIGINT) AS id FROM (SELECT DISTINCT url FROM pages)")(lambda s, d: E.index_vertices(read(s, d, "pages"), "url"))


@add("index_vertices_hash", "SELECT count(*) AS keys, count(*) AS ids FROM (SELECT DISTINCT url FROM pages)")
def hash_ids(spark, d):
    """Keys and the ids they get by hash: as many of each, or the operator stops."""
    return E.index_vertices(read(spark, d, "pages"), "url", "hash").agg(F.count("key").alias("keys"), F.countDistinct("id").alias("ids"))


@add("edges_cosine_banded", SQL["edges_cosine"])
def cosine_banded(spark, d):
    """The form for larger tables: bands of vectors are compared whole, band against band."""
    return E.similar_vectors(read(spark, d, "embeddings"), "vec_id", "embedding", 0.4, block=16384)


# Deduplication and contamination through components.
@add("dedup_keep_one", O.cc("docline", "SELECT comp AS component, arg_min(doc_id, length(text) * -1000000 + doc_id) AS doc_id FROM cc JOIN documents ON doc_id = id GROUP BY comp"))
def dedup_keep_one(spark, d):
    """The longest document of each cluster that shares lines."""
    return R.keep_one(read(spark, d, "documents"), run(spark, d, "docline").labels, "doc_id", -F.length("text"))


@add("dedup_cluster_quality", O.cc("docline", "SELECT comp AS component, count(*) AS labelled, round(avg(quality), 6) AS quality FROM cc JOIN labels ON doc_id = id GROUP BY comp"))
def cluster_quality(spark, d):
    labels = run(spark, d, "docline").labels.withColumnRenamed("id", "doc_id")
    return labels.join(read(spark, d, "labels"), "doc_id").groupBy("component").agg(F.count(F.lit(1)).alias("labelled"), F.round(F.avg("quality"), 6).alias("quality"))


_LINES = "(SELECT k, trim(line, ' ') AS line FROM (SELECT doc_id * 2 AS k, unnest(string_split(text, chr(10))) AS line FROM documents UNION ALL SELECT item_id * 2 + 1, unnest(string_split(text, chr(10))) FROM benchmark) WHERE length(trim(line, ' ')) >= 20)"
_LINE_EDGES = f"WITH r AS (SELECT DISTINCT k, line FROM {_LINES}), m AS (SELECT line, min(k) AS lo FROM r GROUP BY line) SELECT DISTINCT k AS src, lo AS dst FROM r JOIN m USING (line) WHERE k <> lo"


@add("contamination_clusters", O.labelled(_LINE_EDGES, "SELECT doc_id * 2 AS id FROM documents UNION ALL SELECT item_id * 2 + 1 FROM benchmark", "SELECT comp AS component, count(*) FILTER (id % 2 = 0) AS documents, count(*) FILTER (id % 2 = 1) AS items FROM cc GROUP BY comp HAVING count(*) FILTER (id % 2 = 1) > 0 AND count(*) FILTER (id % 2 = 0) > 0"))
def contamination(spark, d):
    lines = lambda t, k: read(spark, d, t).select(k.alias("k"), F.explode(F.split("text", "\n")).alias("line")).select("k", F.trim("line").alias("line")).where(F.length("line") >= 20)
    docs, items = F.col("doc_id") * 2, F.col("item_id") * 2 + 1
    edges = E.shared_value(lines("documents", docs).unionByName(lines("benchmark", items)), "k", "line")
    ids = read(spark, d, "documents").select(docs.alias("id")).unionByName(read(spark, d, "benchmark").select(items.alias("id")))
    labels = A.connected_components(edges, ids).labels
    out = labels.groupBy("component").agg(F.count_if(F.col("id") % 2 == 0).alias("documents"), F.count_if(F.col("id") % 2 == 1).alias("items"))
    return out.where("documents > 0 AND items > 0")


# Streams.
@add("stream_incremental_cc", O.cc("userk"))
def stream_incremental(spark, d):
    events = T.as_stream(read(spark, d, "events"), "ts", 3)
    edges = events.select((F.col("user_id") * 2).alias("src"), (F.get_json_object("props", "$.k").cast("long") * 2 + 1).alias("dst"))
    return T.stream_components(edges)


_KEYED = "SELECT DISTINCT user_id * 1000 + k // 10 AS src, user_id * 1000 + 100 + k % 10 AS dst FROM (SELECT user_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events) WHERE k IS NOT NULL"


@add("stream_state_unionfind", O.labelled(_KEYED, "SELECT CAST(0 AS BIGINT) AS id WHERE false", "SELECT CAST(id // 1000 AS BIGINT) AS key, CAST(id % 1000 AS BIGINT) AS id, CAST(comp % 1000 AS BIGINT) AS component FROM cc"))
def stream_state_unionfind(spark, d):
    """One small graph a user, in the state of the stream: tens against ones of the values seen."""
    k = F.get_json_object("props", "$.k").cast("long")
    rows = T.as_stream(read(spark, d, "events"), "ts", 3).select("user_id", F.floor(k / 10).cast("long").alias("src"), (k % 10 + 100).alias("dst"))
    return T.newest(T.run_now(T.stream_keyed_unionfind(rows, "user_id"), "update"))


def _seconds(df: DataFrame) -> DataFrame:
    return df.withColumn("start", F.unix_timestamp("start"))


@add("stream_window_tumbling", "SELECT CAST(epoch(time_bucket(INTERVAL 1 day, ts, TIMESTAMP '1970-01-01')) AS BIGINT) AS start, count(*) AS n FROM events GROUP BY 1")
def tumbling(spark, d):
    return _seconds(T.run_now(T.windowed_counts(T.as_stream(read(spark, d, "events"), "ts", 3), "1 day"), "complete"))


@add("stream_window_sliding", "SELECT CAST(epoch(b) AS BIGINT) AS start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 12 hour, ts, TIMESTAMP '1970-01-01') - i * INTERVAL 12 hour AS b FROM events, range(0, 2) t(i)) GROUP BY 1")
def sliding(spark, d):
    return _seconds(T.run_now(T.windowed_counts(T.as_stream(read(spark, d, "events"), "ts", 3), "1 day", "12 hours"), "complete"))


@add("stream_session", "SELECT user_id, CAST(epoch(date_trunc('second', min(ts))) AS BIGINT) AS start, count(*) AS n FROM (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 4 hour THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s")
def session(spark, d):
    return _seconds(T.run_now(T.session_counts(T.as_stream(read(spark, d, "events"), "ts", 3), "4 hours"), "complete"))


@add("stream_watermark_late", "SELECT CAST(epoch(b) AS BIGINT) AS start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 1 day, ts, TIMESTAMP '1970-01-01') AS b FROM events) GROUP BY b HAVING b + INTERVAL 1 day <= (SELECT max(ts) FROM events) - INTERVAL 1 hour")
def late(spark, d):
    """The first batch comes again after all others: by then its days are closed and its rows are dropped."""
    events = T.as_stream(read(spark, d, "events"), "ts", 4, replay_first=True)
    return _seconds(T.run_now(T.windowed_counts(events, "1 day", watermark="1 hour"), "append"))


# Functions, sources and sinks.
@add("udf_edge_weight", "SELECT l_orderkey * 2 AS src, l_partkey * 2 + 1 AS dst, round(sum(l_quantity * (1 - l_discount)), 6) AS weight FROM lineitem GROUP BY ALL")
def edge_weight(spark, d):
    rows = read(spark, d, "lineitem").select((F.col("l_orderkey") * 2).alias("src"), (F.col("l_partkey") * 2 + 1).alias("dst"), udfs.weight_pd("l_quantity", "l_discount").alias("w"))
    return rows.groupBy("src", "dst").agg(F.round(F.sum("w"), 6).alias("weight"))


@add("pandas_udf_cosine", "SELECT a.vec_id AS src, b.vec_id AS dst, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def cosine_udf(spark, d):
    v = read(spark, d, "embeddings")
    a, b = v.select(F.col("vec_id").alias("src"), F.col("embedding").alias("a")), v.select(F.col("vec_id").alias("dst"), F.col("embedding").alias("b"))
    return a.join(b, F.col("dst") == F.col("src") + 1).select("src", "dst", F.round(udfs.cosine_pd("a", "b"), 6).alias("cosine"))


@add("udaf_min_label", "SELECT o_custkey, min(o_orderkey) AS least FROM orders GROUP BY o_custkey")
def udaf_min(spark, d):
    return read(spark, d, "orders").groupBy("o_custkey").agg(udfs.min_label_pd("o_orderkey").alias("least"))


@add("udtf_line_edges", "SELECT doc_id, trim(line, ' ') AS line, CAST(length(trim(line, ' ')) AS INT) AS length FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(trim(line, ' ')) >= 20")
def udtf_lines(spark, d):
    spark.udtf.register("line_edges", udfs.LineEdges)
    read(spark, d, "documents").createOrReplaceTempView("documents_for_lines")
    return spark.sql("SELECT doc_id, l.line, l.length FROM documents_for_lines, LATERAL line_edges(text, 20) l")


@add("map_in_arrow_local_contract", O.cc(_G3))
def contract_first(spark, d):
    edges, vertices = graph(spark, d, _G3)
    return A.connected_components(udfs.local_contract(edges), vertices).labels


def _folder(spark, name: str) -> str:
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


_G16_SQL = GRAPHS["nationregion"].edge_sql


@add("sink_parquet_roundtrip", _G16_SQL)
def parquet_roundtrip(spark, d):
    path = _folder(spark, "edges")
    GRAPHS["nationregion"].edges(spark, d).write.parquet(path)
    return S.read_edges(spark, path)


@add("source_orc_edges", _G16_SQL)
def orc_edges(spark, d):
    path = _folder(spark, "edges")
    GRAPHS["nationregion"].edges(spark, d).write.orc(path)
    return S.read_edges(spark, path, "orc")


@add("sink_bucketed_edges", _G16_SQL)
def bucketed(spark, d):
    table = f"edges_{uuid.uuid4().hex}"
    return S.write_edges_bucketed(GRAPHS["nationregion"].edges(spark, d), table, 4)


@add("source_csv_edges", _G16_SQL)
def csv_edges(spark, d):
    path = _folder(spark, "edges")
    GRAPHS["nationregion"].edges(spark, d).write.option("header", True).csv(path)
    return S.read_edges(spark, path, "csv")


@add("source_json_edges", _G16_SQL)
def json_edges(spark, d):
    path = _folder(spark, "edges")
    GRAPHS["nationregion"].edges(spark, d).write.json(path)
    return S.read_edges(spark, path, "json")


@add("source_text_matrix_edges", _G16_SQL)
def text_edges(spark, d):
    path = _folder(spark, "edges")
    rows = GRAPHS["nationregion"].edges(spark, d).select(F.format_string("%d %d", "src", "dst").alias("value"), F.lit(2).alias("at"))
    top = spark.createDataFrame([("% a comment", 0), ("1000 1000 25", 1)], "value string, at int")
    top.unionByName(rows).coalesce(1).sortWithinPartitions("at").select("value").write.text(path)
    return S.read_edges(spark, path, "coordinate")


#: A round in one pass, from ``{old}`` to ``{new}``: the edges have a loop at every vertex, which brings its own label along.
ROUND = """INSERT OVERWRITE {new}
      WITH p AS (SELECT /*+ SHUFFLE_HASH(s) */ e.src, min(s.l) AS m, max(CASE WHEN e.src = e.dst THEN s.l END) AS l FROM {edges} e JOIN {old} s ON s.id = e.dst GROUP BY e.src),
      sent AS (SELECT inline(array(struct(src AS id, m AS v, l AS l), struct(l AS id, m AS v, CAST(NULL AS BIGINT) AS l))) FROM p),
      h AS (SELECT id, min(v) AS n, max(l) AS l FROM sent GROUP BY id)
      SELECT /*+ SHUFFLE_HASH(q) */ h.id, q.n AS l, h.l AS was FROM h JOIN h q ON q.id = h.n"""

SCRIPT = """
BEGIN
  DECLARE moved BIGINT DEFAULT 1;
  WHILE moved > 0 DO
    {there};
    {back};
    SET moved = (SELECT count(*) FROM {state} WHERE l <> was);
  END WHILE;
END
"""


def _script(key: str) -> Query:
    def query(spark, d):
        """The loop in SQL scripting: a label takes the least neighbour's, so does the vertex it names, and both go on to their label's label."""
        names = {k: f"{k}_{uuid.uuid4().hex}" for k in ("state", "next")}
        with Scratch() as scratch:
            layout, ids, _ = A.prepare(*graph(spark, d, key), scratch, loops=True)
            try:
                start = ids.select("id", F.col("id").alias("l"), F.col("id").alias("was"))
                start.write.saveAsTable(names["state"])
                start.limit(0).write.saveAsTable(names["next"])
                there, back = (ROUND.format(edges=layout.table, old=names[x], new=names[y]) for x, y in (("state", "next"), ("next", "state")))
                spark.sql(SCRIPT.format(there=there, back=back, state=names["state"]))
            finally:
                layout.drop()
        return spark.table(names["state"]).select("id", F.col("l").alias("component"))

    return query


add("sql_script_cc", O.cc("nationregion"))(_script("nationregion"))
add("sql_script_cc_orderpart46", O.cc(_G3))(_script(_G3))


from . import experiments  # noqa: E402, F401  (registers its queries)
