"""Reports on labels, checks of forests and labels, and statistics of graphs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.store import Scratch, keep


def component_sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy("component").agg(F.count(F.lit(1)).alias("n"))


def size_histogram(labels: DataFrame) -> DataFrame:
    return component_sizes(labels).groupBy("n").agg(F.count(F.lit(1)).alias("components"))


def top_components(labels: DataFrame, k: int) -> DataFrame:
    return component_sizes(labels).orderBy(F.desc("n"), "component").limit(k)


def giant_share(labels: DataFrame) -> DataFrame:
    return component_sizes(labels).agg(F.round(F.max("n") / F.sum("n"), 6).alias("share"))


def keep_one(df: DataFrame, labels: DataFrame, key: str, best: Column) -> DataFrame:
    """One row id per component: least ``best``, then least id."""
    rows = df.join(labels.withColumnRenamed("id", key), key)
    return rows.groupBy("component").agg(F.min(F.struct(best.alias("b"), F.col(key).alias("k"))).alias("m")).select("component", F.col("m.k").alias(key))


def graph_stats(edges: DataFrame, vertices: DataFrame, labels: DataFrame) -> DataFrame:
    """n, directed_edges, density, components, largest, isolated: one row. Edges are symmetric."""
    m = edges.agg(F.count(F.lit(1)).alias("directed_edges"))
    sizes = component_sizes(labels).agg(F.count(F.lit(1)).alias("components"), F.max("n").alias("largest"), F.sum("n").alias("n"), F.count_if(F.col("n") == 1).alias("isolated"))
    out = sizes.join(F.broadcast(m))  # one row each
    return out.select("n", "directed_edges", F.round(F.col("directed_edges") / F.col("n"), 6).alias("density"), "components", "largest", "isolated")


def degree_histogram(edges: DataFrame) -> DataFrame:
    degree = edges.groupBy("src").agg(F.count(F.lit(1)).alias("degree"))
    return degree.groupBy("degree").agg(F.count(F.lit(1)).alias("vertices"))


def rank_members(labels: DataFrame, order: list[Column]) -> DataFrame:
    """Rank, running sum of ids and quartile of members inside their component, for components of any size.

    Members are sorted by (component, order) into range partitions, so that a giant
    component lies in many. Inside a partition they are numbered by a window; what the
    partitions before hold of the same component is added from one row per (component,
    partition).
    """
    keys = [c.alias(f"_o{i}") for i, c in enumerate(order)]
    names = ["component", *[f"_o{i}" for i in range(len(order))], "id"]
    rows, _ = keep(labels.select("id", "component", *keys).repartitionByRange(*names).withColumn("_p", F.spark_partition_id()))
    w = Window.partitionBy("component", "_p").orderBy(*names[1:])
    run = w.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    inside = rows.select("id", "component", "_p", F.row_number().over(w).alias("_r"), F.sum("id").over(run).alias("_s"))
    parts = rows.groupBy("component", "_p").agg(F.count(F.lit(1)).alias("_n"), F.sum("id").alias("_t"))
    before = Window.partitionBy("component").orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy("component")
    zero = F.lit(0).cast("long")
    parts = parts.select("component", "_p", F.coalesce(F.sum("_n").over(before), zero).alias("_nb"), F.coalesce(F.sum("_t").over(before), zero).alias("_tb"), F.sum("_n").over(whole).alias("_all"))
    out = inside.join(parts, ["component", "_p"])
    rank = F.col("_r") + F.col("_nb")
    # ntile(4): the first (n mod 4) quarters have one member more.
    each, more = F.floor(F.col("_all") / 4), F.col("_all") % 4
    long = more * (each + 1)
    quartile = F.when(rank <= long, F.floor((rank - 1) / (each + 1))).otherwise(more + F.floor((rank - 1 - long) / F.greatest(each, F.lit(1)))) + 1
    return out.select("id", "component", rank.cast("int").alias("rank"), (F.col("_s") + F.col("_tb")).alias("running"), quartile.cast("int").alias("quartile"))


def validate_forest(state: DataFrame) -> DataFrame:
    """Vertices whose parent is larger than they are or does not exist."""
    bad = state.where("f > id").select("id", F.lit("parent is larger").alias("problem"))
    parents = state.select(F.col("id").alias("_p"))
    lost = state.join(parents, state["f"] == parents["_p"], "left_anti").select("id", F.lit("no such parent").alias("problem"))
    return bad.unionByName(lost)


def validate_labels(labels: DataFrame, edges: DataFrame) -> DataFrame:
    """Edges across components, and components not named by their smallest id."""
    a, b = labels.select(F.col("id").alias("src"), F.col("component").alias("ca")), labels.select(F.col("id").alias("dst"), F.col("component").alias("cb"))
    torn = edges.join(a, "src").join(b, "dst").where("ca <> cb").select("src", "dst")
    named = labels.groupBy("component").agg(F.min("id").alias("m")).where("m <> component").select(F.col("component").alias("src"), F.col("m").alias("dst"))
    return torn.unionByName(named)


def same_partition(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows where two labelings disagree about who belongs together; none if they agree."""
    both = a.select("id", F.col("component").alias("x")).join(b.select("id", F.col("component").alias("y")), "id", "full").select("x", "y").distinct()
    twice = lambda c: both.groupBy(c).agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(F.col(c).alias("component"))
    return twice("x").unionByName(twice("y"))


def forest_height(state: DataFrame) -> int:
    """Largest number of steps to a root, however large: ancestors double, then the last steps are found bit by bit.

    A chain of h steps takes 2 log2(h) self-joins. Only vertices that still have such an ancestor are
    kept, so a flat forest costs one pass. A cycle, or a parent that is no vertex, is an error.
    """
    with Scratch() as scratch:
        below = state.where("f <> id").select("id", F.col("f").alias("to"))
        parents = state.select(F.col("id").alias("_p"), F.when(F.col("f") != F.col("id"), F.col("f")).alias("_t"))
        first, seen = scratch.keep(below.join(parents, below["to"] == parents["_p"], "left"), n=F.count(F.lit(1)), lost=F.count_if(F.col("_p").isNull()), more=F.count_if(F.col("_t").isNotNull()))
        if seen["lost"]:
            raise ValueError("a parent is no vertex")
        if not seen["n"]:
            return 0
        # jumps[k]: the ancestor 2**k steps up, of vertices that have one.
        jumps, n, more = [first.select("id", "to")], seen["n"], seen["more"]
        up = first.where("_t IS NOT NULL").select("id", F.col("_t").alias("to"))
        while more:
            jumps.append(up)
            if 2 ** (len(jumps) - 1) > n:
                raise ValueError("the parents form a cycle")
            up, seen = scratch.keep(_jump(up, up), more=F.count(F.lit(1)))
            more = seen["more"]
        height, at = 2 ** (len(jumps) - 1), jumps[-1]
        for k in reversed(range(len(jumps) - 1)):
            ahead, seen = scratch.keep(_jump(at, jumps[k]), n=F.count(F.lit(1)))
            if seen["n"]:
                height, at = height + 2**k, ahead
        return height


def _jump(at: DataFrame, by: DataFrame) -> DataFrame:
    """(id, to): each vertex goes on from where it is, if it can."""
    step = by.select(F.col("id").alias("_p"), F.col("to").alias("_t"))
    return at.join(step, at["to"] == step["_p"]).select("id", F.col("_t").alias("to"))


def roots(state: DataFrame) -> DataFrame:
    return state.where("f = id").select("id")


def shuffled(spark: SparkSession, since: int = -1) -> tuple[int, int, int]:
    """(records, bytes) written to shuffles by the stages after number ``since``, and the last stage's number.

    The session remembers its last 1,000 stages or so: measure one run at a time.
    """
    sc = spark.sparkContext
    none = sc._gateway.new_array(sc._jvm.double, 0)
    stages = sc._jsc.sc().statusStore().stageList(None, False, False, none, sc._jvm.java.util.ArrayList())
    records, size, last = 0, 0, since
    for i in range(stages.size()):
        stage = stages.apply(i)
        if stage.stageId() > since:
            records, size, last = records + stage.shuffleWriteRecords(), size + stage.shuffleWriteBytes(), max(last, stage.stageId())
    return records, size, last
