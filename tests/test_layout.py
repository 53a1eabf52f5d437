"""Edges stay where they are: plans of every kind of round, hubs, and what a run leaves behind."""

import os
import re

import pytest
from pyspark.sql import functions as F
from test_components import frames, labels_of, reference

from pointerforest.functions import udfs
from pointerforest.operators import accelerated as A
from pointerforest.operators import baselines as B
from pointerforest.operators import edges as E
from pointerforest.operators import reports as R
from pointerforest.plans import layout as L
from pointerforest.plans.store import Scratch, shared_folder
from pointerforest.sources.edges import read_edges
from pointerforest.streaming import components as T


def node_lines(df):
    """(depth, text) of the physical plan's nodes."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return [(len(re.match(r"[\s:+\-|]*", x).group()), x) for x in text.split("\n") if x.strip()]


def shuffles_of_edges(df, table):
    """Exchanges between the scan of the edges and the first join or aggregation above it."""
    lines = node_lines(df)
    bad = 0
    for i, (depth, text) in enumerate(lines):
        if "Scan parquet" in text and table in text:
            for d, up in reversed(lines[:i]):
                if d < depth:
                    depth = d
                    if "Exchange" in up:
                        bad += 1
                    if "Join" in up or "Aggregate" in up:
                        break
    return bad


ROUNDS = [dict(level=1), dict(level=1, tie="hash"), dict(level=2), dict(level=3), dict(level=4), dict(level=5, product="dense"), dict(level=5, product="sparse"), dict(hook_depth=3)]


@pytest.mark.parametrize("few", [True, False], ids=["broadcast", "shuffled"])
@pytest.mark.parametrize("hub", [None, 4], ids=["plain", "hubs"])
def test_no_round_shuffles_the_edges(spark, monkeypatch, few, hub):
    assert spark.conf.get("spark.sql.adaptive.enabled") == "true"
    monkeypatch.setattr(L, "BROADCAST_ROWS", 10**6 if few else 0)
    was = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1 if not few else was)
    try:
        edges = spark.range(400).select(F.col("id").alias("src"), (F.col("id") * 7 % 40).alias("dst"))
        with Scratch() as scratch:
            layout, ids, n = A.prepare(edges, None, scratch, hub)
            assert (layout.hubs is not None) == (hub is not None)
            state, _ = scratch.keep(A.start_state(ids, None, 0).withColumn("gf_prev", F.lit(-1).cast("long")).withColumn("f_prev", F.col("f")))
            table = layout.table
            for options in ROUNDS:
                for first in (True, False):
                    df, _ = A.one_round(layout, state, A.Options(**options), first=first, changed=n, n=n)
                    assert not shuffles_of_edges(df, layout.path.rsplit("/", 1)[1]), (options, first)
            star = B.mark_stars(state.select("id", "f", "gf"))
            assert not shuffles_of_edges(B.hook_conditional(layout, star, only_stars=True, rows=n), layout.path.rsplit("/", 1)[1])
            assert not shuffles_of_edges(B.outside(layout, star, rows=n), layout.path.rsplit("/", 1)[1])
            assert shuffles_of_edges(layout.edges.repartition("src").groupBy("src").count(), layout.path.rsplit("/", 1)[1])  # the test can fail
            layout.drop()
            assert not spark.catalog.tableExists(table)
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", was)


def test_a_hub_fills_several_buckets(spark):
    edges = spark.range(1, 20_001).select(F.lit(0).cast("long").alias("src"), F.col("id").alias("dst"))
    with Scratch() as scratch:
        layout, _, n = A.prepare(edges, None, scratch, 1000)
        assert n == 20_001 and layout.n_hubs == 1 and layout.edges.count() == 40_000
        at_hub = layout.edges.where("dst = 0").groupBy(F.input_file_name().alias("bucket")).count().collect()
        assert len(at_hub) > 1 and max(r["count"] for r in at_hub) < 15_000
        layout.drop()
    assert A.connected_components(edges, hub_edges=1000).labels.agg(F.max("component")).first()[0] == 0
    assert B.star_hooking_components(edges, hub_edges=1000).labels.agg(F.max("component")).first()[0] == 0


def test_a_run_leaves_only_what_its_result_reads(spark):
    folder = shared_folder(spark).removeprefix("file:")
    before = set(os.listdir(folder))
    for method in ("accelerated", "star_hooking", "label_propagation", "bfs", "hybrid"):
        run = A.connected_components(*frames(spark, range(12), [(0, 1), (1, 2), (5, 6), (7, 8)]), method=method)
        assert labels_of(run) == reference(range(12), [(0, 1), (1, 2), (5, 6), (7, 8)])
        left = set(os.listdir(folder)) - before
        assert len(left) <= 2, (method, left)  # the labels (of the hybrid: and those of its second part)
        before |= left


@pytest.fixture
def written(monkeypatch):
    """Schemas of the tables that runs write."""
    from pointerforest.plans import store

    seen, stored = [], store.stored
    monkeypatch.setattr(store, "stored", lambda df: seen.append(df.columns) or stored(df))
    return seen


@pytest.mark.parametrize("hub", [None, 3])
def test_label_propagation_does_several_rounds_a_job(spark, written, hub):
    """As many rounds as the path is long, of a hub too; some null ends and loops; far fewer tables."""
    edges = [(i, i + 1) for i in range(20)] + [(40, i) for i in range(41, 50)] + [(7, 7), (60, None), (None, 61)]
    e = spark.createDataFrame(edges, "src long, dst long")
    real = [x for x in edges if None not in x]
    for local, most in ((False, 6), (True, 3)):
        written.clear()
        run = A.connected_components(e.coalesce(1) if local else e, spark.range(64), method="label_propagation", local=local, hub_edges=hub)
        assert labels_of(run) == reference(range(64), real)
        assert run.iterations == (2 if local else 21) and run.trace[-1]["changed"] == 0
        assert len(written) <= most
    with pytest.raises(A.NotConverged):
        A.connected_components(e, method="label_propagation", max_iter=20)
    none = spark.createDataFrame([], "src long, dst long")
    assert A.connected_components(none, method="label_propagation").labels.count() == 0
    assert labels_of(A.connected_components(e.where("src IS NULL OR dst IS NULL"), method="label_propagation", local=True)) == {60: 60, 61: 61}


def test_a_chain_of_events_needs_few_jobs(spark, written):
    from conftest import SF

    from pointerforest.workloads.queries import QUERIES

    QUERIES["cc_labelprop_chain"](spark, SF)
    assert len(written) <= 3


def test_both_methods_start_from_one_layout(spark, monkeypatch):
    """It is made once, and the rival, which takes finished trees out, leaves it whole."""
    from conftest import SF

    from pointerforest.workloads import experiments as X

    edges = [(i, i + 1) for i in range(0, 40, 2)] + [(i, i + 1) for i in range(50, 60)]
    with Scratch() as scratch:
        layout, ids, n = A.prepare(*frames(spark, range(64), edges), scratch)
        for rounds in (B.star_hooking_on, A.rounds_on, B.star_hooking_on):
            assert labels_of(rounds(layout, ids, n)) == reference(range(64), edges)
            assert layout.edges.count() == 2 * len(edges)
        layout.drop()
    made, write = [], L._write
    monkeypatch.setattr(L, "_write", lambda *a, **k: made.append(k.get("fresh", False)) or write(*a, **k))
    a, b, ratio, products, rival_products, rows, rival_rows = X.against_rival(spark, SF, "custorder")
    assert made.count(True) == 1 and ratio == b / a and 0 < products < rival_products and 0 < rows < rival_rows


def test_density_reads_the_lines_once(spark, duck, monkeypatch):
    """Every bound keeps all of its edges, also those of which a smaller line comes first."""
    from conftest import SF

    from pointerforest.workloads import experiments as X

    seen = []
    monkeypatch.setattr(X, "against_rival", lambda spark, d, key, edges, repeat: seen.append((edges.count(), edges.inputFiles())) or (1.0, 1.0, 1.0, 1, 1, 1, 1))
    got = X.density_speed(spark, SF).collect()
    n = duck.sql("SELECT (SELECT count(*) FROM orders) + (SELECT count(*) FROM part)").fetchall()[0][0]
    for r, (m, files) in zip(got, seen, strict=True):
        assert m == duck.sql(f"SELECT count(*) FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem WHERE l_quantity >= {r['least']})").fetchall()[0][0]
        assert r["density"] == 2 * m / n and not any("lineitem" in f for f in files)


def test_copies_are_read_off_one_stored_graph(spark, duck, monkeypatch):
    """The lines are read and made distinct once for all sizes; every size is solved in full, with its right labels."""
    from conftest import SF

    from pointerforest.workloads import experiments as X

    seen, solve = [], A.connected_components

    def solved(edges, vertices, **options):
        out = solve(edges, vertices, **options)
        sizes = out.labels.groupBy("component").count().groupBy("count").count().collect()
        seen.append((edges.inputFiles() + vertices.inputFiles(), edges.distinct().count(), vertices.count(), {r[0]: r[1] for r in sizes}))
        return out

    monkeypatch.setattr(A, "connected_components", solved)
    got = X.replicated_scale(spark, SF).collect()
    m = duck.sql("SELECT count(*) FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem)").fetchall()[0][0]
    n = duck.sql("SELECT (SELECT count(*) FROM orders) + (SELECT count(*) FROM part)").fetchall()[0][0]
    assert [r["copies"] for r in got] == [1, 4, 8] and len({r["iterations"] for r in got}) == 1
    for r, (files, edges, vertices, sizes) in zip(got, seen, strict=True):
        assert r["edges"] == edges == m * r["copies"] and vertices == n * r["copies"]
        assert sizes == {size: k * r["copies"] for size, k in seen[0][3].items()}
        assert files and not any(t in f for f in files for t in ("lineitem", "orders", "part.parquet"))


def test_simple_edges_are_laid_out_as_they_are(spark):
    edges = [(i, i + 1) for i in range(0, 40, 2)] + [(50, i) for i in range(51, 80)]
    for hub in (None, 8):  # with and without a vertex dealt to several buckets
        for simple in (False, True):
            with Scratch() as scratch:
                layout, _, n = A.prepare(*frames(spark, range(90), edges), scratch, hub, simple=simple)
                assert n == 90 and sorted(map(tuple, layout.edges.select("src", "dst").collect())) == sorted(edges + [(b, a) for a, b in edges])
                layout.drop()
            assert labels_of(A.connected_components(*frames(spark, range(90), edges), hub_edges=hub, simple=simple)) == reference(range(90), edges)


@pytest.mark.parametrize("tie", A.TIES)
def test_ties_lead_to_the_same_components(spark, tie):
    edges = [(i, (i * 17 + 5) % 60) for i in range(50)] + [(i, i + 1) for i in range(40, 59)]
    for level in (1, 2):
        assert labels_of(A.connected_components(*frames(spark, range(60), edges), level=level, tie=tie)) == reference(range(60), edges)
    with pytest.raises(ValueError):
        A.Options(level=5, tie="max")


@pytest.mark.parametrize("length", [1, 2, 3, 64, 65, 100, 200])
def test_height_of_a_chain(spark, length):
    state = spark.range(length).select("id", F.greatest(F.col("id") - 1, F.lit(0)).alias("f"))
    assert R.forest_height(state) == length - 1


def test_height_of_a_cycle_is_an_error(spark):
    with pytest.raises(ValueError):
        R.forest_height(spark.createDataFrame([(0, 1), (1, 0), (2, 2)], "id long, f long"))


def test_coordinate_files(spark, tmp_path):
    """The size line is the first that is no comment, whatever weights follow it."""
    (tmp_path / "a b.mtx").write_text("%%Matrix\n% x\n9 9 3\n1 2 5\n2 3 100\n4 5 1\n")
    (tmp_path / "c.mtx").write_text("7 7 2\n6 7\n7 7 2\n")
    got = sorted(map(tuple, read_edges(spark, str(tmp_path), "coordinate").collect()))
    assert got == [(1, 2), (2, 3), (4, 5), (6, 7), (7, 7)]
    (tmp_path / "e").mkdir()
    (tmp_path / "e" / "none.mtx").write_text("% only a comment\n")
    assert read_edges(spark, str(tmp_path / "e"), "coordinate").collect() == []


def test_ids_of_groups_and_hashes_are_checked(spark):
    bad = spark.createDataFrame([(1, 5, 100)], "g long, src long, dst long")
    with pytest.raises(Exception, match="is not in 0"):
        A.components_by_group(bad, "g", 100).collect()
    assert {tuple(r) for r in A.components_by_group(bad, "g", 101).collect()} == {(1, 5, 5), (1, 100, 5)}
    twice = spark.createDataFrame([("a", 1), ("b", 1), ("c", 2)], "key string, id long")
    with pytest.raises(ValueError, match="share an id"):
        E.checked_ids(twice)


def test_ranks_over_partitions_of_one_component(spark):
    labels = spark.range(1000).select("id", F.when(F.col("id") % 10 < 9, 0).otherwise(F.col("id") % 7).cast("long").alias("component"))
    got = {r["id"]: (r["rank"], r["running"], r["quartile"]) for r in R.rank_members(labels, [-F.col("id")]).collect()}
    labels.createOrReplaceTempView("l")
    want = spark.sql("SELECT id, row_number() OVER w AS rank, sum(id) OVER (PARTITION BY component ORDER BY -id ROWS UNBOUNDED PRECEDING) AS running, ntile(4) OVER w AS quartile FROM l WINDOW w AS (PARTITION BY component ORDER BY -id)")
    assert got == {r["id"]: (r["rank"], r["running"], r["quartile"]) for r in want.collect()}


def test_local_contract_in_little_room(spark):
    edges = [(i, (i * 13 + 1) % 300) for i in range(250)]
    e, v = frames(spark, range(300), edges)
    e = e.union(spark.createDataFrame([(None, 4)], "src long, dst long"))
    for most in (20, 10**6):
        small = udfs.local_contract(e.coalesce(1).repartition(2), most=most)
        assert labels_of(A.connected_components(small, v)) == reference(range(300), edges)


def test_labels_go_on_after_a_restart(spark, tmp_path):
    """The same folders, more files: what was known is read from the last version, and versions do not pile up."""
    source, store, progress = (str(tmp_path / x) for x in ("in", "labels", "progress"))
    parts = [[(1, 2), (3, 4)], [(2, 3)], [(9, 8), (4, 9)], [(20, 21)]]
    for k, p in enumerate(parts):
        spark.createDataFrame(p, "src long, dst long").coalesce(1).write.mode("append").parquet(source)
        stream = spark.readStream.schema("src long, dst long").parquet(source)
        got = T.stream_components(stream, store, progress)
        seen = [e for q in parts[: k + 1] for e in q]
        assert {r["id"]: r["component"] for r in got.collect()} == reference([x for e in seen for x in e], seen)
    assert len(T.LabelStore(spark, store).versions()) <= 3


def test_a_round_of_the_rival_writes_two_tables(spark, written):
    """What was hooked, with its marks, and the new state; the marks had a table of their own before."""
    edges = [(0, 3), (3, 1), (1, 2), (5, 6)]
    run = B.star_hooking_components(*frames(spark, range(8), edges), prune_converged=False)
    assert labels_of(run) == reference(range(8), edges)
    assert len(written) == 2 + 2 * run.iterations  # degrees and labels besides
