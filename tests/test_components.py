"""Methods on hand-made and random graphs, against union-find."""

import random

import numpy as np
import pytest

from pointerforest.operators import accelerated as A
from pointerforest.operators import baselines as B
from pointerforest.operators import edges as E
from pointerforest.operators import reports as R
from pointerforest.operators import vectors as V
from pointerforest.plans.store import Scratch


def reference(vertices, edges):
    parent = {v: v for v in vertices}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        parent.setdefault(a, a), parent.setdefault(b, b)
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {v: find(v) for v in parent}


def frames(spark, vertices, edges):
    return spark.createDataFrame(edges, "src long, dst long"), spark.createDataFrame([(v,) for v in vertices], "id long")


def labels_of(run):
    return {r["id"]: r["component"] for r in run.labels.collect()}


PATH = [(i, i + 1) for i in range(7)]


def test_path_of_eight_gives_the_worked_trace(spark):
    states = {}
    e, v = frames(spark, range(8), PATH)
    run = A.connected_components(e, v, on_round=lambda s, k: states.__setitem__(k, [tuple(r) for r in s.select("id", "f", "gf").orderBy("id").collect()]))
    assert [f for _, f, _ in states[1]] == [0, 0, 1, 2, 3, 4, 5, 6]
    assert [f for _, f, _ in states[2]] == [0, 0, 0, 0, 1, 2, 3, 4]
    assert [g for _, _, g in states[2]] == [0, 0, 0, 0, 0, 0, 0, 1]
    assert [f for _, f, _ in states[3]] == [0] * 8
    assert [t["changed_gf"] for t in run.trace] == [7, 5, 1, 0]
    assert all(b["roots"] <= a["roots"] for a, b in zip(run.trace, run.trace[1:], strict=False))


@pytest.mark.parametrize(("level", "rounds"), [(1, 2), (4, 3), (5, 2)])
def test_path_of_three_early_termination(spark, level, rounds):
    e, v = frames(spark, range(3), [(0, 1), (1, 2)])
    assert A.connected_components(e, v, level=level).iterations == rounds


def test_grandparents_may_rest_too_early_below_level_four():
    for level in (1, 2, 3):
        with pytest.raises(ValueError):
            A.Options(level=level, stop="gf")


VARIANTS = [dict(level=k) for k in (1, 2, 3, 4, 5)] + [dict(hook_depth=1), dict(hook_depth=3), dict(product="sparse"), dict(product="dense", grid=(2, 2)), dict(gather="hot"), dict(extra_shortcut=True, stop="f")] + [dict(method=m) for m in B.METHODS] + [dict(method="star_hooking", prune_converged=False), dict(method="sv_full", final_shortcut=False)]


@pytest.mark.parametrize("options", VARIANTS, ids=str)
def test_all_methods_agree_with_union_find(spark, options):
    rng = random.Random(5)
    n = 40
    vertices = list(range(n))
    edges = [(rng.randrange(n), rng.randrange(n)) for _ in range(34)]
    e, v = frames(spark, vertices, edges)
    assert labels_of(A.connected_components(e, v, **options)) == reference(vertices, edges)


def test_untidy_edges(spark):
    e = spark.createDataFrame([(1, 1), (2, 3), (3, 2), (2, 3), (None, 4), (5, None), (-7, 10**15)], "src long, dst long")
    v = spark.createDataFrame([(1,), (9,)], "id long")
    got = labels_of(A.connected_components(e, v))
    assert got == {1: 1, 2: 2, 3: 2, 4: 4, 5: 5, 9: 9, -7: -7, 10**15: -7}


def test_empty_graph(spark):
    e, v = frames(spark, [], [])
    assert labels_of(A.connected_components(e, v)) == {}
    e, v = frames(spark, [3], [])
    assert labels_of(A.connected_components(e, v)) == {3: 3}


@pytest.mark.parametrize("center", [0, 50])
def test_stars_and_bipartite(spark, center):
    edges = [(center, i) for i in range(51) if i != center]
    e, v = frames(spark, range(51), edges)
    assert set(labels_of(A.connected_components(e, v)).values()) == {0}
    e, v = frames(spark, range(7), [(i, 3 + j) for i in range(3) for j in range(4)])
    assert set(labels_of(B.star_hooking_components(e, v)).values()) == {0}


def test_star_hooking_makes_no_cycle(spark):
    """Singletons s < x < y with edges s-y and x-y: y hooks below s, and x must not hook y's star at the same time."""
    e, v = frames(spark, [1, 2, 3], [(1, 3), (2, 3)])
    assert set(labels_of(B.star_hooking_components(e, v)).values()) == {1}


def test_max_iter_is_an_error(spark):
    e, v = frames(spark, range(8), PATH)
    with pytest.raises(A.NotConverged):
        A.connected_components(e, v, max_iter=2)


def test_warm_start_and_permuted_ids(spark):
    rng = random.Random(2)
    edges = [(rng.randrange(60), rng.randrange(60)) for _ in range(50)]
    e, v = frames(spark, range(60), edges)
    first = A.connected_components(e.where("src % 2 = 0"), v).labels
    assert labels_of(A.connected_components(e, v, init=first)) == reference(range(60), edges)
    moved = [((a * 37) % 61, (b * 37) % 61) for a, b in edges]
    e2, v2 = frames(spark, [(i * 37) % 61 for i in range(60)], moved)
    a = {frozenset(k for k, c in x.items() if c == r) for x in [reference(range(60), edges)] for r in set(x.values())}
    got = labels_of(A.connected_components(e2, v2))
    b = {frozenset(k for k, c in got.items() if c == r) for r in set(got.values())}
    assert {frozenset((k * 37) % 61 for k in s) for s in a} == b


def test_sparse_product_keeps_the_trajectory(spark):
    rng = random.Random(3)
    edges = [(rng.randrange(200), rng.randrange(200)) for _ in range(190)]
    e, v = frames(spark, range(200), edges)
    trace = lambda **o: [(t["changed_gf"], t["changed_f"], t["roots"]) for t in A.connected_components(e, v, **o).trace]
    assert trace(product="dense") == trace(product="sparse") == trace(gather="hot") == trace(product="dense", grid=(3, 2))


def test_checks_find_faults(spark):
    bad = spark.createDataFrame([(1, 2), (2, 9)], "id long, f long")
    assert {r["problem"] for r in R.validate_forest(bad).collect()} == {"parent is larger", "no such parent"}
    a = spark.createDataFrame([(1, 1), (2, 1)], "id long, component long")
    b = spark.createDataFrame([(1, 1), (2, 2)], "id long, component long")
    assert R.same_partition(a, a).count() == 0 and R.same_partition(a, b).count() > 0
    chain = spark.createDataFrame([(0, 0), (1, 0), (2, 1), (3, 2)], "id long, f long")
    assert R.forest_height(chain) == 3
    assert V.gather(chain, "f", "gf", hot=1).count() == 4


def test_index_and_relabel(spark):
    got = {r["key"]: r["id"] for r in E.index_vertices(spark.createDataFrame([("b",), ("a",), ("c",), ("a",), (None,)], "k string"), "k").collect()}
    assert got == {"a": 0, "b": 1, "c": 2}


def test_blocks_of_vectors_miss_no_similar_pair(spark):
    rng = np.random.default_rng(4)
    v = rng.standard_normal((300, 16)).astype("float32")
    v[7] = 0
    v[20:40] = v[19]
    df = spark.createDataFrame([(i * 3, x.tolist()) for i, x in enumerate(v)] + [(1, None)], "id long, v array<float>")
    u = v.astype(float) / np.maximum(np.linalg.norm(v.astype(float), axis=1, keepdims=True), 1e-30)
    x, y = np.nonzero(np.triu(np.round(u @ u.T, 6) >= 0.4, 1))
    for block in (50, 1000):
        got = [tuple(r) for r in E.similar_vectors(df, "id", "v", 0.4, block=block).collect()]
        assert sorted(got) == [(a * 3, b * 3) for a, b in zip(x.tolist(), y.tolist(), strict=True)]


def test_rounds_of_several_settings_share_one_layout(spark, monkeypatch):
    """As many rounds as runs by themselves; edges are laid out once a graph."""
    from pointerforest.operators import accelerated as A

    graphs = [(spark.range(n).selectExpr("id AS src", "(id * 7 + 3) % 50 AS dst"), None) for n in (40, 45)]
    settings = [{"level": 1}, {"level": 4}, {}, {"method": "star_hooking"}]
    alone = [[A.connected_components(*g, **s).iterations for s in settings] for g in graphs]
    made, real = [], A.lay_out
    monkeypatch.setattr(A, "lay_out", lambda *a, **k: made.append(1) or real(*a, **k))
    seen = []
    assert A.rounds_of(graphs, settings[:3], lambda g, s, state, k: seen.append((g, s, k))) == [x[:3] for x in alone]
    assert len(made) == 2 and sorted(seen) == [(g, s, k + 1) for g in range(2) for s in range(3) for k in range(alone[g][s])]
    assert [x[0] for x in A.rounds_of(graphs, settings[3:])] == [x[3] for x in alone]


@pytest.mark.parametrize("level", [1, 5])
def test_vertices_without_edges_are_counted_but_take_no_part(spark, level):
    """Labels, roots and shares are those of all vertices; the rounds' states hold only vertices with edges."""
    e, v = frames(spark, range(20), [(4, 5), (5, 6), (7, 7), (9, None)])
    seen = []
    whole = A.connected_components(e, v, level=level, on_round=lambda s, k: seen.append(s.count()))
    assert set(seen) == {20}
    run = A.connected_components(e, v, level=level)
    assert labels_of(run) == labels_of(whole) == reference(range(20), [(4, 5), (5, 6)])
    told = lambda r: [(t["changed_gf"], t["changed_f"], t["roots"], t["frontier_fraction"], t["product"]) for t in r.trace]
    assert told(run) == told(whole)
    with Scratch() as scratch:
        layout, ids, n = A.prepare(e, v, scratch)
        assert n == ids.count() == 20 and layout.n_alone == 17 and layout.joined.count() == 3
        assert A.rounds_on(layout, ids, n, level=level).iterations == whole.iterations
        layout.drop()
    states = []
    A.rounds_of([(e, v)], [{"level": level}], lambda g, s, state, k: states.append(state.count()))
    assert states == [20] * whole.iterations


def test_height_of_broken_and_flat_forests(spark):
    tree = lambda rows: spark.createDataFrame(rows, "id long, f long")
    assert [R.forest_height(tree(x)) for x in ([(0, 0)], [(0, 0), (1, 0), (2, 0)], [(i, max(i - 1, 0)) for i in range(7)])] == [0, 1, 6]
    with pytest.raises(ValueError, match="no vertex"):
        R.forest_height(tree([(1, 1), (2, 9)]))


def test_edges_are_made_once_a_graph(spark):
    """Degrees, layout and counts read what was written; each of them made the edges anew before."""
    from pointerforest.workloads import queries as Q

    made = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            made.add(b.num_rows)
            yield b

    edges = spark.range(30).selectExpr("id AS src", "(id * 7 + 3) % 20 AS dst").mapInArrow(count, "src long, dst long")
    assert len(A.rounds_of([(edges, None)], [{"level": 1}, {}])[0]) == 2 and made.value == 30
    (row,) = Q.stats_of(edges, spark.range(40)).collect()
    plain = {frozenset((i, (i * 7 + 3) % 20)) for i in range(30)}
    assert made.value == 60 and row["n"] == 40 and row["directed_edges"] == 2 * sum(len(x) == 2 for x in plain)
