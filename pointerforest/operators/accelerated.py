"""Connected components by hooking a forest of pointers, with all accelerations.

``f`` is the parent of a vertex and never exceeds its id; ``gf`` is the parent's
parent; ``mngf`` the least grandparent among the neighbours. One round hooks trees
under smaller neighbours and flattens them; all reads are of the old vectors, so a
retry gives the same forest. Five levels, each adding one acceleration:

1. hook roots below the smallest neighbouring parent, flatten the hooked forest;
2. hook to the grandparent instead;
3. hook any tree top, not only roots ("stochastic"), flatten on the old forest;
4. every vertex also takes the least neighbouring grandparent itself ("aggressive");
5. stop once grandparents are stable, a round earlier than parents.

Edges are laid out once (``plans.layout``); in every round the vector travels to them and
they stay.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.layout import HUB_EDGES, Layout, degrees, lay_out
from ..plans.store import Scratch, forget, keep
from .edges import contract, vertices_of
from .vectors import at_edges, gather, grid_neighbour_min, neighbour_min

#: Share of changed grandparents up to which only changed entries are multiplied.
SPARSE_THRESHOLD = 0.1
#: Which of several edges writes a slot of levels 1 and 2: the least or the greatest value, or that of the edge whose ends hash least.
TIES = ("min", "max", "hash")
#: Below this many vertices hot parents need no care of their own.
HOT_ROWS = 5_000_000
HOT = 64


@dataclass
class Run:
    """Labels (id, component) with the trace of the rounds that led there."""

    labels: DataFrame
    trace: list[dict] = field(default_factory=list)

    @property
    def iterations(self) -> int:
        return len(self.trace)


class NotConverged(RuntimeError):
    """``max_iter`` rounds were not enough; no partial labels are given."""


@dataclass
class Options:
    level: int = 5
    hook_depth: int | None = None
    stop: str = "auto"
    product: str = "auto"
    sparse_threshold: float = SPARSE_THRESHOLD
    gather: str = "auto"
    grid: tuple[int, int] | None = None
    extra_shortcut: bool = False
    tie: str = "min"
    hub_edges: int | None = None
    max_iter: int = 200

    def __post_init__(self):
        if self.level not in (1, 2, 3, 4, 5):
            raise ValueError("level is 1 to 5")
        if self.tie not in TIES or self.tie != "min" and self.level > 2:
            raise ValueError(f"tie is one of {', '.join(TIES)}; from level 3 on every slot takes the minimum")
        self.hook_depth = self.hook_depth or (1 if self.level == 1 else 2)
        plain = self.level == 5 and self.hook_depth == 2
        if self.stop == "auto":
            self.stop = "gf" if plain else "f"
        elif self.stop == "gf" and (self.level < 4 or self.hook_depth != 2):
            raise ValueError("grandparents may rest before the forest does below level 4; stop='f' is needed")

    def hot(self, n: int) -> int:
        return HOT if self.gather == "hot" or self.gather == "auto" and n >= HOT_ROWS else 0


def prepare(edges: DataFrame, vertices: DataFrame | None, scratch: Scratch, hub_edges: int | None = None, *, loops: bool = False, simple: bool = False) -> tuple[Layout, DataFrame, int]:
    """Laid-out symmetric edges and the vertices (id), both materialised once: two passes over the edges."""
    hub_edges = hub_edges or HUB_EDGES
    known, seen = scratch.keep(degrees(edges, vertices), n=F.count(F.lit(1)), hubs=F.count_if(F.col("degree") > hub_edges), alone=F.count_if(F.col("degree") == 0))
    layout = lay_out(edges, known, seen["hubs"], hub_edges=hub_edges, loops=loops, simple=simple)
    layout.alone, layout.n_alone = known.where("degree = 0").select("id"), seen["alone"]
    layout.joined = known.where("degree > 0").select("id")
    return layout, known.select("id"), seen["n"]


def start_state(ids: DataFrame, init: DataFrame | None, hot: int) -> DataFrame:
    """Singletons, or a given forest (id, component) for a warm start."""
    if init is None:
        return ids.select("id", F.col("id").alias("f"), F.col("id").alias("gf"), F.col("id").alias("mngf"))
    given = init.select("id", F.col("component").alias("_c"))
    flat = ids.join(given, "id", "left").select("id", F.coalesce("_c", "id").alias("f"))
    return gather(flat, "f", "gf", hot=hot).withColumn("mngf", F.col("id"))


def hook_proposals(edges: Layout, state: DataFrame, o: Options, n: int, hot: int) -> DataFrame:
    """Levels 1 and 2: (id, value) for roots with a smaller neighbouring parent.

    The test is on the neighbour's parent, the value its ancestor of ``hook_depth``. With
    ties to the least parent of all neighbours a plain product tells it; otherwise roots
    travel to their edges, and only edges at roots go on to the parents at their other end.
    """
    if o.hook_depth == 1 and o.tie == "min":
        roots = state.where("f = gf").select(F.col("id").alias("src"), F.col("f").alias("fu"))
        least = neighbour_min(edges, state, "f", rows=n).join(roots, "src").where("mn < fu")
        return least.groupBy(F.col("fu").alias("id")).agg(F.min("mn").alias("value"))
    target = {1: "f", 2: "gf"}.get(o.hook_depth)
    if target is None:
        state, target = ancestors(state, o.hook_depth, hot)
    at_roots = at_edges(edges, state.where("f = gf"), "f", rows=n).select("src", "dst", F.col("_v").alias("fu"))
    v = state.select(F.col("id").alias("src"), F.col("f").alias("fv"), F.col(target).alias("value"))
    found = at_roots.join(v, "src").where("fv < fu").groupBy(F.col("fu").alias("id"))
    pick = {"min": F.min("value"), "max": F.max("value"), "hash": F.min_by("value", F.struct(F.xxhash64("src", "dst"), F.col("value")))}
    return found.agg(pick[o.tie].alias("value"))


def ancestors(state: DataFrame, depth: int, hot: int) -> tuple[DataFrame, str]:
    """State with the ancestor of the given depth, and its column."""
    if depth <= 2:
        return state, "f" if depth == 1 else "gf"
    at = "gf"
    for k in range(3, depth + 1):
        state = gather(state, at, f"a{k}", hot=hot)
        at = f"a{k}"
    return state, at


def round_of_roots(edges: Layout, state: DataFrame, o: Options, n: int, hot: int) -> DataFrame:
    """Levels 1 and 2: hook, then flatten the hooked forest."""
    to = hook_proposals(edges, state, o, n, hot)
    hooked = state.join(to, "id", "left").select("id", F.least("f", "value").alias("h"), F.col("f").alias("f_prev"), F.col("gf").alias("gf_prev"))
    out = gather(hooked, "h", "f", value="h", hot=hot).select("id", "f", "f_prev", "gf_prev")
    return out.withColumn("mngf", F.col("id"))


def round_of_minima(product: DataFrame, state: DataFrame, o: Options) -> DataFrame:
    """Levels 3 to 5: every proposal is a minimum, so one aggregation does them all.

    Each vertex sends its least neighbouring grandparent to its parent's slot, and what
    it would take itself to its own slot together with the columns to carry.
    """
    s = state.join(product.withColumnRenamed("src", "id"), "id", "left").withColumn("mngf", F.least("mngf", "mn"))
    own = F.least("f", "gf", "mngf") if o.level >= 4 else F.least("f", "gf")
    none = F.lit(None).cast("long")
    sends = F.array(
        F.struct(F.col("f").alias("id"), F.col("mngf").alias("f"), none.alias("f_prev"), none.alias("gf_prev"), none.alias("mngf")),
        F.struct(F.col("id").alias("id"), own.alias("f"), F.col("f").alias("f_prev"), F.col("gf").alias("gf_prev"), F.col("mngf").alias("mngf")),
    )
    return s.select(F.inline(sends)).groupBy("id").agg(F.min("f").alias("f"), *[F.max(c).alias(c) for c in ("f_prev", "gf_prev", "mngf")])


def product_of(edges: Layout, state: DataFrame, o: Options, first: bool, changed: int, n: int, hot: int, rows: int | None = None) -> tuple[DataFrame, str]:
    """Least neighbouring grandparent, over all entries or the changed ones only."""
    if first:
        return edges.least_neighbour(), "dense"  # each vertex is its own grandparent
    state, at = ancestors(state, o.hook_depth, hot)
    sparse = o.product == "sparse" or o.product == "auto" and changed <= o.sparse_threshold * n
    if sparse and o.hook_depth == 2 and "gf_prev" in state.columns:
        return neighbour_min(edges, state.where("gf <> gf_prev"), at, rows=changed), "sparse"
    if o.grid:
        return grid_neighbour_min(edges, state, at, *o.grid), "dense"
    return neighbour_min(edges, state, at, rows=n if rows is None else rows), "dense"


def one_round(edges: Layout, state: DataFrame, o: Options, *, first: bool, changed: int, n: int, rows: int | None = None) -> tuple[DataFrame, str]:
    """(id, f, f_prev, gf, gf_prev, mngf) after a round, not yet materialised. ``rows``: of the state, if not all ``n`` vertices are in it."""
    hot, kind, rows = o.hot(n), "dense", n if rows is None else rows
    if o.level <= 2:
        out = round_of_roots(edges, state, o, rows, hot)
    else:
        product, kind = product_of(edges, state, o, first, changed, n, hot, rows)
        out = round_of_minima(product, state, o)
    if o.extra_shortcut:
        out = gather(out.withColumnRenamed("f", "h"), "h", "f", value="h", hot=hot).drop("h")
    return gather(out, "f", "gf", hot=hot), kind


def connected_components(edges: DataFrame, vertices: DataFrame | None = None, *, init: DataFrame | None = None, method: str = "accelerated", on_round=None, simple: bool = False, **options) -> Run:
    """Labels: the smallest id of each component.

    ``vertices`` adds isolated ones; null ends, loops and repeated edges are dropped, but
    every id among the edges is a vertex. ``init``: labels of an earlier run
    on fewer edges. ``on_round(state, k)`` sees each materialised round. ``simple``: the caller
    knows that no edge is given twice, in either orientation.
    """
    if method != "accelerated":
        from . import baselines

        return baselines.METHODS[method](edges, vertices, **options)
    o = Options(**options)
    with Scratch() as scratch:
        layout, ids, n = prepare(edges, vertices, scratch, o.hub_edges, simple=simple)
        try:
            return _rounds(layout, ids, n, init, o, scratch, on_round, whole=on_round is not None)
        finally:
            layout.drop()


def rounds_on(layout: Layout, ids: DataFrame, n: int, **options) -> Run:
    """The rounds alone, on edges that ``prepare`` has laid out, which stay as they are."""
    with Scratch() as scratch:
        return _rounds(layout, ids, n, None, Options(**options), scratch, None)


def _rounds(layout: Layout, ids: DataFrame, n: int, init: DataFrame | None, o: Options, scratch: Scratch, on_round, whole: bool = False) -> Run:
    # A vertex without edges is its own parent in every round: it is counted, but takes no part, unless a given forest moves it
    # or every state is to be ``whole``, readable after the run.
    apart = layout.n_alone if init is None and not whole and 0 < layout.n_alone < n else 0
    state, changed, trace = start_state(layout.joined if apart else ids, init, o.hot(n)), n, []
    if init is not None:
        state, _ = scratch.keep(state)
    resting = [F.col("id").alias(c) for c in ("id", "f", "f_prev", "gf", "gf_prev", "mngf")]
    for k in range(1, o.max_iter + 1):
        began = time.monotonic()
        new, kind = one_round(layout, state, o, first=k == 1 and init is None, changed=changed, n=n, rows=n - apart)
        old = state
        state, seen = scratch.keep(
            new,
            changed_gf=F.count_if(F.col("gf") != F.col("gf_prev")),
            changed_f=F.count_if(F.col("f") != F.col("f_prev")),
            roots=F.count_if(F.col("f") == F.col("id")),
        )
        if k > 1 and not on_round:
            forget(old)
        changed, seen["roots"] = seen["changed_gf"], seen["roots"] + apart
        trace.append({"iteration": k, **seen, "product": kind, "products": 1, "frontier_fraction": changed / n if n else 0.0, "seconds": time.monotonic() - began})
        if on_round:
            on_round(scratch.spare(state).unionByName(layout.alone.select(*resting)) if apart else scratch.spare(state), k)
        if not seen["changed_gf" if o.stop == "gf" else "changed_f"]:
            if apart:  # written as one table, as that of the vertices goes with the run
                return Run(keep(state.select("id", F.col("f").alias("component")).unionByName(layout.alone.select("id", F.col("id").alias("component"))))[0], trace)
            labels = scratch.spare(state).select("id", F.col("f").alias("component"))
            labels.stored_at = state.stored_at
            return Run(labels, trace)
    raise NotConverged(f"no rest after {o.max_iter} rounds")


#: Runs that ``rounds_of`` and ``side_by_side`` have under way at a time: one plans while others compute.
AT_ONCE = 4


def side_by_side(work: list[Callable], at_once: int = AT_ONCE) -> list:
    """Results of independent runs, in order."""
    with ThreadPoolExecutor(at_once) as pool:
        return list(pool.map(lambda f: f(), work))


def _prepare_stored(edges: DataFrame, vertices: DataFrame | None, scratch: Scratch) -> tuple[Layout, DataFrame, int]:
    """As ``prepare``, from edges that are made once and written, as it reads them twice."""
    edges, _ = scratch.keep(edges)
    out = prepare(edges, vertices, scratch)
    forget(edges)
    return out


def rounds_of(graphs: list[tuple[DataFrame, DataFrame | None]], settings: list[dict], on_round=None) -> list[list[int]]:
    """Rounds of every setting on every graph, each to its end. Edges of a graph are laid out once for all settings.

    ``on_round(graph, setting, state, k)`` counts them from 0. The rival (``method``) has a layout of its own.
    """
    laid: dict[int, tuple[Layout, DataFrame, int]] = {}

    def one(g: int, s: int) -> int:
        if "method" in settings[s]:
            run = connected_components(*graphs[g], **settings[s])
        else:
            see = on_round and (lambda state, k: on_round(g, s, state, k))
            with Scratch() as own:
                run = _rounds(*laid[g], None, Options(**settings[s]), own, see)
        forget(run.labels)
        return run.iterations

    with Scratch() as scratch:
        try:
            side_by_side([lambda g=g: laid.__setitem__(g, _prepare_stored(*graphs[g], scratch)) for g in range(len(graphs))])
            found = side_by_side([lambda g=g, s=s: one(g, s) for g in range(len(graphs)) for s in range(len(settings))])
        finally:
            for layout, _, _ in laid.values():
                layout.drop()
    return [found[g * len(settings) : (g + 1) * len(settings)] for g in range(len(graphs))]


def incremental(labels: DataFrame, new_edges: DataFrame, vertices: DataFrame | None = None, **options) -> DataFrame:
    """Labels (id, component) after more edges, from the labels before: old components shrink to
    points, only the new edges between them are solved, and the labels compose. Old edges are not needed."""
    ids = vertices_of(new_edges)
    if vertices is not None:
        ids = ids.union(vertices.select("id").where("id IS NOT NULL")).distinct()
    known = labels.select("id", "component").unionByName(ids.join(labels, "id", "left_anti").select("id", F.col("id").alias("component")))
    top = connected_components(contract(new_edges, known), **options).labels
    joined = known.join(top.select(F.col("id").alias("component"), F.col("component").alias("_c")), "component", "left")
    return joined.select("id", F.coalesce("_c", "component").alias("component"))


def components_by_group(edges: DataFrame, group: str, ids_per_group: int, **options) -> DataFrame:
    """Many graphs at once: (group, id, component). Ids lie in 0 .. ids_per_group - 1; others are an error, as they would fall into another graph."""
    inside = lambda c: F.when(F.col(c).between(0, ids_per_group - 1), F.col(c)).when(F.col(c).isNotNull(), F.raise_error(F.concat(F.lit(f"{c} is not in 0 .. {ids_per_group - 1}: "), F.col(c).cast("string"))).cast("long"))
    at = F.col(group).cast("long") * ids_per_group
    labels = connected_components(edges.select((at + inside("src")).alias("src"), (at + inside("dst")).alias("dst")), **options).labels
    own = F.floor(F.col("id") / ids_per_group).cast("long")
    return labels.select(own.alias(group), F.pmod("id", F.lit(ids_per_group)).alias("id"), F.pmod("component", F.lit(ids_per_group)).alias("component"))
