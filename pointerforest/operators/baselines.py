"""What the accelerated method is compared with: star hooking, the full four-step
scheme, minimum-label propagation, breadth-first search, and a hybrid of ours.

Unconditional hooks can give a root a larger parent, so these methods end with the
smallest id of each tree.
"""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from ..functions.udfs import local_contract
from ..plans.layout import Layout
from ..plans.store import Scratch, forget, keep
from .accelerated import NotConverged, Run, connected_components, prepare
from .vectors import at_edges, gather, neighbour_min, scatter_min


def mark_stars(state: DataFrame) -> DataFrame:
    """Add ``star``: whether every vertex of the tree points at its root. Needs f and gf."""
    deep = state.where("f <> gf").select(F.explode(F.array("id", "gf")).alias("_d")).distinct()
    own = state.join(deep, state["id"] == deep["_d"], "left").withColumn("s0", F.col("_d").isNull()).drop("_d")
    return gather(own, "f", "s1", value="s0").withColumn("star", F.col("s0") & F.col("s1")).drop("s0", "s1")


def hook_conditional(edges: DataFrame | Layout, state: DataFrame, *, only_stars: bool, upward_only: bool = False, rows: int | None = None) -> DataFrame:
    """(id, value): roots with the least smaller parent next to their tree.

    ``upward_only`` leaves out targets whose own parent is larger than they are.
    """
    values = state.where("gf <= f") if upward_only else state
    mn = neighbour_min(edges, values, "f", rows=rows).withColumnRenamed("src", "id")
    own = state.where("star" if only_stars else "f = gf")
    return scatter_min(own.join(mn, "id").where("mn < f").select("f", F.col("mn").alias("value")), "f", "value")


def outside(edges: DataFrame | Layout, state: DataFrame, *, rows: int | None = None) -> DataFrame:
    """Per vertex of a star, a neighbour's parent outside its tree: the least, or else the greatest, that differs."""
    ends = at_edges(edges, state, "f", rows=rows).groupBy(F.col("src").alias("id")).agg(F.min("_v").alias("lo"), F.max("_v").alias("hi"))
    pick = F.when(F.col("lo") != F.col("f"), F.col("lo")).when(F.col("hi") != F.col("f"), F.col("hi"))
    return state.where("star").join(ends, "id").select("f", pick.alias("value")).where("value IS NOT NULL")


def hook_unconditional(edges: DataFrame | Layout, state: DataFrame, touched: DataFrame) -> DataFrame:
    """(id, value): roots of stars that neither hooked nor were hooked onto, below any other tree."""
    return scatter_min(outside(edges, state), "f", "value").join(touched, "id", "left_anti")


def _sent(rows: DataFrame, own: list[str], *sends: tuple[Column, Column, dict[str, Column]], least: tuple[str, ...] = ()) -> DataFrame:
    """Each row's ``own`` columns at its id, with what others send to that id: one aggregation, like all of a round's.

    A send is (target, condition, columns); columns in ``least`` take the minimum of what arrives, flags whether any is set.
    """
    names = [*own, *dict.fromkeys(c for _, _, what in sends for c in what if c not in own)]
    kinds = {c: "boolean" if c in rows.columns and dict(rows.dtypes)[c] == "boolean" or c not in rows.columns and c not in least else "long" for c in names}
    row = lambda to, what: F.struct(to.alias("id"), *[what.get(c, F.lit(None)).cast(kinds[c]).alias(c) for c in names])
    mine = row(F.col("id"), {c: F.col(c) for c in own})
    others = [F.when(when, row(to, what)) for to, when, what in sends]
    out = rows.select(F.explode(F.array(mine, *others)).alias("_r")).where("_r IS NOT NULL").select("_r.*")
    found = out.groupBy("id").agg(*[(F.min if c in least else F.max)(c).alias(c) for c in names])
    return found.select("id", *[F.coalesce(F.col(c), F.lit(False)).alias(c) if kinds[c] == "boolean" else c for c in names])


def _flat(state: DataFrame, *more: str, marks: tuple = ()) -> DataFrame:
    """State (id, f, ...) with ``s0``: no vertex of it is, or is two steps above, one whose parent is not a root.

    The tree of a root r is a star for its vertices with ``s0`` if r has it too. Needs gf.
    """
    deep = F.col("f") != F.col("gf")
    rows = state.withColumn("deep", deep)
    out = _sent(rows, ["f", *more, "deep"], (F.col("gf"), deep, {"deep": F.lit(True)}), *marks)
    return out.withColumn("s0", ~F.col("deep")).drop("deep")


#: Edges of finished trees are taken out of the layout once they touch this share of the vertices.
PRUNE_SHARE = 0.1


def _tree_scheme(edges, vertices, *, only_stars: bool, middle_shortcut: bool, last_shortcut: bool, prune: bool, max_iter: int, hub_edges: int | None = None) -> Run:
    """Rounds on the same edge layout as the accelerated method: two products and two written tables
    a round (three with the middle shortcut). Marks and hooks of a step meet at their vertex in one aggregation."""
    with Scratch() as scratch:
        layout, ids, n = prepare(edges, vertices, scratch, hub_edges)
        own = [layout]
        try:
            return _tree_rounds(own, ids, n, scratch, only_stars, middle_shortcut, last_shortcut, prune, max_iter)
        finally:
            own[-1].drop()


def _tree_rounds(own: list[Layout], ids: DataFrame, n: int, scratch: Scratch, only_stars: bool, middle_shortcut: bool, last_shortcut: bool, prune: bool, max_iter: int, given: bool = False) -> Run:
    state = ids.select("id", F.col("id").alias("f"), F.col("id").alias("gf"))
    done, trace, left, gone = None, [], n, []
    spent: list[DataFrame] = []  # tables that nothing reads once the next state is written
    for k in range(1, max_iter + 1):
        began, layout = time.monotonic(), own[-1]
        # Hook below smaller neighbours: what a vertex finds goes to its root, which takes the least if its tree may hook.
        mn = neighbour_min(layout, state if last_shortcut else state.where("gf <= f"), "f", rows=left).withColumnRenamed("src", "id")
        s = (_flat(state) if only_stars else state.select("id", "f", (F.col("f") == F.col("gf")).alias("s0"))).join(mn, "id", "left")
        s = _sent(s, ["f", "s0"], (F.col("f"), F.col("s0") & (F.col("mn") < F.col("f")), {"value": F.col("mn")}), least=("value",))
        hooks = F.col("value").isNotNull() & (F.col("s0") if only_stars else F.lit(True))
        hooked = s.select("id", F.when(hooks, F.col("value")).otherwise(F.col("f")).alias("f"), F.col("f").alias("f_prev"), hooks.alias("touched"))
        marks = [(F.col("f"), F.col("touched"), {"touched": F.lit(True)})]
        if middle_shortcut:
            hooked, _ = scratch.keep(gather(hooked.withColumnRenamed("f", "h"), "h", "f", value="h"))
            spent.append(hooked)
            # A tree that the shortcut has just flattened is not stagnant: its neighbour may hook this round too.
            marks = [(F.col("h"), F.col("touched"), {"touched": F.lit(True)}), (F.col("f"), F.col("f") != F.col("h"), {"touched": F.lit(True)})]
        hooked, _ = scratch.keep(_flat(gather(hooked, "f", "gf"), "f_prev", "touched", marks=tuple(marks)))
        spent.append(hooked)
        # What the unconditional step sees also tells which stars have no edge to anywhere else.
        ends = at_edges(layout, hooked, "f", rows=left).groupBy(F.col("src").alias("id")).agg(F.min("_v").alias("lo"), F.max("_v").alias("hi"))
        pick = F.when(F.col("lo") != F.col("f"), F.col("lo")).when(F.col("hi") != F.col("f"), F.col("hi"))
        s = hooked.join(ends, "id", "left").withColumn("pick", pick)
        s = _sent(s, ["f", "f_prev", "touched", "s0"], (F.col("f"), F.col("s0") & F.col("pick").isNotNull(), {"value": F.col("pick")}), least=("value",))
        idle = F.col("s0") & (F.col("id") == F.col("f")) & ~F.col("touched")  # a root of a star that neither hooked nor was hooked onto
        hooks = idle & F.col("value").isNotNull()
        new = s.select("id", F.when(hooks, F.col("value")).otherwise(F.col("f")).alias("h"), "f_prev", (F.col("s0") & ~hooks).alias("stays"), (idle & F.col("value").isNull()).alias("alone"))
        parents = new.select(F.col("id").alias("_p"), F.col("h").alias("up"), F.col("alone").alias("_a"))
        flatten = last_shortcut or not middle_shortcut
        new = new.join(parents, F.col("h") == F.col("_p")).select("id", F.col("up" if flatten else "h").alias("f"), "f_prev", (F.col("stays") & F.col("_a")).alias("over"))
        state, seen = scratch.keep(gather(new, "f", "gf"), changed_f=F.count_if(F.col("f") != F.col("f_prev")), roots=F.count_if(F.col("f") == F.col("id")), n=F.count(F.lit(1)), over=F.count_if("over"))
        for table in spent:
            forget(table)
        spent = [] if prune and seen["over"] else [state]
        trace.append({"iteration": k, "changed_f": seen["changed_f"], "roots": seen["roots"], "products": 2, "inactive_fraction": 1 - seen["n"] / n if n else 0.0, "seconds": time.monotonic() - began})
        if not seen["changed_f"]:
            labels = state.select("id", "f")
            labels = labels.unionByName(done) if done is not None else labels
            least = labels.groupBy("f").agg(F.min("id").alias("component"))
            out, _ = keep(labels.join(least, "f").select("id", "component"))
            return Run(out, trace)
        if prune and seen["over"]:
            finished = state.where("over").select("id", "f")
            done = finished if done is None else done.unionByName(finished)
            state, left = state.where("NOT over"), seen["n"] - seen["over"]
            gone.append((finished.select("id"), seen["over"]))
            if sum(m for _, m in gone) >= PRUNE_SHARE * (left + sum(m for _, m in gone)):
                ids_gone = reduce(DataFrame.unionByName, [g for g, _ in gone])
                own.append(layout.without(ids_gone, sum(m for _, m in gone)))
                if not (given and layout is own[0]):
                    layout.drop(hubs=False)
                gone = []
    raise NotConverged(f"no rest after {max_iter} rounds")


def star_hooking_components(edges: DataFrame, vertices: DataFrame | None = None, *, prune_converged: bool = True, hub_edges: int | None = None, max_iter: int = 100) -> Run:
    """The rival: detect stars, hook them below smaller neighbours, hook the untouched ones anywhere, flatten."""
    return _tree_scheme(edges, vertices, only_stars=True, middle_shortcut=False, last_shortcut=True, prune=prune_converged, max_iter=max_iter, hub_edges=hub_edges)


def star_hooking_on(layout: Layout, ids: DataFrame, n: int, *, prune_converged: bool = True, max_iter: int = 100) -> Run:
    """The rival's rounds on edges that ``prepare`` has laid out, which stay as they are."""
    own = [layout]
    with Scratch() as scratch:
        try:
            return _tree_rounds(own, ids, n, scratch, True, False, True, prune_converged, max_iter, given=True)
        finally:
            if own[-1] is not layout:
                own[-1].drop(hubs=False)


def sv_full_components(edges: DataFrame, vertices: DataFrame | None = None, *, final_shortcut: bool = True, max_iter: int = 100) -> Run:
    """Four steps: hook roots of any height, flatten, hook stagnant trees, flatten again (or not)."""
    return _tree_scheme(edges, vertices, only_stars=False, middle_shortcut=True, last_shortcut=final_shortcut, prune=False, max_iter=max_iter)


#: Rounds of label propagation in one job: two at first, then twice as many each time up to this (longer plans take longer to plan).
ROUNDS_A_JOB = 8


def spread(layout: Layout, state: DataFrame) -> DataFrame:
    """(id, l, l_prev) after a round of label propagation on edges laid out with loops.

    The state is read once and comes out dealt as the edges lie, so rounds follow each other in one job with
    one shuffle each.
    """
    met = layout.edges.join(layout.entries(state, "l").hint("shuffle_hash"), layout.keys)
    own = F.when(F.col("src") == F.col("dst"), F.col("_v"))
    return met.groupBy(F.col("src").alias("id")).agg(F.min("_v").alias("l"), F.max(own).alias("l_prev"))


def label_propagation_components(edges: DataFrame, vertices: DataFrame | None = None, *, local: bool = False, hub_edges: int | None = None, max_iter: int = 1000) -> Run:
    """Every vertex takes the least label around it; rounds grow with the diameter.

    ``local``: labels first come to rest inside each partition of the edges, where they lie; rounds then grow
    with the partitions that a path crosses.
    """
    if local:
        # A row with one end missing becomes a loop, as its other end is a vertex.
        edges = local_contract(edges.select(F.coalesce("src", "dst").alias("src"), F.coalesce("dst", "src").alias("dst")))
    with Scratch() as scratch:
        layout, ids, n = prepare(edges, vertices, scratch, hub_edges, loops=True)
        try:
            state, trace, many = ids.select("id", F.col("id").alias("l")), [], 2
            while n and len(trace) < max_iter:
                old, began, seen = state, time.monotonic(), []
                for _ in range(min(many, max_iter - len(trace))):
                    seen.append(Observation())
                    state = spread(layout, state).observe(seen[-1], F.count_if(F.col("l") != F.col("l_prev")).alias("changed"))
                state, _ = scratch.keep(state)
                changed = [s.get["changed"] for s in seen]
                seconds, many = (time.monotonic() - began) / len(seen), min(2 * many, ROUNDS_A_JOB)
                if trace:
                    forget(old)
                for c in changed[: changed.index(0) + 1] if 0 in changed else changed:
                    trace.append({"iteration": len(trace) + 1, "changed": c, "products": 1, "seconds": seconds})
                if not changed[-1]:
                    return Run(scratch.spare(state).select("id", F.col("l").alias("component")), trace)
            if not n:
                return Run(keep(state.select("id", F.col("l").alias("component")))[0], trace)
        finally:
            layout.drop()
    raise NotConverged(f"no rest after {max_iter} rounds")


def reached_from(edges: Layout, seed: DataFrame, max_iter: int, scratch: Scratch) -> tuple[DataFrame, int]:
    """Ids that a breadth-first search from the seed ids reaches, and its levels."""
    visited, frontier, rows = seed, seed, 1
    for level in range(1, max_iter + 1):
        step = edges.meet(frontier, "id", rows=rows).select(F.col("src").alias("id")).distinct()
        frontier, seen = scratch.keep(step.join(visited, "id", "left_anti"), n=F.count(F.lit(1)))
        rows = seen["n"]
        if not rows:
            return visited, level
        visited = visited.union(frontier)
        if level % 16 == 0:  # a plan of many branches is as slow as a table
            visited, _ = scratch.keep(visited)
    raise NotConverged(f"no rest after {max_iter} levels")


def bfs_components(edges: DataFrame, vertices: DataFrame | None = None, *, max_iter: int = 1000) -> Run:
    """One search after the other, each from the smallest id not yet reached: for few, short components only."""
    with Scratch() as scratch:
        layout, ids, _ = prepare(edges, vertices, scratch)
        try:
            left, labels, trace = ids, None, []
            while (least := left.agg(F.min("id").alias("m")).first()["m"]) is not None:
                found, levels = reached_from(layout, left.where(F.col("id") == least).select("id"), max_iter, scratch)
                own, _ = scratch.keep(found.withColumn("component", F.lit(least).cast("long")))
                labels = own if labels is None else labels.unionByName(own)
                trace.append({"iteration": len(trace) + 1, "levels": levels})
                left, _ = scratch.keep(left.join(own, "id", "left_anti"))
            out, _ = keep(labels if labels is not None else ids.select("id", F.col("id").alias("component")))
            return Run(out, trace)
        finally:
            layout.drop()


def hybrid_components(edges: DataFrame, vertices: DataFrame | None = None, *, max_iter: int = 1000) -> Run:
    """Our stand-in for a third distributed method: one search from the busiest vertex, hooking for the rest."""
    with Scratch() as scratch:
        layout, ids, _ = prepare(edges, vertices, scratch)
        try:
            busiest, _ = scratch.keep(layout.edges.groupBy(F.col("dst").alias("id")).count().orderBy(F.desc("count"), "id").limit(1).select("id"))
            found, levels = reached_from(layout, busiest, max_iter, scratch)
            found, seen = scratch.keep(found, least=F.min("id"), n=F.count(F.lit(1)))
            rest = layout.edges.select("src", "dst").join(found.withColumnRenamed("id", "src"), "src", "left_anti")
            run = connected_components(rest, ids.join(found, "id", "left_anti"))
            own = found.select("id", F.lit(seen["least"]).cast("long").alias("component"))
            out, _ = keep(own.where("component IS NOT NULL").unionByName(run.labels))
            return Run(out, [{"iteration": 0, "levels": levels}, *run.trace])
        finally:
            layout.drop()


METHODS = {"star_hooking": star_hooking_components, "sv_full": sv_full_components, "label_propagation": label_propagation_components, "bfs": bfs_components, "hybrid": hybrid_components}
