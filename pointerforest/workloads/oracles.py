"""SQL that checks the queries: components by keyed recursion, trajectories by full-state recursion."""

from __future__ import annotations

from .graphs import GRAPHS


def base(edge_sql: str, vertex_sql: str) -> str:
    """CTEs v (ids) and e (both orientations)."""
    return f"g AS MATERIALIZED ({edge_sql}), e AS MATERIALIZED (SELECT src, dst FROM g WHERE src <> dst UNION SELECT dst, src FROM g WHERE src <> dst), v AS MATERIALIZED (SELECT DISTINCT id FROM ({vertex_sql}) UNION SELECT src FROM e)"


_CC = """cc(id, comp) USING KEY (id) AS (
  SELECT id, id FROM v
  UNION
  SELECT e.src, min(w.comp) FROM cc w JOIN e ON e.dst = w.id JOIN recurring.cc o ON o.id = e.src
  WHERE w.comp < o.comp GROUP BY e.src, o.comp)"""


def labelled(edge_sql: str, vertex_sql: str, select: str = "SELECT id, comp AS component FROM cc") -> str:
    """``select`` over cc(id, comp), e and v; independent of any hooking."""
    return f"WITH RECURSIVE {base(edge_sql, vertex_sql)}, {_CC} {select}"


def cc(graph: str, select: str | None = None) -> str:
    g = GRAPHS[graph]
    if g.direct_sql and not select:
        return g.direct_sql
    return labelled(g.edge_sql, g.vertex_sql, *([select] if select else []))


def step(level: int) -> str:
    """One round as nested SQL over st (level k of it is the working table)."""
    if level <= 2:
        value = "sv.f" if level == 1 else "sv.gf"
        return f"""
  p AS (SELECT su.f AS t, min({value}) AS x FROM e JOIN st su ON su.id = e.src JOIN st sv ON sv.id = e.dst WHERE su.f = su.gf AND sv.f < su.f GROUP BY su.f),
  h AS (SELECT s.k, s.id, s.f AS f0, s.gf AS gf0, s.mn, least(s.f, p.x) AS h FROM st s LEFT JOIN p ON p.t = s.id),
  n AS (SELECT h.k, h.id, h.f0, h.gf0, h.mn, q.h AS f FROM h JOIN h q ON q.id = h.h)"""
    own = "least(m.f, m.gf, m.mn, a.x)" if level >= 4 else "least(m.f, m.gf, a.x)"
    return f"""
  p AS (SELECT e.src, min(s.gf) AS x FROM e JOIN st s ON s.id = e.dst GROUP BY e.src),
  m AS (SELECT s.k, s.id, s.f, s.gf, least(s.mn, p.x) AS mn FROM st s LEFT JOIN p ON p.src = s.id),
  a AS (SELECT f AS t, min(mn) AS x FROM m GROUP BY f),
  n AS (SELECT m.k, m.id, m.f AS f0, m.gf AS gf0, m.mn, {own} AS f FROM m LEFT JOIN a ON a.t = m.id)"""


def trajectory(graph: str, level: int, select: str, rounds: int = 60) -> str:
    """``select`` over st(k, id, f, gf, mn, cf, cg, go) and v: states of all rounds until the level's stop."""
    g = GRAPHS[graph]
    stop = "cg" if level == 5 else "cf"
    return f"""WITH RECURSIVE {base(g.edge_sql, g.vertex_sql)}, st(k, id, f, gf, mn, cf, cg, go) AS (
  SELECT 0, id, id, id, id, 0, 0, 1 FROM v
  UNION ALL
  (WITH {step(level)},
  r AS (SELECT n.k + 1 AS k, n.id, n.f, q.f AS gf, n.mn, CAST(n.f <> n.f0 AS INT) AS cf, CAST(q.f <> n.gf0 AS INT) AS cg FROM n JOIN n q ON q.id = n.f)
  SELECT k, id, f, gf, mn, cf, cg, CAST(sum({stop}) OVER () > 0 AS INT) FROM r
  WHERE k <= {rounds} AND (SELECT max(go) FROM st) = 1))
{select}"""


def changes(graph: str, level: int) -> str:
    return trajectory(graph, level, "SELECT CAST(k AS INT) AS iteration, CAST(sum(cg) AS BIGINT) AS changed_gf, CAST(sum(cf) AS BIGINT) AS changed_f FROM st WHERE k > 0 GROUP BY k")


def state_after(graph: str, level: int, k: int) -> str:
    return trajectory(graph, level, f"SELECT id, f, gf FROM st WHERE k = {k}", rounds=k)


def iterations(graph: str, level: int) -> str:
    return f"SELECT '{graph}' AS graph, CAST({level} AS INT) AS level, (SELECT CAST(max(k) AS INT) FROM ({trajectory(graph, level, 'SELECT k FROM st')})) AS iterations"
