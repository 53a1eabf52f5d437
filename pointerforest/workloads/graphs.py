"""Graphs G01 to G18 built from the given tables, in Spark and in SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import edges as E


@dataclass(frozen=True)
class Graph:
    key: str
    edges: Callable[[SparkSession, str], DataFrame]  # one orientation
    vertices: Callable[[SparkSession, str], DataFrame]
    edge_sql: str
    vertex_sql: str
    direct_sql: str | None = None  # labels without recursion, where the shape is known


def _table(name: str):
    return lambda spark, d: spark.read.parquet(f"{d}/{name}.parquet")


def _ids(*parts: tuple[str, str]):
    """Vertices from (table, SQL expression) pairs."""

    def build(spark: SparkSession, d: str) -> DataFrame:
        out = None
        for table, expression in parts:
            one = _table(table)(spark, d).select(F.expr(expression).cast("long").alias("id"))
            out = one if out is None else out.unionByName(one)
        return out

    return build, " UNION ALL ".join(f"SELECT CAST({x} AS BIGINT) AS id FROM {t}" for t, x in parts)


def _bipartite(table: str, left: str, right: str, where: str = "true"):
    build = lambda spark, d: E.bipartite(_table(table)(spark, d).where(where), left, right)
    return build, f"SELECT DISTINCT CAST({left} AS BIGINT) * 2 AS src, CAST({right} AS BIGINT) * 2 + 1 AS dst FROM {table} WHERE {where}"


def _star_of(key: str, table: str, value_sql: str) -> str:
    rows = f"SELECT DISTINCT {key} AS k, {value_sql} AS v FROM {table}"
    return f"WITH r AS ({rows}), m AS (SELECT v, min(k) AS lo FROM r WHERE v IS NOT NULL GROUP BY v) SELECT DISTINCT k AS src, lo AS dst FROM r JOIN m USING (v) WHERE k <> lo"


def customer_part(spark: SparkSession, d: str) -> DataFrame:
    lines = _table("lineitem")(spark, d).where("l_quantity >= 50 AND l_discount >= 0.09")
    return E.bipartite(_table("orders")(spark, d).join(lines, F.col("o_orderkey") == F.col("l_orderkey")), "o_custkey", "l_partkey")


def event_chain(spark: SparkSession, d: str, gap: bool = False) -> DataFrame:
    # Whole seconds of the clock, as the SQL counts them: 0.9 s and 1.1 s are one apart.
    close = F.expr("unix_seconds(CAST(next_ts AS TIMESTAMP)) - unix_seconds(CAST(ts AS TIMESTAMP)) < 14400") if gap else None
    return E.chain(_table("events")(spark, d), "event_id", ["user_id"], ["ts", "event_id"], close)


def event_path(spark: SparkSession, d: str) -> DataFrame:
    e = _table("events")(spark, d).select(F.col("event_id").alias("src"))
    return e.join(e.select(F.col("src").alias("dst")), F.col("src") + 1 == F.col("dst"))


def shared_lines(spark: SparkSession, d: str) -> DataFrame:
    lines = _table("documents")(spark, d).select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line"))
    return E.shared_value(lines.where(F.length("line") >= 20), "doc_id", "line")


def shared_hrefs(spark: SparkSession, d: str) -> DataFrame:
    links = _table("pages")(spark, d).select("page_id", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("href"))
    return E.shared_value(links, "page_id", "href")


def shared_hosts(spark: SparkSession, d: str) -> DataFrame:
    host = F.regexp_extract("url", "//([^/]+)/", 1)
    return E.shared_value(_table("pages")(spark, d).where(host != ""), "page_id", host)


def cosine_edges(spark: SparkSession, d: str, least: float = 0.3) -> DataFrame:
    return E.similar_vectors(_table("embeddings")(spark, d), "vec_id", "embedding", least, block=16384)


def turns(spark: SparkSession, d: str) -> DataFrame:
    t = _table("conversations")(spark, d).select((F.col("conv_id") * 100 + F.col("turn")).alias("src"))
    return t.join(t.select(F.col("src").alias("dst")), F.col("src") + 1 == F.col("dst"))


def user_k(spark: SparkSession, d: str) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("long")
    return E.bipartite(_table("events")(spark, d).select("user_id", k.alias("k")).where("k IS NOT NULL"), "user_id", "k")


_COS = "SELECT a.vec_id AS src, b.vec_id AS dst FROM (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings) a JOIN (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings) b ON a.vec_id < b.vec_id WHERE round(list_cosine_similarity(a.v, b.v), 6) >= {}"
_CHAIN = "SELECT src, dst FROM (SELECT event_id AS src, lead(event_id) OVER w AS dst, ts, lead(ts) OVER w AS nts FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE dst IS NOT NULL"
_LINE_ROWS = "(SELECT doc_id, trim(line, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)) WHERE length(line) >= 20"
_K_EDGES = "SELECT DISTINCT user_id * 2 AS src, k * 2 + 1 AS dst FROM (SELECT user_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events) WHERE k IS NOT NULL"


def _own(key: str, edges: tuple, vertices: tuple, direct: str | None = None) -> Graph:
    return Graph(key, edges[0], vertices[0], edges[1], vertices[1], direct)


def _k_vertices(spark: SparkSession, d: str) -> DataFrame:
    return E.vertices_of(user_k(spark, d))


_ORDER_PART = _ids(("orders", "o_orderkey * 2"), ("part", "p_partkey * 2 + 1"))
_EVENTS, _ORDERS, _DOCS, _PAGES, _VECS = _ids(("events", "event_id")), _ids(("orders", "o_orderkey")), _ids(("documents", "doc_id")), _ids(("pages", "page_id")), _ids(("embeddings", "vec_id"))

GRAPHS: dict[str, Graph] = {
    g.key: g
    for g in [
        _own("orderpart", _bipartite("lineitem", "l_orderkey", "l_partkey"), _ORDER_PART),
        _own("partsupp", _bipartite("lineitem", "l_partkey", "l_suppkey"), _ids(("part", "p_partkey * 2"), ("supplier", "s_suppkey * 2 + 1"))),
        _own("orderpart46", _bipartite("lineitem", "l_orderkey", "l_partkey", "l_quantity >= 46"), _ORDER_PART),
        _own("orderpart50", _bipartite("lineitem", "l_orderkey", "l_partkey", "l_quantity >= 50"), _ORDER_PART),
        _own("custorder", _bipartite("orders", "o_custkey", "o_orderkey"), _ids(("customer", "c_custkey * 2"), ("orders", "o_orderkey * 2 + 1"))),
        _own(
            "orderchain",
            (lambda s, d: E.chain(_table("orders")(s, d), "o_orderkey", ["o_custkey"], ["o_orderdate", "o_orderkey"]), "SELECT src, dst FROM (SELECT o_orderkey AS src, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS dst FROM orders) WHERE dst IS NOT NULL"),
            _ORDERS,
            "SELECT o_orderkey AS id, min(o_orderkey) OVER (PARTITION BY o_custkey) AS component FROM orders",
        ),
        _own("eventchain", (event_chain, _CHAIN), _EVENTS),
        _own("eventpath", (event_path, "SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON b.event_id = a.event_id + 1"), _EVENTS, "SELECT event_id AS id, min(event_id) OVER (PARTITION BY event_id - r) AS component FROM (SELECT event_id, row_number() OVER (ORDER BY event_id) AS r FROM events)"),
        _own("eventsession", (lambda s, d: event_chain(s, d, True), _CHAIN + " AND date_diff('second', ts, nts) < 14400"), _EVENTS),
        _own("docexact", (lambda s, d: E.shared_value(_table("documents")(s, d), "doc_id", "text"), _star_of("doc_id", "documents", "text")), _DOCS, "SELECT doc_id AS id, min(doc_id) OVER (PARTITION BY text) AS component FROM documents"),
        _own("docline", (shared_lines, _star_of("doc_id", _LINE_ROWS, "line")), _DOCS),
        _own("pagehref", (shared_hrefs, _star_of("page_id", "(SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages)", "href")), _PAGES),
        _own("pagehost", (shared_hosts, _star_of("page_id", "pages", "nullif(regexp_extract(url, '//([^/]+)/', 1), '')")), _PAGES),
        _own("cosine3", (cosine_edges, _COS.format(0.3)), _VECS),
        _own("cosine4", (lambda s, d: cosine_edges(s, d, 0.4), _COS.format(0.4)), _VECS),
        _own("turns", (turns, "SELECT a.conv_id * 100 + a.turn AS src, b.conv_id * 100 + b.turn AS dst FROM conversations a JOIN conversations b ON b.conv_id * 100 + b.turn = a.conv_id * 100 + a.turn + 1"), _ids(("conversations", "conv_id * 100 + turn"))),
        _own("nationregion", _bipartite("nation", "n_regionkey", "n_nationkey"), _ids(("region", "r_regionkey * 2"), ("nation", "n_nationkey * 2 + 1"))),
        _own("userk", (user_k, _K_EDGES), (_k_vertices, f"SELECT src AS id FROM ({_K_EDGES}) UNION SELECT dst FROM ({_K_EDGES})")),
        _own("custpart", (customer_part, "SELECT DISTINCT o_custkey * 2 AS src, l_partkey * 2 + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_quantity >= 50 AND l_discount >= 0.09"), _ids(("customer", "c_custkey * 2"), ("part", "p_partkey * 2 + 1"))),
    ]
}
