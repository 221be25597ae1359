"""Edge builders over the given tables, one for each experiment graph, with the same edges in SQL.

Each returns canonical edges and, where vertices without edges matter, the vertices.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ccspark.functions import textlinks, vectors, vertexids
from ccspark.operators import edges as E
from ccspark.plans.store import Scratch
from ccspark.sources.io import load

MIN_LINE, MIN_COSINE, MAX_GAP_S = 20, 0.4, 7200


def purchase(spark, d):
    o, li = load(spark, d, "orders"), load(spark, d, "lineitem")
    j = o.join(li, o["o_orderkey"] == li["l_orderkey"])
    return E.simplify(j.select(vertexids.encode("customer", F.col("o_custkey")).alias("src"), vertexids.encode("part", F.col("l_partkey")).alias("dst"))), None


def copart(spark, d):
    li = load(spark, d, "lineitem").select("l_orderkey", "l_partkey")
    return E.simplify(li.select("l_orderkey", F.col("l_partkey").alias("src")).join(li.select("l_orderkey", F.col("l_partkey").alias("dst")), "l_orderkey").where("src < dst")), None


def _starred(rows: DataFrame):
    return E.star(rows, "k", "v"), rows.select("v").distinct()


def pagelink(spark, d):
    return _starred(load(spark, d, "pages").select(F.col("page_id").alias("v"), F.explode(textlinks.links(F.col("html"))).alias("k")))


def pagehost(spark, d):
    return _starred(load(spark, d, "pages").select(F.col("page_id").alias("v"), textlinks.host(F.col("url")).alias("k")).where("k is not null"))


def embedsim(spark, d):
    return E.simplify(vectors.similar_pairs(load(spark, d, "embeddings"), "vec_id", "embedding", MIN_COSINE)), None


def docline(spark, d):
    return _starred(load(spark, d, "documents").select(F.col("doc_id").alias("v"), F.explode(textlinks.lines(F.col("text"), MIN_LINE)).alias("k")))


def sparse_orders(spark, d):
    li = load(spark, d, "lineitem").where("l_quantity >= 45 and l_returnflag = 'R' and l_discount >= 0.05")
    return E.simplify(li.select(vertexids.encode("order", F.col("l_orderkey")).alias("src"), vertexids.encode("part", F.col("l_partkey")).alias("dst"))), None


def doc_exact(spark, d):
    rows = load(spark, d, "documents").select(F.col("doc_id").alias("v"), textlinks.digest(F.col("text")).alias("k"))
    return E.star(rows, "k", "v"), rows.select("v")


def user_paths(spark, d):
    return E.simplify(E.gap_links(load(spark, d, "events"), "user_id", "ts", "event_id")), None


def global_path(spark, d):
    """Successive events of all: dealt by range, linked in each part, and from each part to the next that has rows."""
    ev = load(spark, d, "events").select("ts", F.col("event_id").cast("long").alias("v"))
    dealt = Scratch(spark, "global-path").write(ev.repartitionByRange("ts", "v").withColumn("part", F.spark_partition_id()), "events")
    inside = dealt.select(F.col("v").alias("src"), F.lead("v").over(Window.partitionBy("part").orderBy("ts", "v")).alias("dst")).where("dst is not null")
    ends = dealt.groupBy("part").agg(F.min(F.struct("ts", "v"))["v"].alias("head"), F.max(F.struct("ts", "v"))["v"].alias("tail"))
    over = Window.orderBy("part")  # one row a part
    seams = ends.select(F.lag("tail").over(over).alias("src"), F.col("head").alias("dst")).where("src is not null")
    return E.simplify(inside.unionByName(seams)), None


def turn_chain(spark, d):
    c = load(spark, d, "conversations").where("turn > 0").select((F.col("conv_id") * 1024 + F.col("turn")).alias("dst"))
    return E.simplify(c.select((F.col("dst") - 1).alias("src"), "dst")), None


def hierarchy(spark, d):
    c, s, n = load(spark, d, "customer"), load(spark, d, "supplier"), load(spark, d, "nation")
    pair = lambda df, a, x, b, y: df.select(vertexids.encode(a, F.col(x)).alias("src"), vertexids.encode(b, F.col(y)).alias("dst"))
    all_ = pair(c, "customer", "c_custkey", "nation", "c_nationkey").unionByName(pair(s, "supplier", "s_suppkey", "nation", "s_nationkey")).unionByName(pair(n, "nation", "n_nationkey", "region", "n_regionkey"))
    return E.simplify(all_), None


def sessions(spark, d, gap_s: float = MAX_GAP_S):
    ev = load(spark, d, "events")
    return E.simplify(E.gap_links(ev, "user_id", "ts", "event_id", gap_s)), ev.select(F.col("event_id").cast("long").alias("v"))


@dataclass(frozen=True)
class Workload:
    build: Callable[[SparkSession, str], tuple[DataFrame, DataFrame | None]]
    edges_sql: str
    vertices_sql: str | None = None
    closed_sql: str | None = None


def _star_sql(rows: str) -> tuple[str, str]:
    low = f"SELECT v, min(v) OVER (PARTITION BY k) AS low FROM ({rows})"
    return f"SELECT DISTINCT low AS src, v AS dst FROM ({low}) WHERE low < v", f"SELECT DISTINCT v FROM ({rows})"


_LINK = """SELECT DISTINCT page_id AS v, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS k FROM pages"""
_HOST = "SELECT page_id AS v, regexp_extract(url, '://([^/:?]+)', 1) AS k FROM pages WHERE regexp_matches(url, '://([^/:?]+)')"
_LINE = f"SELECT DISTINCT v, k FROM (SELECT doc_id AS v, trim(unnest(string_split(text, chr(10)))) AS k FROM documents) WHERE length(k) >= {MIN_LINE}"
_SESSION = f"""SELECT event_id AS vertex, min(event_id) OVER (PARTITION BY user_id, s) AS component FROM (
SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (
SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL {MAX_GAP_S} SECOND THEN 0 ELSE 1 END AS b FROM events))"""
_MANY = "count(*) OVER (PARTITION BY user_id) > 1"

WORKLOADS = {
    "purchase": Workload(purchase, "SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM (SELECT o_custkey * 8 + 1 AS a, l_partkey * 8 + 2 AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey)"),
    "copart": Workload(copart, "SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey"),
    "pagelink": Workload(pagelink, *_star_sql(_LINK)),
    "pagehost": Workload(pagehost, *_star_sql(_HOST)),
    "embedsim": Workload(embedsim, f"SELECT a.vec_id AS src, b.vec_id AS dst FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id WHERE list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) >= {MIN_COSINE}"),
    "docline": Workload(docline, *_star_sql(_LINE)),
    "sparse_orders": Workload(sparse_orders, "SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM (SELECT l_orderkey * 8 + 3 AS a, l_partkey * 8 + 2 AS b FROM lineitem WHERE l_quantity >= 45 AND l_returnflag = 'R' AND l_discount >= 0.05)"),
    "doc_exact": Workload(doc_exact, *_star_sql("SELECT doc_id AS v, text AS k FROM documents"), "SELECT doc_id AS vertex, min(doc_id) OVER (PARTITION BY text) AS component FROM documents"),
    "user_paths": Workload(user_paths, "SELECT event_id AS src, n AS dst FROM (SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM events) WHERE n IS NOT NULL", None, f"SELECT event_id AS vertex, min(event_id) OVER (PARTITION BY user_id) AS component FROM events QUALIFY {_MANY}"),
    "global_path": Workload(global_path, "SELECT event_id AS src, n AS dst FROM (SELECT event_id, lead(event_id) OVER (ORDER BY ts, event_id) AS n FROM events) WHERE n IS NOT NULL", None, "SELECT event_id AS vertex, min(event_id) OVER () AS component FROM events"),
    "turn_chain": Workload(turn_chain, "SELECT conv_id * 1024 + turn - 1 AS src, conv_id * 1024 + turn AS dst FROM conversations WHERE turn > 0", None, "SELECT DISTINCT v AS vertex, conv_id * 1024 AS component FROM (SELECT conv_id, unnest([conv_id * 1024 + turn - 1, conv_id * 1024 + turn]) AS v FROM conversations WHERE turn > 0)"),
    "hierarchy": Workload(hierarchy, "SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM (SELECT c_custkey * 8 + 1 AS a, c_nationkey * 8 + 5 AS b FROM customer UNION ALL SELECT s_suppkey * 8 + 4, s_nationkey * 8 + 5 FROM supplier UNION ALL SELECT n_nationkey * 8 + 5, n_regionkey * 8 + 6 FROM nation)"),
    "sessions": Workload(sessions, f"SELECT event_id AS src, n AS dst FROM (SELECT event_id, ts, lead(event_id) OVER w AS n, lead(ts) OVER w AS t FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE t - ts <= INTERVAL {MAX_GAP_S} SECOND", "SELECT event_id AS v FROM events", _SESSION),
}


def components_sql(name: str) -> str:
    """The components in DuckDB: a closed form, or smaller labels spread along edges until none improves."""
    w = WORKLOADS[name]
    if w.closed_sql:
        return f"SELECT vertex::BIGINT AS vertex, component::BIGINT AS component FROM ({w.closed_sql})"
    return spread_sql(w.edges_sql, w.vertices_sql)


def spread_sql(edges_sql: str, vertices_sql: str | None = None) -> str:
    """Smaller labels spread along the edges until none improves."""
    vertices = "SELECT src AS v FROM s" + (f" UNION SELECT v FROM ({vertices_sql})" if vertices_sql else "")
    return f"""
WITH RECURSIVE e AS MATERIALIZED ({edges_sql}), s AS MATERIALIZED (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e),
cc(vertex, component) USING KEY (vertex) AS (
  SELECT v, v FROM (SELECT DISTINCT v FROM ({vertices}))
  UNION
  SELECT s.dst, min(c.component) FROM cc c JOIN s ON s.src = c.vertex JOIN recurring.cc r ON r.vertex = s.dst WHERE c.component < r.component GROUP BY s.dst
) SELECT vertex::BIGINT AS vertex, component::BIGINT AS component FROM cc"""
