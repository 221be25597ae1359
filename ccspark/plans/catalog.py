"""The library's own queries and their SQL twins.

Names: ``<method>__<workload>`` for components, ``step_<name>__<workload>`` for one step with the
affine order, ``op_<name>`` for operators, ``cost_<name>`` and ``exp_<name>`` for measures and experiments.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from contextlib import contextmanager

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ccspark.functions import textlinks, vertexids
from ccspark.functions.priority import MODULUS, MULTIPLIER, Priority, permute64, unpermute64
from ccspark.operators import absorb, contract, edges, labels, post, stars
from ccspark.plans import metrics, sqlsurface, verify
from ccspark.plans.runner import connected_components, rewire
from ccspark.plans.store import Scratch
from ccspark.sources import generators
from ccspark.sources.io import load, page
from ccspark.sources.workloads import WORKLOADS, components_sql, spread_sql

_Q: dict[str, Callable] = {}
_SQL: dict[str, str] = {}
_SEED = 17
_AFFINE = Priority("affine", _SEED)


def _affine(x: str) -> str:
    return f"(({MULTIPLIER} * {x} + {_SEED}) % {MODULUS})"


_BACK = pow(MULTIPLIER, -1, MODULUS)


def _owner(y: str) -> str:
    return f"(((({y} - {_SEED} + {MODULUS}) % {MODULUS})::HUGEINT * {_BACK}) % {MODULUS})::BIGINT"


def _query(name: str, sql: str | None = None):
    def add(f):
        _Q[name] = f
        if sql is not None:
            _SQL[name] = sql
        return f

    return add


# ---- components: every method on the graphs that suit it

_ALL = list(WORKLOADS)
_RUNS: list[tuple[str, str, list[str], dict]] = [
    ("two_hop", "two_hop", _ALL, {"finish_edges": 0}),
    ("forest", "forest", ["purchase", "copart", "pagelink", "docline", "sparse_orders", "user_paths", "turn_chain", "hierarchy", "sessions"], {"finish_edges": 0}),
    ("forest_lookup", "forest", ["purchase", "pagelink", "user_paths", "global_path"], {"finish_edges": 0, "lookup": True}),
    ("rewire_merge", "rewire_merge", ["purchase", "copart", "pagelink", "embedsim", "sparse_orders", "user_paths"], {"finish_edges": 0}),
    ("star_alternation", "star_alternation", ["purchase", "pagelink", "turn_chain"], {}),
    ("star_alternation_lookup", "star_alternation", ["purchase", "turn_chain", "hierarchy"], {"lookup": True}),
    ("min_hub", "min_hub", ["purchase", "pagelink", "turn_chain", "hierarchy"], {"beyond": "contract"}),
    ("min_spread", "min_spread", ["purchase", "turn_chain", "hierarchy"], {}),
    ("full_cluster", "full_cluster", ["turn_chain", "embedsim", "pagehost"], {"beyond": "contract"}),
    ("single_task", "single_task", ["purchase", "docline", "user_paths"], {}),
    ("finisher", "two_hop", ["purchase", "copart", "docline"], {}),
    ("keep_isolated", "two_hop", ["sparse_orders", "docline"], {"finish_edges": 0, "drop_isolated": False}),
    ("lazy", "two_hop", ["hierarchy", "turn_chain"], {"finish_edges": 0, "lazy": 0.25}),
    ("inherited", "forest", ["purchase", "turn_chain"], {"finish_edges": 0, "reseed": False}),
    ("absorb_mean_degree", "two_hop", ["copart", "docline"], {"finish_edges": 0, "absorb": absorb.Schedule.mean_degree()}),
    ("absorb_squared", "two_hop", ["user_paths"], {"finish_edges": 0, "absorb": absorb.Schedule.squared(2)}),
    ("absorb_all_move", "two_hop", ["copart"], {"finish_edges": 0, "absorb": absorb.Schedule.explicit([8, 64]), "large_moves": True}),
    ("salted", "two_hop", ["hierarchy"], {"finish_edges": 0, "salt": 4}),
    ("preforest", "two_hop", ["copart", "user_paths"], {"finish_edges": 0, "preforest": True}),
    ("affine_order", "two_hop", ["user_paths"], {"finish_edges": 0, "priority": "affine"}),
]


def _components(workload: str, method: str, options: dict):
    def run(spark, sf_dir):
        e, v = WORKLOADS[workload].build(spark, sf_dir)
        return connected_components(e, vertices=v, method=method, **options).assignment

    return run


for _name, _method, _graphs, _options in _RUNS:
    for _g in _graphs:
        _query(f"{_name}__{_g}", components_sql(_g))(_components(_g, _method, _options))


_RANDOM = {
    "gnp": (lambda spark: generators.gnp(spark, 2000, seed=1), "SELECT range AS vertex, 0::BIGINT AS component FROM range(2000)"),
    "gnp_plus_path": (lambda spark: generators.gnp_plus(spark, 2000, "path", seed=2), "SELECT range AS vertex, 0::BIGINT AS component FROM range(2000)"),
    "gnp_plus_star": (lambda spark: generators.gnp_plus(spark, 1000, "star", seed=3), "SELECT range AS vertex, 0::BIGINT AS component FROM range(1000)"),
    "gnp_blocks": (lambda spark: generators.gnp_blocks(spark, [50, 400, 1500], seed=4), "SELECT range AS vertex, (CASE WHEN range < 50 THEN 0 WHEN range < 450 THEN 50 ELSE 450 END)::BIGINT AS component FROM range(1950)"),
}
for _name, (_graph, _sql) in _RANDOM.items():
    for _m, _options in (("two_hop", {}), ("two_hop_absorb", {"absorb": absorb.Schedule.mean_degree()}), ("forest", {"method": "forest"})):
        _query(f"{_m}__{_name}", _sql)(lambda spark, d, g=_graph, o=_options: connected_components(g(spark), finish_edges=0, **o).assignment)


# ---- single steps with the affine order

_S = "e AS MATERIALIZED ({edges}), s AS MATERIALIZED (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e)"
_CLOSED = f"c AS (SELECT src AS v, least(min({_affine('dst')}), {_affine('src')}) AS m FROM s GROUP BY src)"
_TWO = "t AS (SELECT s.dst AS v, min(c.m) AS label FROM s JOIN c ON c.v = s.src GROUP BY s.dst)"
_PARENT = f"p AS (SELECT src AS v, {_owner('min(' + _affine('dst') + ')')} AS parent FROM s GROUP BY src)"
_NODE = f"n AS (SELECT v, {_owner('label')} AS node FROM t)"


def _with(workload: str, *parts: str, last: str) -> str:
    return "WITH " + ", ".join([_S.format(edges=WORKLOADS[workload].edges_sql), *parts]) + " " + last


def _sym(workload):
    return lambda spark, d: edges.symmetrise(WORKLOADS[workload].build(spark, d)[0])


def _two_hop_nodes(sym):
    return labels.two_hop_min(sym, _AFFINE).select("v", _AFFINE.owner(F.col("label")).alias("node"))


def _steps(w: str) -> None:
    sym = _sym(w)

    _query(f"step_edges__{w}", f"SELECT src::BIGINT AS src, dst::BIGINT AS dst FROM ({WORKLOADS[w].edges_sql})")(lambda spark, d: WORKLOADS[w].build(spark, d)[0].select("src", "dst"))
    _query(f"step_closed_min__{w}", _with(w, _CLOSED, last="SELECT v::BIGINT AS v, m::BIGINT AS m FROM c"))(lambda spark, d: labels.closed_min(sym(spark, d), _AFFINE))
    _query(f"step_two_hop_min__{w}", _with(w, _CLOSED, _TWO, last="SELECT v::BIGINT AS v, label::BIGINT AS label FROM t"))(lambda spark, d: labels.two_hop_min(sym(spark, d), _AFFINE))
    _query(f"step_relabel__{w}", _with(w, _CLOSED, _TWO, _NODE, last="SELECT DISTINCT least(a.node, b.node) AS src, greatest(a.node, b.node) AS dst FROM e JOIN n a ON a.v = e.src JOIN n b ON b.v = e.dst WHERE a.node <> b.node"))(
        lambda spark, d: contract.relabel_edges(WORKLOADS[w].build(spark, d)[0], Scratch(spark, "step").write(_two_hop_nodes(sym(spark, d)), "map"))
    )
    _query(f"step_parent__{w}", _with(w, _PARENT, last="SELECT v::BIGINT AS v, parent FROM p"))(lambda spark, d: labels.lowest_neighbour(sym(spark, d), _AFFINE))
    _query(
        f"step_mutual_roots__{w}",
        _with(w, _PARENT, last=f"SELECT p.v::BIGINT AS v, CASE WHEN q.parent = p.v AND {_affine('p.v')} < {_affine('p.parent')} THEN p.v ELSE p.parent END::BIGINT AS parent FROM p JOIN p q ON q.v = p.parent"),
    )(lambda spark, d: labels.mutual_roots(Scratch(spark, "step").write(labels.lowest_neighbour(sym(spark, d), _AFFINE), "parent"), _AFFINE))
    rooted = f"m AS MATERIALIZED (SELECT p.v::BIGINT AS v, CASE WHEN q.parent = p.v AND {_affine('p.v')} < {_affine('p.parent')} THEN p.v ELSE p.parent END::BIGINT AS parent FROM p JOIN p q ON q.v = p.parent)"
    chase = "r(v, x) AS (SELECT v, parent FROM m UNION ALL SELECT r.v, m.parent FROM r JOIN m ON m.v = r.x WHERE m.parent <> r.x)"
    _query(f"step_jump_pointers__{w}", _with(w, _PARENT.replace("p AS (", "p AS MATERIALIZED ("), rooted, chase, last="SELECT r.v, r.x AS parent FROM r JOIN m ON m.v = r.x AND m.parent = r.x").replace("WITH ", "WITH RECURSIVE ", 1))(lambda spark, d: labels.jump_pointers(labels.mutual_roots(Scratch(spark, "step").write(labels.lowest_neighbour(sym(spark, d), _AFFINE), "parent"), _AFFINE), Scratch(spark, "step"))[0])
    _query(f"step_cluster_sizes__{w}", _with(w, _CLOSED, _TWO, _NODE, last="SELECT node, count(*)::BIGINT AS size FROM n GROUP BY node HAVING count(*) >= 2"))(lambda spark, d: absorb.large_nodes(_two_hop_nodes(sym(spark, d)), 2))
    _query(
        f"step_kth_largest__{w}",
        _with(w, _CLOSED, _TWO, _NODE, last=f"SELECT node, key FROM (SELECT node, {_affine('v')} AS key, row_number() OVER (PARTITION BY node ORDER BY {_affine('v')} DESC) AS r FROM n) WHERE r = 2"),
    )(lambda spark, d: absorb.kth_largest(_two_hop_nodes(sym(spark, d)), _AFFINE, 0, 2))
    hub = f"h AS (SELECT v AS src, {_owner('m')} AS hub FROM c)"
    _query(
        f"step_rewire__{w}",
        _with(w, _CLOSED, hub, last="SELECT DISTINCT least(a, b)::BIGINT AS src, greatest(a, b)::BIGINT AS dst FROM (SELECT s.dst AS a, h.hub AS b FROM s JOIN h ON h.src = s.src UNION ALL SELECT src, hub FROM h) WHERE a <> b"),
    )(lambda spark, d: rewire(WORKLOADS[w].build(spark, d)[0], _AFFINE))
    low = "l AS (SELECT src, least(min(dst), src) AS m FROM s GROUP BY src)"
    _query(f"step_large_star__{w}", _with(w, low, last="SELECT DISTINCT least(s.dst, l.m)::BIGINT AS src, greatest(s.dst, l.m)::BIGINT AS dst FROM s JOIN l ON l.src = s.src WHERE s.dst > s.src AND s.dst <> l.m"))(lambda spark, d: stars.large_star(WORKLOADS[w].build(spark, d)[0]))
    down = "w AS (SELECT src, dst, min(dst) OVER (PARTITION BY src) AS m FROM s WHERE dst < src)"
    _query(f"step_small_star__{w}", _with(w, down, last="SELECT DISTINCT least(a, m)::BIGINT AS src, greatest(a, m)::BIGINT AS dst FROM (SELECT dst AS a, m FROM w UNION ALL SELECT src, m FROM w) WHERE a <> m"))(lambda spark, d: stars.small_star(WORKLOADS[w].build(spark, d)[0]))
    _query(f"step_min_spread__{w}", _with(w, low, last="SELECT src::BIGINT AS vertex, m::BIGINT AS label FROM l"))(lambda spark, d: labels.closed_min(sym(spark, d), Priority("identity")).select(F.col("v").alias("vertex"), F.col("m").alias("label")))
    _query(f"step_distinct_labels__{w}", _with(w, _CLOSED, _TWO, last="SELECT count(*)::BIGINT AS vertices, count(DISTINCT label)::BIGINT AS labels FROM t"))(lambda spark, d: labels.two_hop_min(sym(spark, d), _AFFINE).agg(F.count(F.lit(1)).alias("vertices"), F.count_distinct("label").alias("labels")))
    _query(f"step_isolated__{w}", _with(w, "x AS (SELECT src AS v FROM s GROUP BY src HAVING count(*) = 1)", last="SELECT v::BIGINT AS v FROM x"))(lambda spark, d: edges.degrees(WORKLOADS[w].build(spark, d)[0]).where("degree = 1").select("v"))


for _g in ("purchase", "user_paths", "hierarchy"):
    _steps(_g)

_query("op_closed_min_by_struct", _with("purchase", _CLOSED, last="SELECT v::BIGINT AS v, m::BIGINT AS m FROM c"))(lambda spark, d: labels.closed_min_by_struct(_sym("purchase")(spark, d), _AFFINE))


# ---- operators around the methods


def _assigned(spark, d, w="docline"):
    e, v = WORKLOADS[w].build(spark, d)
    return connected_components(e, vertices=v).assignment


def _cc(w: str) -> str:
    return f"({components_sql(w)})"


_query("op_degrees", f"SELECT v::BIGINT AS v, count(*)::BIGINT AS degree FROM (SELECT unnest([src, dst]) AS v FROM ({WORKLOADS['purchase'].edges_sql})) GROUP BY v")(lambda spark, d: edges.degrees(WORKLOADS["purchase"].build(spark, d)[0]))
_query("op_top_degrees", f"SELECT v::BIGINT AS v, count(*)::BIGINT AS degree FROM (SELECT unnest([src, dst]) AS v FROM ({WORKLOADS['hierarchy'].edges_sql})) GROUP BY v ORDER BY degree DESC, v LIMIT 10")(lambda spark, d: metrics.top_degrees(WORKLOADS["hierarchy"].build(spark, d)[0], 10))
_query("op_min_degree", f"WITH e AS MATERIALIZED ({WORKLOADS['copart'].edges_sql}), k AS MATERIALIZED (SELECT v FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v HAVING count(*) >= 100) SELECT e.src::BIGINT AS src, e.dst::BIGINT AS dst FROM e JOIN k a ON a.v = e.src JOIN k b ON b.v = e.dst")(lambda spark, d: edges.min_degree(WORKLOADS["copart"].build(spark, d)[0], 100))
_query("op_induced", f"SELECT src::BIGINT AS src, dst::BIGINT AS dst FROM ({WORKLOADS['copart'].edges_sql}) WHERE src % 3 = 0 AND dst % 3 = 0")(lambda spark, d: edges.induced(WORKLOADS["copart"].build(spark, d)[0], load(spark, d, "part").select(F.col("p_partkey").alias("v")).where("v % 3 = 0")))
_UNION = " UNION ALL ".join(f"SELECT src, dst FROM ({WORKLOADS[w].edges_sql})" for w in ("user_paths", "global_path"))
_query("op_union_edges", f"SELECT least(src, dst)::BIGINT AS src, greatest(src, dst)::BIGINT AS dst FROM ({_UNION})")(lambda spark, d: edges.union_all(*[WORKLOADS[w].build(spark, d)[0] for w in ("user_paths", "global_path")]))
_PAIRS = {w: f"SELECT least(src, dst)::BIGINT AS src, greatest(src, dst)::BIGINT AS dst FROM ({WORKLOADS[w].edges_sql})" for w in ("user_paths", "global_path")}
_query("op_common_edges", f"{_PAIRS['user_paths']} INTERSECT {_PAIRS['global_path']}")(lambda spark, d: edges.common(*[WORKLOADS[w].build(spark, d)[0] for w in ("user_paths", "global_path")]))
_query("op_minus_edges", f"{_PAIRS['global_path']} EXCEPT {_PAIRS['user_paths']}")(lambda spark, d: edges.minus(*[WORKLOADS[w].build(spark, d)[0] for w in ("global_path", "user_paths")]))
_query("op_where_edges", "SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM (SELECT o_custkey * 8 + 1 AS a, l_partkey * 8 + 2 AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_quantity >= 40)")(
    lambda spark, d: edges.simplify(edges.where(load(spark, d, "lineitem"), "l_quantity >= 40").join(load(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).select(vertexids.encode("customer", F.col("o_custkey")).alias("src"), vertexids.encode("part", F.col("l_partkey")).alias("dst")))
)
_query("op_band_join", "SELECT a.p_partkey::BIGINT AS src, b.p_partkey::BIGINT AS dst FROM part a JOIN part b ON a.p_partkey < b.p_partkey AND abs(a.p_retailprice - b.p_retailprice) <= 0.25")(lambda spark, d: edges.band_join(load(spark, d, "part"), "p_partkey", "p_retailprice", 0.25))
_query("op_overlap_join", "WITH i AS (SELECT event_id, user_id, epoch(ts)::BIGINT AS a, epoch(ts)::BIGINT + 5400 AS b FROM events) SELECT x.event_id::BIGINT AS src, y.event_id::BIGINT AS dst FROM i x JOIN i y ON x.user_id = y.user_id AND x.event_id < y.event_id AND x.a <= y.b AND y.a <= x.b")(
    lambda spark, d: edges.overlap_join(load(spark, d, "events").select("event_id", "user_id", F.unix_seconds(F.col("ts").cast("timestamp")).alias("a")).withColumn("b", F.col("a") + 5400), "event_id", "user_id", "a", "b", 3600)
)
_query("op_page", "SELECT o_orderkey, o_custkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50 OFFSET 100")(lambda spark, d: page(load(spark, d, "orders").withColumn("down", -F.col("o_totalprice")), ["down", "o_orderkey"], 50, 100).select("o_orderkey", "o_custkey"))
_query("op_asof_link", "SELECT src, dst FROM (SELECT o.o_orderkey::BIGINT AS src, p.o_orderkey::BIGINT AS dst, row_number() OVER (PARTITION BY o.o_orderkey ORDER BY p.o_orderdate DESC, p.o_orderkey DESC) AS r FROM orders o JOIN orders p ON o.o_custkey = p.o_custkey AND p.o_orderdate <= o.o_orderdate WHERE o.o_orderpriority = '1-URGENT' AND p.o_orderpriority <> '1-URGENT') WHERE r = 1")(
    lambda spark, d: edges.asof_link(load(spark, d, "orders").where("o_orderpriority = '1-URGENT'"), load(spark, d, "orders").where("o_orderpriority <> '1-URGENT'"), "o_custkey", "o_orderdate", "o_orderkey", "o_orderkey")
)
_query("op_split_isolated", f"SELECT event_id::BIGINT AS v FROM events WHERE event_id NOT IN (SELECT unnest([src, dst]) FROM ({WORKLOADS['sessions'].edges_sql}))")(lambda spark, d: contract.split_isolated(WORKLOADS["sessions"].build(spark, d)[1], WORKLOADS["sessions"].build(spark, d)[0])[1])
_query("op_component_sizes", f"SELECT component, count(*)::BIGINT AS size FROM {_cc('docline')} GROUP BY component")(lambda spark, d: metrics.component_sizes(_assigned(spark, d)))
_query("op_size_histogram", f"SELECT size, count(*)::BIGINT AS components FROM (SELECT component, count(*)::BIGINT AS size FROM {_cc('docline')} GROUP BY component) GROUP BY size")(lambda spark, d: metrics.size_histogram(_assigned(spark, d)))
_query("op_top_components", f"SELECT component, count(*)::BIGINT AS size FROM {_cc('docline')} GROUP BY component ORDER BY size DESC, component LIMIT 10")(lambda spark, d: metrics.top_components(_assigned(spark, d), 10))
_query(
    "op_rank_components",
    f'WITH z AS (SELECT component, count(*)::BIGINT AS size FROM {_cc("sessions")} GROUP BY component), b AS (SELECT *, length(size::VARCHAR)::INTEGER AS band FROM z) SELECT component, size, band, (row_number() OVER w)::INTEGER AS "row", (rank() OVER t)::INTEGER AS rank, (dense_rank() OVER t)::INTEGER AS dense, (ntile(4) OVER w)::INTEGER AS tile FROM b WINDOW w AS (PARTITION BY band ORDER BY size DESC, component), t AS (PARTITION BY band ORDER BY size DESC)',
)(lambda spark, d: metrics.rank_components(_assigned(spark, d, "sessions")))
_query("op_count_nodes", f"SELECT count(DISTINCT vertex)::BIGINT AS vertices, count(DISTINCT component)::BIGINT AS components FROM {_cc('docline')}")(lambda spark, d: metrics.count_nodes(_assigned(spark, d)))
_query("op_count_nodes_approx")(lambda spark, d: metrics.count_nodes(_assigned(spark, d), approx=True))
_query("op_size_percentiles", f"SELECT quantile_disc(size, [0.5, 0.9, 0.99]) AS sizes, max(size) AS largest, count(*)::BIGINT AS components FROM (SELECT count(*)::BIGINT AS size FROM {_cc('docline')} GROUP BY component)")(lambda spark, d: metrics.size_percentiles(_assigned(spark, d)))
for _how, _sets in (("rollup", "ROLLUP (lang, source)"), ("cube", "CUBE (lang, source)"), ("sets", "GROUPING SETS ((lang), (source))")):
    _query(f"op_by_attributes_{_how}", f"SELECT lang, source, count(*)::BIGINT AS vertices, count(DISTINCT component)::BIGINT AS components FROM {_cc('docline')} JOIN documents ON doc_id = vertex GROUP BY {_sets}")(lambda spark, d, how=_how: metrics.by_attributes(_assigned(spark, d), load(spark, d, "documents"), "doc_id", ["lang", "source"], how))
_query("op_dedupe_rows", f"SELECT doc_id, lang FROM documents JOIN {_cc('doc_exact')} ON doc_id = vertex WHERE vertex = component")(lambda spark, d: post.dedupe(load(spark, d, "documents"), _assigned(spark, d, "doc_exact"), "doc_id").select("doc_id", "lang"))
_query("op_members", f"SELECT component, list(vertex ORDER BY vertex) AS members FROM {_cc('sparse_orders')} GROUP BY component HAVING count(*) <= 100")(lambda spark, d: post.members(_assigned(spark, d, "sparse_orders"), 100))
_USER_CC = "event_id::BIGINT AS vertex, (min(event_id) OVER (PARTITION BY user_id))::BIGINT AS component FROM events QUALIFY count(*) OVER (PARTITION BY user_id) > 1"
_USER_EDGES = lambda spark, d: edges.gap_links(load(spark, d, "events"), "user_id", "ts", "event_id").join(load(spark, d, "events").select(F.col("event_id").cast("long").alias("src"), "user_id"), "src")
_query("op_per_block", f"SELECT user_id::BIGINT AS user_id, {_USER_CC}")(lambda spark, d: post.per_block(_USER_EDGES(spark, d), "user_id"))
_query("op_local_components", f"SELECT user_id::BIGINT AS k, {_USER_CC}")(lambda spark, d: sqlsurface.local_components(_USER_EDGES(spark, d), "user_id"))


@_query("op_component_count", "SELECT user_id::BIGINT AS user_id, 1::BIGINT AS components FROM events GROUP BY user_id HAVING count(*) > 1")
def _component_count(spark, d):
    sqlsurface.register_functions(spark)
    _USER_EDGES(spark, d).createOrReplaceTempView("cc_user_edges")
    return spark.sql("SELECT user_id, component_count(src, dst) AS components FROM cc_user_edges GROUP BY user_id")


_query(
    "op_spread_sql",
    "WITH g AS (SELECT n_regionkey AS r, least(min(n_nationkey * 8 + 5), n_regionkey * 8 + 6) AS m FROM nation GROUP BY n_regionkey) "
    "SELECT (n_nationkey * 8 + 5)::BIGINT AS vertex, m::BIGINT AS component FROM nation JOIN g ON r = n_regionkey UNION ALL SELECT r * 8 + 6, m FROM g",
)(lambda spark, d: sqlsurface.spread_sql(load(spark, d, "nation").select(vertexids.encode("nation", F.col("n_nationkey")).alias("src"), vertexids.encode("region", F.col("n_regionkey")).alias("dst")), 3))
_query("op_permute_round_trip", "SELECT event_id::BIGINT AS v, event_id::BIGINT AS back FROM events")(lambda spark, d: load(spark, d, "events").select(F.col("event_id").cast("long").alias("v"), unpermute64(permute64(F.col("event_id"), 3, 5), 3, 5).alias("back")))
_query("op_affine", f"SELECT event_id::BIGINT AS v, {_affine('event_id')}::BIGINT AS p FROM events")(lambda spark, d: load(spark, d, "events").select(F.col("event_id").cast("long").alias("v"), _AFFINE.of(F.col("event_id")).cast("long").alias("p")))

def _kinds(spark, d):
    """Customers of all orders and parts of all items, whether the two meet or not; a null key is one more of its kind."""
    ids = [load(spark, d, t).select(vertexids.encode(kind, F.col(key)).alias("v")).distinct().select(F.coalesce(vertexids.kind_of(F.col("v")), F.lit(vertexids.KINDS[kind])).alias("kind")) for t, kind, key in (("orders", "customer", "o_custkey"), ("lineitem", "part", "l_partkey"))]
    return ids[0].unionByName(ids[1]).groupBy("kind").agg(F.count(F.lit(1)).alias("n"))


_query("op_entity_kinds", "SELECT kind::INTEGER AS kind, count(*)::BIGINT AS n FROM (SELECT DISTINCT o_custkey * 8 + 1 AS v, 1 AS kind FROM orders UNION ALL SELECT DISTINCT l_partkey * 8 + 2, 2 FROM lineitem) GROUP BY kind")(_kinds)
_query("op_dictionary", "SELECT value, (row_number() OVER (ORDER BY value) - 1)::BIGINT AS id FROM (SELECT DISTINCT p_brand AS value FROM part UNION SELECT DISTINCT p_type FROM part)")(lambda spark, d: vertexids.dictionary(load(spark, d, "part"), ["p_brand", "p_type"], Scratch(spark, "dictionary")))
_query("op_hash_collisions", "SELECT 0::BIGINT AS id, 0::BIGINT AS n WHERE false")(lambda spark, d: vertexids.collisions(load(spark, d, "documents"), "text"))
_query("op_json_key", "SELECT event_id::BIGINT AS event_id, json_extract_string(props, '$.k') AS k FROM events")(lambda spark, d: load(spark, d, "events").select(F.col("event_id").cast("long").alias("event_id"), vertexids.from_json(F.col("props"), "$.k").alias("k")))
_query("op_shingles", "SELECT item_id, len(list_distinct(list_transform(range(1, greatest(len(w) - 3, 1) + 1), lambda i: array_to_string(w[i : i + 3], ' '))))::INTEGER AS n FROM (SELECT item_id, regexp_split_to_array(trim(text), '\\s+') AS w FROM benchmark)")(lambda spark, d: load(spark, d, "benchmark").select("item_id", F.size(textlinks.shingles(F.col("text"), 4)).alias("n")))

@_query("op_gap_seconds", "SELECT event_id::BIGINT AS event_id, ((epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id))) / 1000000.0)::DOUBLE AS gap FROM events")
def _gaps(spark, d):
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, d, "events").select(F.col("event_id").cast("long").alias("event_id"), edges.gap_seconds(F.col("ts"), F.lag("ts").over(w)).cast("double").alias("gap"))


_LINKED = "SELECT a.vec_id AS src, b.vec_id AS dst FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id WHERE list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) >= {}"


@_query("op_single_linkage", " UNION ALL ".join(f"SELECT {i}::INTEGER AS level, {t}::DOUBLE AS threshold, vertex, component FROM ({spread_sql(_LINKED.format(t))})" for i, t in enumerate((0.6, 0.5, 0.4))))
def _linkage(spark, d):
    from ccspark.functions import vectors

    v = load(spark, d, "embeddings").select(F.col("vec_id").cast("long").alias("k"), "embedding")
    pairs = vectors.similar_pairs(v, "k", "embedding", 0.4)
    a, b = (v.select(F.col("k").alias(x), F.col("embedding").alias(f"{x}_v")) for x in ("src", "dst"))
    weighed = pairs.join(a, "src").join(b, "dst").select("src", "dst", vectors.cosine(F.col("src_v"), F.col("dst_v")).alias("w"))
    return post.levels(weighed, "w", [0.6, 0.5, 0.4])


# ---- measures and experiments


def _stats(spark, d, w, method, **options):
    e, v = WORKLOADS[w].build(spark, d)
    return connected_components(e, vertices=v, method=method, **options).stats_frame()


def _phases_sql(workload: str, phases: int, last: str) -> str:
    """Tables e0, t0, n0, e1, ... of the two-hop method with affine orders, whose seed grows by one a phase; ``last`` is repeated for each."""
    parts = [f"e0 AS MATERIALIZED ({WORKLOADS[workload].edges_sql})"]
    for k in range(phases):
        p = lambda x, k=k: f"(({MULTIPLIER} * {x} + {_SEED + k}) % {MODULUS})"
        back = f"((((label - {_SEED + k} + {MODULUS}) % {MODULUS})::HUGEINT * {_BACK}) % {MODULUS})::BIGINT"
        parts += [
            f"s{k} AS MATERIALIZED (SELECT src, dst FROM e{k} UNION ALL SELECT dst, src FROM e{k})",
            f"c{k} AS MATERIALIZED (SELECT src AS v, least(min({p('dst')}), {p('src')}) AS m FROM s{k} GROUP BY src)",
            f"n{k} AS MATERIALIZED (SELECT v, {back} AS node FROM (SELECT s.dst AS v, min(c.m) AS label FROM s{k} s JOIN c{k} c ON c.v = s.src GROUP BY s.dst))",
            f"e{k + 1} AS MATERIALIZED (SELECT DISTINCT least(a.node, b.node) AS src, greatest(a.node, b.node) AS dst FROM e{k} e JOIN n{k} a ON a.v = e.src JOIN n{k} b ON b.v = e.dst WHERE a.node <> b.node)",
        ]
    rows = " UNION ALL ".join(f"SELECT {k}::INTEGER AS phase, (SELECT count(*) FROM n{k})::BIGINT AS nodes_in, (SELECT count(*) FROM e{k})::BIGINT AS edges_in, (SELECT count(DISTINCT node) FROM n{k})::BIGINT AS labels, (SELECT max(n) FROM (SELECT count(*) AS n FROM n{k} GROUP BY node))::BIGINT AS largest_cluster" for k in range(phases))
    return f"WITH {', '.join(parts)}, stats AS (SELECT 'two_hop' AS method, * FROM ({rows}) WHERE edges_in > 0) {last}"


_BY_AFFINE = {"finish_edges": 0, "priority": "affine", "seed": _SEED}
for _g, _k in (("purchase", 4), ("copart", 4), ("pagelink", 6), ("embedsim", 7), ("docline", 7), ("sparse_orders", 6)):
    _query(f"cost_phase_stats__{_g}", _phases_sql(_g, _k, "SELECT method, phase, nodes_in, edges_in, labels, largest_cluster FROM stats"))(
        lambda spark, d, g=_g: _stats(spark, d, g, "two_hop", details=True, **_BY_AFFINE).select("method", "phase", "nodes_in", "edges_in", "labels", "largest_cluster")
    )
    _query(f"cost_edge_decay__{_g}", _phases_sql(_g, _k, "SELECT method, phase, edges_in, (edges_in / lead(edges_in) OVER (ORDER BY phase))::DOUBLE AS factor FROM stats"))(lambda spark, d, g=_g: metrics.decay(_stats(spark, d, g, "two_hop", **_BY_AFFINE)))
_query("cost_node_shrink", _phases_sql("docline", 7, "SELECT method, phase, nodes_in, (lead(nodes_in) OVER (ORDER BY phase) / nodes_in)::DOUBLE AS ratio FROM stats"))(lambda spark, d: metrics.shrink(_stats(spark, d, "docline", "two_hop", **_BY_AFFINE)))
_query("cost_density", _phases_sql("copart", 4, "SELECT method, phase, nodes_in, edges_in, (edges_in / (nodes_in * (nodes_in - 1) / 2.0))::DOUBLE AS density FROM stats"))(lambda spark, d: metrics.density(_stats(spark, d, "copart", "two_hop", **_BY_AFFINE)))
_query("cost_running")(lambda spark, d: metrics.running(_stats(spark, d, "user_paths", "forest", finish_edges=0)))
_query("cost_traffic")(lambda spark, d: _stats(spark, d, "copart", "two_hop", finish_edges=0).select("phase", "edges_in", "rounds", "records_sent", "bytes_sent", (F.col("records_sent") / F.col("edges_in")).alias("records_per_edge")))


@_query("cost_received")
def _received(spark, d):
    e = Scratch(spark, "received").write(WORKLOADS["hierarchy"].build(spark, d)[0], "edges")
    traffic = metrics.Traffic(spark)
    connected_components(e, finish_edges=0)
    got = traffic.received()
    return spark.createDataFrame([(float(got["bytes"]), float(got["ratio"]))], "most_bytes double, over_mean double")


_query("cost_skew", f"WITH n AS (SELECT v, count(*) AS n FROM (SELECT unnest([src, dst]) AS v FROM ({WORKLOADS['hierarchy'].edges_sql})) GROUP BY v) SELECT max(n)::BIGINT AS most, avg(n)::DOUBLE AS mean, count(*)::BIGINT AS keys, (max(n) / avg(n))::DOUBLE AS ratio FROM n")(lambda spark, d: metrics.skew(edges.symmetrise(WORKLOADS["hierarchy"].build(spark, d)[0]), "src"))


_DEPTHS = ("user_paths", "hierarchy", "purchase")


def _depth_sql(w: str) -> str:
    walk = "r(v, x, d) AS (SELECT v, v, 0 FROM p UNION ALL SELECT r.v, p.parent, r.d + 1 FROM r JOIN p ON p.v = r.x JOIN p q ON q.v = p.parent WHERE q.parent <> r.x)"
    return _with(w, _PARENT.replace("p AS (", "p AS MATERIALIZED ("), walk, last=f"SELECT '{w}' AS graph, max(d)::INTEGER AS depth FROM r").replace("WITH ", "WITH RECURSIVE ", 1)


@_query("cost_chain_depth", " UNION ALL ".join(f"SELECT * FROM ({_depth_sql(w)})" for w in _DEPTHS))
def _depth(spark, d):
    rows = []
    for w in _DEPTHS:
        scratch = Scratch(spark, "depth")
        parent = scratch.write(labels.lowest_neighbour(_sym(w)(spark, d), _AFFINE), "parent")
        rows.append((w, labels.chain_depth(parent, scratch)))
    return spark.createDataFrame(rows, "graph string, depth int")


@_query("cost_exchanges")
def _exchanges(spark, d):
    e = Scratch(spark, "plan").write(WORKLOADS["purchase"].build(spark, d)[0], "edges")
    rows = [("two_hop_min", metrics.exchanges(labels.two_hop_min(edges.symmetrise(e), _AFFINE))), ("lowest_neighbour", metrics.exchanges(labels.lowest_neighbour(edges.symmetrise(e), _AFFINE)))]
    return spark.createDataFrame(rows, "step string, exchanges int")


@_query("verify_label_identity", "SELECT * FROM (VALUES ('purchase', true), ('user_paths', true)) AS t(graph, same)")
def _identity(spark, d):
    return spark.createDataFrame([(w, verify.rewire_label_identity(WORKLOADS[w].build(spark, d)[0], 5)) for w in ("purchase", "user_paths")], "graph string, same boolean")


@_query("verify_random_graph_events")
def _events(spark, d):
    got = verify.random_graph_events(generators.gnp(spark, 2000, seed=1), 2000, 30, 1)
    return spark.createDataFrame(list(got.items()), "event string, share double")


@_query("verify_bernoulli_bound", "SELECT true AS holds")
def _bernoulli(spark, d):
    got, bound = verify.bernoulli_bound(load(spark, d, "events"), "event_id", 50, 0.01)
    return spark.createDataFrame([(bool(got >= bound),)], "holds boolean")


@_query("verify_half_rule", "SELECT * FROM (VALUES (1, true), (2, true), (3, true)) AS t(seed, holds)")
def _half(spark, d):
    e = WORKLOADS["user_paths"].build(spark, d)[0]
    return spark.createDataFrame([(s, verify.half_rule(e, s) >= 0.5) for s in (1, 2, 3)], "seed int, holds boolean")


@contextmanager
def _hash_joins(spark):
    """Within it AQE joins without a sort where one side's partitions, as counted once they are written, are small: each is held by one task."""
    most, names = f"{8 << 20}b", ("spark.sql.adaptive.maxShuffledHashJoinLocalMapThreshold", "spark.sql.adaptive.advisoryPartitionSizeInBytes")
    before = [spark.conf.get(k) for k in names]
    try:
        for k in names:  # a partition that AQE makes of several must not pass the bound either
            spark.conf.set(k, most)
        yield
    finally:
        for k, v in zip(names, before):
            spark.conf.set(k, v)


def _grid(spark, d, graphs, methods, **options):
    """Phases of each method on each graph. A graph is built once and read by all methods; runs go side by side, as their
    many small jobs leave most cores idle (their counts of what is sent would mix, and are not used). Labels meet the edges
    in hash joins where they fit."""
    from multiprocessing.pool import ThreadPool

    from pyspark import inheritable_thread_target

    from ccspark.plans.runner import TooLarge

    built = Scratch(spark, "grid")
    table = {}

    def build(w):
        table[w] = built.write(WORKLOADS[w].build(spark, d)[0], w)

    def run(w, m):
        scratch = Scratch(spark, m)
        try:
            r = connected_components(table[w], method=m, scratch=scratch, **(options if m in ("two_hop", "forest", "rewire_merge") else {}))
            return w, m, r.phases, "ok"
        except TooLarge:
            return w, m, None, "x"
        finally:
            scratch.drop()

    with ThreadPool(_ABREAST) as pool, _hash_joins(spark):
        pool.map(inheritable_thread_target(spark)(build), graphs, 1)
        rows = pool.starmap(inheritable_thread_target(spark)(run), [(w, m) for w in graphs for m in methods], 1)
    built.drop()
    return spark.createDataFrame(rows, "graph string, method string, phases int, status string")


#: Runs of an experiment that go side by side.
_ABREAST = 4
_GRAPHS = ["purchase", "copart", "pagelink", "embedsim", "docline", "sparse_orders"]
_query("exp_phases")(lambda spark, d: _grid(spark, d, _GRAPHS, ["two_hop", "forest", "rewire_merge", "star_alternation", "min_hub"], finish_edges=0))
_query("exp_phases_finisher")(lambda spark, d: _grid(spark, d, ["purchase", "copart", "docline"], ["two_hop", "forest", "rewire_merge"], finish_edges=1000))


@_query("exp_path_bound")
def _paths(spark, d):
    """Phases on a path of n vertices: each method's must grow with the logarithm of n, min_spread's with n itself."""
    longest = {"two_hop": 12, "forest": 12, "rewire_merge": 12, "star_alternation": 8, "min_hub": 10, "min_spread": 5}
    rows = []
    for m, most in longest.items():
        for k in range(4, most + 1, 1 if m == "min_spread" else 2):
            got = connected_components(generators.path(spark, 1 << k), method=m, **({"finish_edges": 0} if m in ("two_hop", "forest", "rewire_merge") else {}))
            rows.append((m, 1 << k, got.phases))
            got.scratch.drop()
    return spark.createDataFrame(rows, "method string, n long, phases int")


@_query("exp_absorption")
def _absorption(spark, d):
    """Random graphs of doubling size and of the relaxed classes: phases with and without absorption, nodes left after one phase
    against n over alpha, and their density against alpha squared over m."""
    graphs = [("gnp", n, lambda n=n: generators.gnp(spark, n, seed=n)) for n in (500, 1000, 2000, 4000)]
    graphs += [("gnp_plus_path", 2000, lambda: generators.gnp_plus(spark, 2000, "path", 5)), ("gnp_plus_star", 2000, lambda: generators.gnp_plus(spark, 2000, "star", 6)), ("gnp_blocks", 2050, lambda: generators.gnp_blocks(spark, [50, 500, 1500], 7))]
    rows = []
    for name, n, graph in graphs:
        for kind, s in (("none", None), ("mean_degree", absorb.Schedule.mean_degree())):
            r = connected_components(graph(), finish_edges=0, absorb=s)
            m = r.phase_stats[0].edges_in
            left = (r.phase_stats[1].nodes_in, r.phase_stats[1].edges_in) if len(r.phase_stats) > 1 else (0, 0)
            alpha = 2 * m / n
            bound = metrics.density_bound((n, m), left, alpha)
            rows.append((name, n, kind, r.phases, math.log2(math.log2(n)), left[0], n / alpha, bound["density"], bound["bound"]))
            r.scratch.drop()
    return spark.createDataFrame(rows, "graph string, n long, absorption string, phases int, log_log_n double, second_phase_nodes long, nodes_bound double, density double, density_bound double")


@_query("exp_scaling")
def _scaling(spark, d):
    """Phases, counted rows and seconds on graphs of ten times the size each: rows sent should stay in proportion to the edges."""
    rows = []
    for n in (1_000, 10_000, 100_000):
        e = Scratch(spark, "scaling").write(generators.forest_mix(spark, n, seed=1), "edges")
        for m in ("two_hop", "forest", "rewire_merge"):
            r = connected_components(e, method=m, finish_edges=0)
            first = r.phase_stats[0]
            rows.append((m, n, first.edges_in, r.phases, sum(s.records_sent for s in r.phase_stats) / first.edges_in, sum(s.seconds for s in r.phase_stats)))
            r.scratch.drop()
    return spark.createDataFrame(rows, "method string, n long, edges long, phases int, records_per_edge double, seconds double")


@_query("exp_store")
def _store(spark, d):
    """The map held by the tasks against doubling by joins: exchanges, rows sent and lookups of the methods that use it."""
    rows = []
    for w in ("user_paths", "hierarchy"):
        for m in ("forest", "star_alternation"):
            for lookup in (True, False):
                r = connected_components(WORKLOADS[w].build(spark, d)[0], method=m, lookup=lookup, **({"finish_edges": 0} if m == "forest" else {}))
                total = {k: sum(getattr(s, k) for s in r.phase_stats) for k in ("rounds", "records_sent", "lookups", "jump_steps")}
                rows.append((w, m, lookup, r.phases, *total.values()))
                r.scratch.drop()
    return spark.createDataFrame(rows, "graph string, method string, lookup boolean, phases int, rounds long, records_sent long, lookups long, jump_steps long")


@_query("exp_two_cycles", "SELECT * FROM (VALUES ('one', 1::BIGINT), ('two', 2::BIGINT)) AS t(graph, components)")
def _two_cycles(spark, d):
    rows = [(name, connected_components(generators.cycles(spark, 400, k), finish_edges=0).assignment.select("component").distinct().count()) for name, k in (("one", 1), ("two", 2))]
    return spark.createDataFrame(rows, "graph string, components long")


@_query("stream_merge", components_sql("user_paths"))
def _stream(spark, d):
    import uuid

    from ccspark.plans.store import shared_dir
    from ccspark.streaming.incremental import AssignmentStore, merge_batches, read_edges

    folder = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    WORKLOADS["user_paths"].build(spark, d)[0].repartition(3, "src").write.parquet(f"{folder}/edges")
    store = AssignmentStore(spark)
    merge_batches(read_edges(spark, f"{folder}/edges"), store, f"{folder}/checkpoint").awaitTermination()
    return store.current


@_query("stream_sessions", f"SELECT user_id::BIGINT AS user_id, min(vertex)::BIGINT AS component, count(*)::BIGINT AS n FROM {_cc('sessions')} JOIN events ON event_id = vertex GROUP BY user_id, component")
def _sessions(spark, d):
    from ccspark.streaming.windows import window_components

    # the boundary of a session window is open, so a gap of exactly the length starts a new one; the links keep it
    ev = load(spark, d, "events")
    return window_components(ev, "session", "user_id", "ts", "7200 seconds 1 microsecond").select("user_id", "component", "n")


def _windows(kind: str, slide: str | None):
    def run(spark, d):
        from ccspark.streaming.windows import window_components

        return window_components(load(spark, d, "events"), kind, "user_id", "ts", "1 hour", slide).select("user_id", F.col("w.start").alias("start"), "component", "n")

    return run


_query("stream_windows_tumbling", "SELECT user_id, time_bucket(INTERVAL 1 HOUR, ts) AS start, min(event_id) AS component, count(*)::BIGINT AS n FROM events GROUP BY ALL")(_windows("tumbling", None))
_query("stream_windows_sliding", "SELECT user_id, time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE AS start, min(event_id) AS component, count(*)::BIGINT AS n FROM events, range(2) AS r(k) GROUP BY ALL")(_windows("sliding", "30 minutes"))


def queries() -> dict[str, Callable[..., DataFrame]]:
    return dict(_Q)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)
