"""Every method against a plain union-find, on ordinary and awkward graphs."""

import random

import pytest

from ccspark.functions.priority import Priority, permute64, unpermute64
from ccspark.operators import absorb, contract, edges, labels
from ccspark.plans import metrics, verify
from ccspark.plans.runner import TooLarge, connected_components
from ccspark.plans.store import Scratch
from ccspark.sources import generators


def union_find(pairs):
    up = {}

    def root(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in pairs:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    return {v: root(v) for v in list(up)}


def frame(spark, pairs):
    return spark.createDataFrame(pairs, "src long, dst long")


def solve(spark, pairs, **options):
    return {r.vertex: r.component for r in connected_components(frame(spark, pairs), **options).assignment.collect()}


def sparse(seed, n=150, m=110, scale=10**14):
    rng = random.Random(seed)
    return [((rng.randrange(n) - n // 2) * scale, (rng.randrange(n) - n // 2) * scale) for _ in range(m)]


OPTIONS = [
    {"method": "two_hop", "finish_edges": 0},
    {"method": "two_hop"},
    {"method": "two_hop", "finish_edges": 0, "drop_isolated": False},
    {"method": "two_hop", "finish_edges": 0, "salt": 3, "preforest": True},
    {"method": "two_hop", "finish_edges": 0, "lazy": 0.25},
    {"method": "two_hop", "finish_edges": 0, "absorb": absorb.Schedule.mean_degree()},
    {"method": "two_hop", "finish_edges": 0, "absorb": absorb.Schedule.explicit([3]), "large_moves": True},
    {"method": "forest", "finish_edges": 0},
    {"method": "forest", "finish_edges": 0, "lookup": True},
    {"method": "forest", "finish_edges": 0, "reseed": False},
    {"method": "rewire_merge", "finish_edges": 0},
    {"method": "star_alternation"},
    {"method": "star_alternation", "lookup": True},
    {"method": "min_hub"},
    {"method": "min_spread"},
    {"method": "full_cluster"},
    {"method": "single_task"},
]


@pytest.mark.parametrize("options", OPTIONS, ids=lambda o: "-".join(f"{k}={v}" for k, v in o.items())[:60])
def test_methods_agree(spark, options):
    pairs = sparse(1)
    assert solve(spark, pairs, **options) == union_find(pairs)


@pytest.mark.parametrize("method", ["two_hop", "forest", "rewire_merge", "star_alternation"])
@pytest.mark.parametrize("pairs", [[], [(1, 2)], [(5, 5)], [(1, 2), (2, 1), (1, 2)], [(0, i) for i in range(1, 300)], [(i, (i + 1) % 16) for i in range(16)], [(2**62, -(2**62)), (-(2**62), 7)]], ids=["empty", "one", "loop", "repeated", "star", "cycle", "wide"])
def test_awkward_graphs(spark, method, pairs):
    options = {} if method == "star_alternation" else {"finish_edges": 0}
    assert solve(spark, pairs, method=method, **options) == union_find(pairs)


def test_null_ends_and_lone_vertices(spark):
    e = frame(spark, [(1, 2), (None, 3), (4, None)])
    v = spark.createDataFrame([(1,), (9,), (None,)], "v long")
    got = {r.vertex: r.component for r in connected_components(e, vertices=v).assignment.collect()}
    assert got == {1: 1, 2: 1, 9: 9}


def test_one_cycle_against_two(spark):
    for parts in (1, 2):
        got = connected_components(generators.cycles(spark, 64, parts), finish_edges=0).assignment
        assert got.select("component").distinct().count() == parts


def test_priorities_are_bijections(spark):
    rows = spark.range(-500, 500).selectExpr("id * 9007199254740993 as v")
    got = rows.select("v", permute64(rows["v"], 3, 4).alias("p"), unpermute64(permute64(rows["v"], 3, 4), 3, 4).alias("b")).collect()
    assert len({r.p for r in got}) == 1000 and all(r.v == r.b for r in got)
    a = Priority("affine", 12345)
    small = spark.range(2_147_483_000, 2_147_483_600)
    assert all(r.id == r.b for r in small.select("id", a.owner(a.of(small["id"])).alias("b")).collect())


def test_label_identity_and_shrink(spark):
    e = edges.simplify(frame(spark, sparse(3)))
    assert verify.rewire_label_identity(e, 1)
    path = generators.path(spark, 400)
    assert sum(verify.shrink_share(path, s) for s in range(5)) / 5 <= 0.75
    assert verify.shrink_share(path, 1, "forest") <= 0.75
    assert sum(verify.half_rule(path, s) for s in range(4)) / 4 >= 0.5


def test_forest_halves_nodes(spark):
    r = connected_components(generators.path(spark, 600), method="forest", finish_edges=0)
    nodes = [s.nodes_in for s in r.phase_stats]
    assert all(b <= a / 2 for a, b in zip(nodes, nodes[1:], strict=False))


def test_same_seed_same_costs(spark):
    e = frame(spark, sparse(5))
    runs = [connected_components(e.repartition(k), finish_edges=0, seed=4) for k in (2, 5)]
    assert [(s.nodes_in, s.edges_in) for s in runs[0].phase_stats] == [(s.nodes_in, s.edges_in) for s in runs[1].phase_stats]
    assert verify.same_partition(runs[0].assignment, runs[1].assignment)
    assert verify.edges_within(e, runs[0].assignment) == 0


def test_bounds_mark_failure(spark):
    with pytest.raises(TooLarge):
        connected_components(generators.clique(spark, 40), method="full_cluster", max_pairs=1000)
    with pytest.raises(TooLarge):
        connected_components(generators.path(spark, 30), method="min_spread", max_phases=3)


def test_chain_depth_and_large_nodes(spark):
    e = frame(spark, [(1, 2), (2, 3), (3, 4)])
    parent = labels.lowest_neighbour(edges.symmetrise(e), Priority("identity"))
    assert labels.chain_depth(parent, Scratch(spark, "t")) == 2
    lab = spark.createDataFrame([(i, i // 4) for i in range(10)], "v long, node long")
    assert {r.node for r in absorb.large_nodes(lab, 3).collect()} == {0, 1}
    assert {(r.node, r.key) for r in absorb.kth_largest(lab, Priority("identity"), 0, 3).collect()} == {(0, 1), (1, 5)}


def test_salted_relabel_equals_plain(spark):
    e = edges.simplify(frame(spark, sparse(8)))
    lab = edges.endpoints(e).selectExpr("v", "v div 3 as node")
    plain = {tuple(r) for r in contract.relabel_edges(e, lab).collect()}
    assert plain == {tuple(r) for r in contract.relabel_edges(e, lab, salt=4).collect()} == {tuple(r) for r in contract.relabel_edges(e, lab, "merge").collect()}


def test_two_hop_needs_few_exchanges(spark):
    e = Scratch(spark, "plan").write(edges.simplify(frame(spark, sparse(2))), "e")
    assert metrics.exchanges(labels.two_hop_min(edges.symmetrise(e), Priority())) <= 4


def test_bucketed_edges_keep_their_layout(spark):
    from ccspark.sources.io import put_edges

    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    table = put_edges(edges.symmetrise(edges.simplify(frame(spark, sparse(2)))), "sym_edges", 4)
    try:
        assert metrics.exchanges(labels.closed_min(table, Priority())) == 0
        assert metrics.exchanges(labels.two_hop_min(table, Priority())) == 1
    finally:
        spark.sql("DROP TABLE sym_edges")
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


@pytest.mark.parametrize("cut", [1, 2])
def test_resume_after_failure(spark, cut):
    pairs = [(i, i + 1) for i in range(300)]
    e = frame(spark, pairs)
    with pytest.raises(TooLarge):
        connected_components(e, finish_edges=0, max_phases=cut, scratch=Scratch(spark, "resumed", f"run{cut}"))
    again = connected_components(e, finish_edges=0, resume=True, scratch=Scratch(spark, "resumed", f"run{cut}"))
    assert again.phase_stats[0].phase == cut
    assert {r.component for r in again.assignment.collect()} == {0} and again.assignment.count() == 301
