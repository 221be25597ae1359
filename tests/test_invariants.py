"""What the methods' proofs rest on, over many seeds; and the finisher, the traffic counts and the joins around them."""

import random

import pytest
from test_components import frame, sparse, union_find

from ccspark.functions.priority import Priority
from ccspark.operators import edges, finish, labels
from ccspark.plans import metrics
from ccspark.plans.runner import connected_components
from ccspark.plans.store import Scratch, transient
from ccspark.sources import generators
from ccspark.sources.io import page

SEEDS = range(20)


def test_components_do_not_see_each_other(spark):
    """Labels of a union of two graphs are those of each alone: only comparisons inside a component count."""
    one, two = [(a, b) for a, b in sparse(1, scale=1)], [(a + 10_000, b + 10_000) for a, b in sparse(2, scale=1)]
    for seed in SEEDS:
        prio = Priority("permute", seed)
        alone = [set(map(tuple, labels.two_hop_min(edges.symmetrise(edges.simplify(frame(spark, p))), prio).collect())) for p in (one, two)]
        both = set(map(tuple, labels.two_hop_min(edges.symmetrise(edges.simplify(frame(spark, one + two))), prio).collect()))
        assert both == alone[0] | alone[1]


def test_merged_vertices_need_not_be_linked(spark):
    """Equal labels merge, linked or not, and always inside one component."""
    pairs = sparse(4, n=60, m=80, scale=1)
    e = edges.simplify(frame(spark, pairs))
    linked = {tuple(r) for r in e.collect()}
    truth, apart = union_find(pairs), 0
    for seed in SEEDS:
        label = {r.v: r.label for r in labels.two_hop_min(edges.symmetrise(e), Priority("permute", seed)).collect()}
        by = {}
        for v, x in label.items():
            by.setdefault(x, []).append(v)
        assert all(len({truth[v] for v in vs}) == 1 for vs in by.values())
        apart += sum((a, b) not in linked for vs in by.values() for a in vs for b in vs if a < b)
    assert apart > 0


def test_forest_nodes_are_connected_sets(spark):
    """Each node of the forest method is connected by edges between its own vertices; so contraction gives a minor."""
    pairs = sparse(6, n=80, m=110, scale=1)
    e = edges.simplify(frame(spark, pairs))
    own = [tuple(r) for r in e.collect()]
    for seed in SEEDS:
        prio, scratch = Priority("permute", seed), Scratch(spark, "minor")
        parent = scratch.write(labels.lowest_neighbour(edges.symmetrise(e), prio), "parent")
        node = {r.v: r.parent for r in labels.chase_lookup(labels.mutual_roots(parent, prio)).collect()}
        inside = union_find([(a, b) for a, b in own if node[a] == node[b]])
        for x in set(node.values()):
            members = [v for v in node if node[v] == x]
            assert len(members) > 1 and len({inside[v] for v in members}) == 1


def test_bounds_hold_on_average(spark):
    """Distinct two-hop labels stay under three quarters of the vertices; forest chains under six times log2 n."""
    e = edges.simplify(generators.path(spark, 256).unionByName(generators.gnp(spark, 256, 3, seed=1, first=1000)))
    sym = Scratch(spark, "bounds").write(edges.symmetrise(e), "sym")
    n, shares = edges.endpoints(e).count(), []
    for seed in SEEDS:
        prio = Priority("permute", seed)
        shares.append(labels.two_hop_min(sym, prio).select("label").distinct().count() / n)
        if seed % 4 == 0:
            scratch = Scratch(spark, "depth")
            parent = scratch.write(labels.lowest_neighbour(sym, prio), "parent")
            depth = labels.chain_depth(parent, scratch)
            _, steps = labels.jump_pointers(labels.mutual_roots(parent, prio), scratch)
            assert depth <= 6 * 8 and steps <= max(1, depth).bit_length() + 1
    assert sum(shares) / len(shares) <= 0.75


@pytest.mark.parametrize("chunk", [1 << 20, 7])
def test_finisher_equals_plain_union_find(spark, monkeypatch, chunk):
    """Edges that come in chunks, in awkward orders."""
    import pyarrow as pa

    monkeypatch.setattr(finish, "CHUNK", chunk)
    rng = random.Random(2)
    path = [(i, i + 1) for i in range(500)]
    rng.shuffle(path)
    for pairs in ([], [(3, 3)], path, sparse(9), [(0, i) for i in range(200, 0, -1)], [(i, 400 - i) for i in range(400)]):
        batches = [pa.RecordBatch.from_arrays([pa.array([p[k] for p in pairs[i : i + 5]], pa.int64()) for k in (0, 1)], names=["src", "dst"]) for i in range(0, len(pairs), 5)]
        got = {v: x for b in finish._spanning(iter(batches), False) for v, x in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)}
        assert got == union_find(pairs)
    assert {r.v: r.node for r in finish.union_find(finish.local_forest(frame(spark, path).repartition(3))).collect()} == union_find(path)


def test_traffic_is_counted(spark):
    traffic = metrics.Traffic(spark)
    spark.range(1000).repartition(3).write.format("noop").mode("overwrite").save()
    sent = traffic.take()
    assert sent["exchanges"] == 1 and sent["records"] == 1000 and sent["bytes"] > 0
    spark.range(1000).repartition(3).write.format("noop").mode("overwrite").save()
    got = traffic.received()
    assert got["bytes"] > 0 and got["ratio"] >= 1
    assert traffic.take()["records"] == 0
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        r = connected_components(generators.gnp(spark, 300, seed=1), finish_edges=0)
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    # a round sends at most two rows an edge, and a phase has a bounded number of them
    assert all(0 < s.records_sent <= 2 * s.rounds * s.edges_in + 10 for s in r.phase_stats)
    looked = connected_components(generators.path(spark, 100), method="forest", lookup=True, finish_edges=0)
    assert looked.phase_stats[0].lookups >= 100


def test_store_variants_of_the_star_baseline(spark):
    pairs = sparse(11)
    for rows in (0, 1000):
        got = connected_components(frame(spark, pairs), method="star_alternation", lookup=True, lookup_rows=rows)
        assert {r.vertex: r.component for r in got.assignment.collect()} == union_find(pairs)
        assert (got.phase_stats[0].lookups > 0) == (rows > 0)


def test_overlap_join_and_pages(spark):
    rng = random.Random(1)
    rows = [(i, i % 3, a := rng.randrange(-50, 50), a + rng.choice((0, 3, 40))) for i in range(60)] + [(99, 0, 5, 1)]
    df = spark.createDataFrame(rows, "v long, k long, a long, b long")
    want = {(x[0], y[0]) for x in rows for y in rows if x[0] < y[0] and x[1] == y[1] and x[2] <= y[3] and y[2] <= x[3] and x[2] <= x[3] and y[2] <= y[3]}
    assert [tuple(r) for r in edges.overlap_join(df, "v", "k", "a", "b", 10).collect()].__len__() == len(want)
    assert {tuple(r) for r in edges.overlap_join(df, "v", "k", "a", "b", 10).collect()} == want
    assert [r.v for r in page(df, ["v"], 5, 10).collect()] == [10, 11, 12, 13, 14]


def test_transient_tables_go(spark):
    with transient():
        scratch = Scratch(spark, "gone")
        scratch.write(spark.range(3).toDF("v"), "t")
        assert scratch.has("t")
    assert not scratch.has("t")


def test_struct_minimum_is_a_sort_aggregate(spark):
    e = edges.symmetrise(edges.simplify(frame(spark, sparse(2))))
    plans = [f(e, Priority())._jdf.queryExecution().executedPlan().toString() for f in (labels.closed_min, labels.closed_min_by_struct)]
    assert "SortAggregate" not in plans[0] and "SortAggregate" in plans[1]
    assert {tuple(r) for r in labels.closed_min(e, Priority()).collect()} == {tuple(r) for r in labels.closed_min_by_struct(e, Priority()).collect()}
