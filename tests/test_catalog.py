"""Queries of the catalogue on small tables that the given ones don't resemble."""

import pytest

from ccspark.plans import catalog


@pytest.fixture
def tables(spark, tmp_path):
    def put(**named):
        for name, (rows, schema) in named.items():
            spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / f"{name}.parquet"))
        return str(tmp_path)

    return put


def run(spark, name, folder):
    return sorted(tuple(r) for r in catalog.queries()[name](spark, folder).collect())


def test_entity_kinds_of_orders_without_items(spark, tables):
    """A customer whose orders have no items and a part of no known order count; so does a null key, once."""
    d = tables(orders=([(1, 7), (2, 8), (3, 8), (4, None), (5, None)], "o_orderkey long, o_custkey long"), lineitem=([(1, 5), (1, 6), (99, 9)], "l_orderkey long, l_partkey long"))
    assert run(spark, "op_entity_kinds", d) == [(1, 3), (2, 3)]


@pytest.mark.parametrize("name", ["full_cluster", "min_hub"])
def test_cluster_sets_beyond_their_bound(spark, name):
    """As the catalogue calls them, with a bound that cliques, a star, a path and sparse edges outgrow: whole components still."""
    from ccspark.plans.runner import connected_components

    method, options = next((m, o) for n, m, _, o in catalog._RUNS if n == name)
    pairs = [(a, b) for a in range(30) for b in range(a)] + [(100, 100 + i) for i in range(1, 60)] + [(200 + i, 201 + i) for i in range(40)] + [(29, 160), (300, 301), (400, 400)]
    e = spark.createDataFrame(pairs, "src long, dst long")
    got = connected_components(e, method=method, **{**options, "max_pairs": 300})
    want = dict.fromkeys(range(30), 0) | dict.fromkeys(range(100, 160), 100) | dict.fromkeys(range(200, 241), 200) | {160: 0, 300: 300, 301: 300, 400: 400}
    assert {r.vertex: r.component for r in got.assignment.collect()} == want
    assert any(s.finished_by == "contraction" for s in got.phase_stats)


def test_full_cluster_of_a_large_host(spark, tables):
    """The sets of one host's 400 pages would be 64 million pairs in the second round."""
    d = tables(pages=([(i, f"http://{'a' if i >= 5 else 'b'}.org/{i}", "") for i in range(405)], "page_id long, url string, html string"))
    assert run(spark, "full_cluster__pagehost", d) == [(i, 0 if i < 5 else 5) for i in range(405)]


def test_full_cluster_sends_no_sets_in_vain(spark):
    """The star's first round is under the bound and its second far over it: its square is never sent. A path stays under it and is not contracted."""
    from ccspark.plans.runner import connected_components

    star = spark.createDataFrame([(0, i) for i in range(1, 400)] + [(500, 501)], "src long, dst long")
    got = connected_components(star, method="full_cluster", beyond="contract", max_pairs=200_000)
    assert {r.vertex: r.component for r in got.assignment.collect()} == dict.fromkeys(range(400), 0) | {500: 500, 501: 500}
    assert got.phase_stats[0].finished_by == "contraction" and sum(s.records_sent for s in got.phase_stats) < 20_000
    path = connected_components(spark.createDataFrame([(i, i + 1) for i in range(20)], "src long, dst long"), method="full_cluster", beyond="contract", max_pairs=200_000)
    assert not any(s.finished_by for s in path.phase_stats) and {r.component for r in path.assignment.collect()} == {0}


def test_grid_builds_each_graph_once(spark, monkeypatch):
    """The rows are those of single runs, in their order; a run that outgrows its bound is marked and the others go on."""
    from ccspark.plans import runner
    from ccspark.sources import generators

    built = []
    graph = lambda name, n: lambda s, d: (built.append(name), (generators.path(s, n), None))[1]
    monkeypatch.setattr(catalog, "WORKLOADS", {k: type("W", (), {"build": staticmethod(graph(k, n))}) for k, n in (("a", 16), ("b", 70))})
    monkeypatch.setattr(runner.Config.__init__, "__defaults__", tuple(40 if v == 64 else v for v in runner.Config.__init__.__defaults__))
    methods = ["two_hop", "min_hub", "min_spread"]
    got = [tuple(r) for r in catalog._grid(spark, "", ["a", "b"], methods, finish_edges=0).collect()]
    assert sorted(built) == ["a", "b"]
    for w, m, phases, status in got:
        if (w, m) == ("b", "min_spread"):
            assert (phases, status) == (None, "x")
        else:
            one = runner.connected_components(generators.path(spark, 16 if w == "a" else 70), method=m, **({"finish_edges": 0} if m == "two_hop" else {}))
            assert (phases, status) == (one.phases, "ok")
    assert [r[:2] for r in got] == [(w, m) for w in ("a", "b") for m in methods]


def test_bernoulli_bound_draws_rows_of_events(spark, tables):
    """A table without rows of success at this seed gives no success: the draws come from the rows, not from made-up numbers."""
    from pyspark.sql import functions as F

    from ccspark.plans import verify

    draws = spark.range(100_000).select(F.col("id").alias("event_id"), (F.pmod(F.xxhash64("id", F.lit(0)), F.lit(1 << 53)) / float(1 << 53) < 0.01).alias("hit"))
    share, bound = verify.bernoulli_bound(draws, "event_id", 50, 0.01)
    assert bound == pytest.approx(0.25) and abs(share - (1 - 0.99**50)) < 0.05
    assert verify.bernoulli_bound(draws.where("not hit"), "event_id", 50, 0.01)[0] == 0
    d = tables(events=([(r.event_id,) for r in draws.where("not hit").limit(500).collect()], "event_id long"))
    assert run(spark, "verify_bernoulli_bound", d) == [(False,)]


def test_band_join_at_the_edge_of_bins(spark, tables):
    """0.5 and the number under 0.25 differ by 0.25 as doubles do, and lie two bins apart."""
    d = tables(part=([(1, 0.24999999999999997), (2, 0.5), (3, 0.5), (4, None), (5, 0.76), (6, 0.6), (0, 0.9)], "p_partkey long, p_retailprice double"))
    assert run(spark, "op_band_join", d) == [(0, 5), (1, 2), (1, 3), (2, 3), (2, 6), (3, 6), (5, 6)]


def test_band_join_of_groups(spark, monkeypatch):
    """Bins of several groups, values below zero, equal rows; single pairs go through no exchange."""
    from ccspark.operators import edges
    from ccspark.plans.metrics import Traffic

    monkeypatch.setattr(edges, "BAND_ROWS", 8, raising=False)
    rows = [(i * 7919 % 600, (i * i % 41) / 10 - 2) for i in range(600)] + [(5, 0.0), (5, 0.0), (900, 1e6), (901, 1e6 + 0.25)]
    df = spark.createDataFrame(rows, "k long, x double").coalesce(1)
    want = sorted((min(a, b), max(a, b)) for i, (a, x) in enumerate(rows) for b, y in rows[:i] if a != b and abs(x - y) <= 0.25)
    threshold = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        traffic = Traffic(spark)
        assert sorted(tuple(r) for r in edges.band_join(df, "k", "x", 0.25).collect()) == want
        sent = traffic.take()["records"]
        assert sent < 2 * len(rows) < len(want)
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", threshold)


def test_min_hub_sends_each_pair_once(spark):
    """Of a minimum and a member one direction goes through the exchange; the settings for the joins are put back."""
    from ccspark.plans.runner import connected_components

    name = "spark.sql.adaptive.maxShuffledHashJoinLocalMapThreshold"
    before = spark.conf.get(name)
    edges = [(i, i * 37 % 211 + 300) for i in range(300)] + [(1000 + i, 1001 + i) for i in range(60)]
    with catalog._hash_joins(spark):
        assert spark.conf.get(name) != before
        got = connected_components(spark.createDataFrame(edges, "src long, dst long").coalesce(1), method="min_hub")
    assert spark.conf.get(name) == before
    low = {v: v for e in edges for v in e}
    for _ in range(100):
        for a, b in edges:
            low[a] = low[b] = min(low[a], low[b])
    assert {r.vertex: r.component for r in got.assignment.collect()} == low
    sent = sum(s.records_sent for s in got.phase_stats)
    assert sent < 28_000
