"""Sources, sinks, streams, SQL surface and operators around the methods."""

from pyspark.sql import functions as F

from ccspark.operators import edges, post
from ccspark.plans import metrics, sqlsurface
from ccspark.plans.runner import connected_components
from ccspark.sources import datasource, generators, io
from ccspark.streaming.incremental import AssignmentStore, merge_batches, rate_edges, read_edges, start
from ccspark.streaming.windows import dedupe, split_late, user_state, with_lateness


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_edge_files(spark, tmp_path):
    (tmp_path / "e.csv").write_text("src,dst\n1,2\n3,x\n4,5\n")
    good, bad = io.read_edges(spark, str(tmp_path / "e.csv"))
    assert rows(good) == [(1, 2), (4, 5)] and bad.count() == 1
    (tmp_path / "e.txt").write_text("1 2\n 3\t4 \n5\n")
    good, bad = io.read_edges(spark, str(tmp_path / "e.txt"), "text")
    assert rows(good) == [(1, 2), (3, 4)] and bad.count() == 1
    (tmp_path / "e.json").write_text('{"src": 1, "dst": 2}\n{"src": "a", "dst": 2}\n')
    good, bad = io.read_edges(spark, str(tmp_path / "e.json"), "json")
    assert rows(good) == [(1, 2)] and bad.count() == 1
    (tmp_path / "a.txt").write_text("1 2 3\n4\n")
    assert rows(io.read_adjacency(spark, str(tmp_path / "a.txt"))) == [(1, 2), (1, 3)]
    for fmt in ("parquet", "orc", "csv", "json"):
        io.write(good, str(tmp_path / fmt), fmt, sort_by=["src"])
        assert spark.read.option("header", True).format(fmt).load(str(tmp_path / fmt)).count() == 1


def test_data_source(spark):
    datasource.register(spark)
    for kind, n in (("path", 9), ("star", 9), ("cycle", 10)):
        assert spark.read.format("cc_graph").option("kind", kind).option("n", 10).load().count() == n


def test_generators(spark):
    assert generators.clique(spark, 5).count() == 10
    assert generators.grid(spark, 3, 4).count() == 17
    assert connected_components(generators.gnp_blocks(spark, [50, 60, 70])).assignment.select("component").distinct().count() == 3
    assert connected_components(generators.gnp_plus(spark, 100)).assignment.select("component").distinct().count() == 1


def test_star_links_are_linear(spark):
    r = spark.createDataFrame([(1, "a"), (2, "a"), (3, "a"), (4, "b"), (None, "a"), (5, None)], "v long, k string")
    assert rows(edges.star(r, "k", "v")) == [(1, 2), (1, 3)]


def test_asof_and_gaps(spark):
    a = spark.createDataFrame([(1, 1, 10), (2, 1, 20), (3, 2, 5)], "id long, k long, t long")
    b = spark.createDataFrame([(11, 1, 10), (12, 1, 15), (13, 2, 9)], "id long, k long, t long")
    assert rows(edges.asof_link(a, b, "k", "t", "id", "id")) == [(1, 11), (2, 12)]
    e = spark.sql("SELECT * FROM VALUES (1, 7, TIMESTAMP'2020-01-01 00:00:00'), (2, 7, TIMESTAMP'2020-01-01 01:00:00'), (3, 7, TIMESTAMP'2020-01-01 04:00:00') AS t(event_id, user_id, ts)")
    assert rows(edges.gap_links(e, "user_id", "ts", "event_id", 7200)) == [(1, 2)]


def test_levels_nest(spark):
    e = spark.createDataFrame([(1, 2, 0.9), (2, 3, 0.7), (4, 5, 0.8), (3, 4, 0.5)], "src long, dst long, w double")
    got = rows(post.levels(e, "w", [0.5, 0.75, 0.85]).select("level", "vertex", "component"))
    assert [(v, c) for i, v, c in got if i == 0] == [(1, 1), (2, 1)]
    assert [(v, c) for i, v, c in got if i == 1] == [(1, 1), (2, 1), (4, 4), (5, 4)]
    assert [(v, c) for i, v, c in got if i == 2] == [(v, 1) for v in range(1, 6)]


def test_sql_surface(spark):
    e = spark.createDataFrame([(1, 1, 2), (1, 3, 4), (2, 1, 2), (2, 2, 3)], "k long, src long, dst long")
    assert rows(sqlsurface.local_components(e, "k")) == [(1, 1, 1), (1, 2, 1), (1, 3, 3), (1, 4, 3), (2, 1, 1), (2, 2, 1), (2, 3, 1)]
    e.createOrReplaceTempView("e")
    assert rows(spark.sql("SELECT k, component_count(src, dst) FROM e GROUP BY k")) == [(1, 2), (2, 1)]
    assert rows(post.per_block(e, "k")) == rows(sqlsurface.local_components(e, "k"))
    assert {r.component for r in sqlsurface.spread_sql(generators.path(spark, 6), 6).collect()} == {0}
    sqlsurface.register(connected_components(e, finish_edges=0), "r")
    assert spark.table("r_stats").count() >= 1 and spark.table("r_assignment").count() == 4


def test_stream_in_any_split(spark, tmp_path):
    pairs = [(1, 2), (3, 4), (2, 3), (10, 11), (11, 12), (4, 1)]
    for k in (1, 3):
        folder = str(tmp_path / f"s{k}")
        for i in range(k):
            spark.createDataFrame(pairs[i::k], "src long, dst long").coalesce(1).write.mode("append").parquet(folder)
        store = AssignmentStore(spark)
        merge_batches(read_edges(spark, folder), store, str(tmp_path / f"c{k}")).awaitTermination()
        assert rows(store.current) == [(1, 1), (2, 1), (3, 1), (4, 1), (10, 10), (11, 10), (12, 10)]
        before = store.version
        store.merge(spark.createDataFrame([(1, 10)], "src long, dst long"), 0)
        assert store.version == before


def test_stream_state_and_duplicates(spark, tmp_path):
    src = str(tmp_path / "ev")
    spark.sql("SELECT * FROM VALUES (1L, 7L, TIMESTAMP'2020-01-01 00:00:00'), (2L, 7L, TIMESTAMP'2020-01-01 01:00:00'), (2L, 7L, TIMESTAMP'2020-01-01 01:00:00'), (3L, 7L, TIMESTAMP'2020-01-01 09:00:00') AS t(event_id, user_id, ts)").coalesce(1).write.parquet(src)
    stream = lambda: with_lateness(spark.readStream.schema("event_id long, user_id long, ts timestamp").parquet(src), "ts", "1 day")
    start(dedupe(stream(), ["event_id", "ts"]), "once").awaitTermination()
    assert spark.table("once").count() == 3
    start(user_state(stream()), "state", "update").awaitTermination()
    assert rows(spark.table("state")) == [(7, 1, 3), (7, 3, 1)]
    on_time, late = split_late(spark.read.parquet(src), "ts", F.lit("2020-01-01 00:30:00").cast("timestamp"))
    assert (on_time.count(), late.count()) == (3, 1)
    assert rate_edges(spark, 5, 10).isStreaming


def test_relative_times(spark):
    runs = spark.createDataFrame([("g", "a", 2.0), ("g", "a", 4.0), ("g", "a", 3.0), ("g", "b", 6.0)], "graph string, method string, seconds double")
    assert rows(metrics.relative_times(runs)) == [("g", "a", 3.0, 1.0), ("g", "b", 6.0, 2.0)]
