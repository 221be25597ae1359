"""Edge frames: ``src long, dst long``; canonical means src < dst, distinct, no loops."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Rows of a group of :func:`band_join`; the square of it are the pairs that a task may hold at once.
BAND_ROWS = 256


def require_schema(df: DataFrame, columns: Sequence[str] = ("src", "dst")) -> DataFrame:
    """The named columns as longs; any other column is left behind. Raises if one is missing."""
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"edge frame lacks {missing}; it has {df.columns}")
    return df.select(*[F.col(c).cast("long").alias(c) for c in columns])


def canonical(df: DataFrame) -> DataFrame:
    """Lower end first; loops and rows with a null end go."""
    e = require_schema(df)
    return e.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).where("src < dst").where(F.col("src").isNotNull())


def simplify(df: DataFrame) -> DataFrame:
    """Canonical pairs without duplicates."""
    e = require_schema(df).where("src is not null and dst is not null")
    return canonical(e).dropDuplicates(["src", "dst"])


def symmetrise(df: DataFrame) -> DataFrame:
    """Both directions of each pair from one scan (weak reading of a directed graph)."""
    both = F.explode(F.array(F.struct(F.col("src"), F.col("dst")), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst"))))
    return df.select(both.alias("e")).select("e.src", "e.dst")


def endpoints(df: DataFrame) -> DataFrame:
    return df.select(F.explode(F.array("src", "dst")).alias("v")).distinct()


def where(df: DataFrame, condition: Column | str) -> DataFrame:
    return df.where(condition)


def degrees(df: DataFrame) -> DataFrame:
    """Degree of each endpoint of canonical edges."""
    return df.select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("degree"))


def min_degree(df: DataFrame, k: int) -> DataFrame:
    """Edges both of whose ends have at least k neighbours."""
    keep = degrees(df).where(F.col("degree") >= k).select("v")
    return induced(df, keep)


def induced(df: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges with both ends among the given vertices (column ``v``)."""
    return df.join(vertices.select(F.col("v").alias("src")), "src", "left_semi").join(vertices.select(F.col("v").alias("dst")), "dst", "left_semi").select("src", "dst")


def union_all(*frames: DataFrame) -> DataFrame:
    out = frames[0].select("src", "dst")
    for f in frames[1:]:
        out = out.unionByName(f.select("src", "dst"))
    return out


def common(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("src", "dst").intersect(b.select("src", "dst"))


def minus(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("src", "dst").exceptAll(b.select("src", "dst"))


def star(rows: DataFrame, key: str, vertex: str) -> DataFrame:
    """Each vertex linked to the lowest vertex with the same key: linear in the rows, never all pairs.

    The minimum per key is aggregated before it meets the rows, so a key that holds a third of the
    rows is one row on the aggregated side and AQE may split the other.
    """
    r = rows.select(F.col(key).alias("k"), F.col(vertex).cast("long").alias("v")).where("k is not null and v is not null")
    low = r.groupBy("k").agg(F.min("v").alias("low"))
    return simplify(r.join(low, "k").select(F.col("low").alias("src"), F.col("v").alias("dst")))


def band_join(df: DataFrame, key: str, value: str, width: float) -> DataFrame:
    """Pairs of rows whose values lie within ``width``. Bins of that width are cut into groups of rows in the order of the value;
    groups that may hold a pair meet, are dealt out evenly, and each pair of them makes its pairs of rows in one loop, so that
    neither a join nor a sort handles single pairs. All pairs of rows come out, which grow with the square of a bin's rows."""
    rows = df.select(F.col(key).cast("long").alias("k"), F.col(value).cast("double").alias("x")).where("k is not null and x is not null")
    place = F.row_number().over(Window.partitionBy("bin").orderBy("x", "k"))
    placed = rows.withColumn("bin", F.floor(F.col("x") / width)).withColumn("part", F.floor((place - 1) / BAND_ROWS))
    groups = placed.groupBy("bin", "part").agg(F.min("x").alias("low"), F.max("x").alias("high"), F.collect_list(F.struct("x", "k")).alias("rows"))
    # two bins on, as the difference is rounded too
    reach = groups.select(F.col("bin").alias("home"), F.col("part").alias("nth"), F.col("high").alias("top"), F.col("rows").alias("lower"), F.explode(F.sequence(F.col("bin"), F.col("bin") + 2)).alias("bin"))
    apart = (F.col("home") < F.col("bin")) | (F.col("nth") < F.col("part"))
    near = reach.join(groups, "bin").where((apart | (F.col("nth") == F.col("part"))) & (F.col("low") - F.col("top") <= width))
    dealt = near.select("lower", "rows", apart.alias("apart"), "home", "nth", "bin", "part").repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), "home", "nth", "bin", "part")
    low = dealt.select("rows", "apart", F.inline("lower").alias("x", "a"))
    met = low.select("x", "a", "apart", F.inline("rows").alias("y", "b")).where((F.abs(F.col("x") - F.col("y")) <= width) & ((F.col("a") < F.col("b")) | (F.col("apart") & (F.col("a") > F.col("b")))))
    return met.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"))


def gap_links(df: DataFrame, key: str, order: str, vertex: str, max_gap_s: float | None = None) -> DataFrame:
    """Successive rows of one key in the order of a time column (ties by vertex), gap at most ``max_gap_s``."""
    w = Window.partitionBy(key).orderBy(order, vertex)
    t = F.unix_micros(F.col(order).cast("timestamp"))
    out = df.withColumn("_t", t).select(F.col(vertex).cast("long").alias("src"), F.lead(F.col(vertex).cast("long")).over(w).alias("dst"), (F.lead("_t").over(w) - F.col("_t")).alias("gap"))
    out = out.where("dst is not null")
    if max_gap_s is not None:
        out = out.where(F.col("gap") <= int(max_gap_s * 1_000_000))
    return out.select("src", "dst")


def gap_seconds(later: Column, earlier: Column) -> Column:
    return (F.unix_micros(later.cast("timestamp")) - F.unix_micros(earlier.cast("timestamp"))) / 1_000_000


def asof_link(left: DataFrame, right: DataFrame, by: str, ts: str, left_id: str, right_id: str) -> DataFrame:
    """Each left row linked to the latest right row of the same key at or before it: one union, one window."""
    a = left.select(F.col(by).alias("k"), F.col(ts).alias("t"), F.lit(1).alias("side"), F.col(left_id).cast("long").alias("l"), F.lit(None).cast("long").alias("r"))
    b = right.select(F.col(by).alias("k"), F.col(ts).alias("t"), F.lit(0).alias("side"), F.lit(None).cast("long").alias("l"), F.col(right_id).cast("long").alias("r"))
    w = Window.partitionBy("k").orderBy("t", "side", "r").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn("r", F.last("r", ignorenulls=True).over(w)).where("side = 1 and r is not null").select(F.col("l").alias("src"), F.col("r").alias("dst"))


def overlap_join(df: DataFrame, vertex: str, key: str, start: str, end: str, width: int) -> DataFrame:
    """Pairs of rows of one key whose closed intervals (longs) overlap: bins of ``width``, met in the first bin that both have."""
    rows = df.select(F.col(vertex).cast("long").alias("v"), F.col(key).alias("k"), F.col(start).cast("long").alias("lo"), F.col(end).cast("long").alias("hi")).where("lo <= hi")
    bin_ = lambda c: F.floor(F.col(c) / width).cast("long")
    binned = rows.select("*", F.explode(F.sequence(bin_("lo"), bin_("hi"))).alias("bin"))
    a, b = (binned.select("k", "bin", *[F.col(c).alias(f"{c}_{x}") for c in ("v", "lo", "hi")]) for x in ("a", "b"))
    first = F.col("bin") == F.floor(F.greatest("lo_a", "lo_b") / width)
    return a.join(b, ["k", "bin"]).where((F.col("v_a") < F.col("v_b")) & (F.col("lo_a") <= F.col("hi_b")) & (F.col("lo_b") <= F.col("hi_a")) & first).select(F.col("v_a").alias("src"), F.col("v_b").alias("dst"))
