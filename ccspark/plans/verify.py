"""Checks of assignments, of label maps, and of the statements about random orders and graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ccspark.functions.priority import Priority
from ccspark.operators import labels
from ccspark.operators.edges import symmetrise
from ccspark.plans.runner import rewire


def same_partition(a: DataFrame, b: DataFrame) -> bool:
    """Whether two assignments (``vertex, component``) make the same groups, whatever the names."""
    j = a.select("vertex", F.col("component").alias("x")).join(b.select("vertex", F.col("component").alias("y")), "vertex", "full")
    bad = j.where("x is null or y is null").limit(1).count()
    pairs = j.select("x", "y").distinct()
    row = pairs.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("x").alias("x"), F.count_distinct("y").alias("y")).first()
    return not bad and row["n"] == row["x"] == row["y"]


def edges_within(edges: DataFrame, assignment: DataFrame) -> int:
    """Edges whose ends lie in different components: none in a right assignment."""
    a = assignment.select(F.col("vertex").alias("src"), F.col("component").alias("x"))
    b = assignment.select(F.col("vertex").alias("dst"), F.col("component").alias("y"))
    return edges.join(a, "src", "left").join(b, "dst", "left").where("x is null or y is null or x <> y").count()


def rewire_label_identity(edges: DataFrame, seed: int = 0, phase: int = 0) -> bool:
    """One-hop minima after rewiring equal two-hop minima before it."""
    prio = Priority("permute", seed)
    two = labels.two_hop_min(symmetrise(edges), prio, phase)
    one = labels.closed_min(symmetrise(rewire(edges, prio, phase)), prio, phase).select("v", F.col("m").alias("label"))
    return not two.exceptAll(one).limit(1).count() and not one.exceptAll(two).limit(1).count()


def half_rule(edges: DataFrame, seed: int) -> float:
    """Share of vertices of the higher half of the order whose two-hop label lies in the lower half."""
    prio = Priority("permute", seed)
    got = labels.two_hop_min(symmetrise(edges), prio)
    middle = got.select(prio.of(F.col("v")).alias("p")).agg(F.percentile("p", F.lit(0.5)).alias("m")).first()["m"]
    high = got.where(prio.of(F.col("v")) >= F.lit(int(middle)))
    return high.agg(F.avg((F.col("label") < F.lit(int(middle))).cast("double"))).first()[0] or 0.0


def shrink_share(edges: DataFrame, seed: int, method: str = "two_hop") -> float:
    """Distinct labels over vertices after one phase."""
    prio = Priority("permute", seed)
    sym = symmetrise(edges)
    lab = labels.two_hop_min(sym, prio) if method == "two_hop" else labels.lowest_neighbour(sym, prio).withColumnRenamed("parent", "label")
    row = lab.agg(F.count_distinct("label").alias("k"), F.count(F.lit(1)).alias("n")).first()
    return row["k"] / max(1, row["n"])


def random_graph_events(edges: DataFrame, n: int, alpha: int, seed: int = 0) -> dict[str, float]:
    """For the n / alpha lowest vertices A of a random order and the rest B: shares of B that see A, and of A that B
    sees from; vertices in classes with alpha / 4 or more members from B; vertices within two hops of those."""
    prio = Priority("permute", seed)
    sym = symmetrise(edges).persist()
    ranked = sym.select(F.col("src").alias("v")).distinct().withColumn("p", prio.of(F.col("v")))
    cut = ranked.orderBy("p").limit(max(1, n // alpha)).agg(F.max("p")).first()[0]
    low = ranked.where(F.col("p") <= cut).select("v")
    sees_a = sym.join(low.withColumnRenamed("v", "dst"), "dst", "left_semi").select(F.col("src").alias("v")).distinct()
    b_sees = sees_a.join(low, "v", "left_anti").count()
    a_seen = sym.join(low.withColumnRenamed("v", "src"), "src", "left_semi").join(low.withColumnRenamed("v", "dst"), "dst", "left_anti").select("src").distinct().count()
    lab = labels.two_hop_min(sym, prio)
    big = lab.join(low, "v", "left_anti").groupBy("label").agg(F.count(F.lit(1)).alias("c")).where(F.col("c") >= alpha / 4)
    inside = lab.join(big, "label", "left_semi").select("v").persist()
    one = sym.join(inside.withColumnRenamed("v", "src"), "src", "left_semi").select(F.col("dst").alias("v")).union(inside).distinct()
    two = sym.join(one.withColumnRenamed("v", "src"), "src", "left_semi").select(F.col("dst").alias("v")).union(one).distinct()
    out = {"b_sees_a": b_sees / n, "a_seen": a_seen / max(1, n // alpha), "in_large": inside.count() / n, "two_hops": two.count() / n}
    sym.unpersist()
    inside.unpersist()
    return out


def bernoulli_bound(rows: DataFrame, key: str, n: int, p: float, seed: int = 0) -> tuple[float, float]:
    """Share of runs of n draws with a success, and the lower bound n p / 2 (for n p up to a half).

    Each row is a draw and n successive keys are a run; the bound of a run follows the rows that it has.
    """
    draw = F.pmod(F.xxhash64(key, F.lit(seed)), F.lit(1 << 53)) / float(1 << 53) < p
    hit = rows.select(F.floor(F.col(key) / n).alias("run"), draw.cast("int").alias("hit")).groupBy("run").agg(F.max("hit").alias("hit"), F.count(F.lit(1)).alias("c"))
    got = hit.agg(F.avg("hit").alias("share"), F.avg(F.least(F.col("c") * p, F.lit(0.5)) / 2).alias("bound")).first()
    return got["share"] or 0.0, got["bound"] or 0.0
