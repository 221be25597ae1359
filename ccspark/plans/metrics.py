"""Costs and descriptions of runs, graphs and assignments."""

from __future__ import annotations

import re
from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def decay(stats: DataFrame) -> DataFrame:
    """``method, phase, edges_in, factor``: edges at the start of a phase over those of the next."""
    w = Window.partitionBy("method").orderBy("phase")
    return stats.select("method", "phase", "edges_in", (F.col("edges_in") / F.lead("edges_in").over(w)).alias("factor"))


def shrink(stats: DataFrame) -> DataFrame:
    """``method, phase, nodes_in, ratio``: nodes of the next phase over those of this one."""
    w = Window.partitionBy("method").orderBy("phase")
    return stats.select("method", "phase", "nodes_in", (F.lead("nodes_in").over(w) / F.col("nodes_in")).alias("ratio"))


def running(stats: DataFrame) -> DataFrame:
    """Records sent and edges so far, by phase."""
    w = Window.partitionBy("method").orderBy("phase").rowsBetween(Window.unboundedPreceding, 0)
    return stats.select("method", "phase", F.sum("records_sent").over(w).alias("sent_so_far"), F.sum("edges_in").over(w).alias("edges_so_far"))


def exchanges(df: DataFrame) -> int:
    """Exchanges in the physical plan: the rounds that Spark itself would count."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return len(re.findall(r"(?<!Broadcast)Exchange (?:hash|range|Single|Round)", plan))


def component_sizes(assignment: DataFrame) -> DataFrame:
    return assignment.groupBy("component").agg(F.count(F.lit(1)).alias("size"))


def size_histogram(assignment: DataFrame) -> DataFrame:
    return component_sizes(assignment).groupBy("size").agg(F.count(F.lit(1)).alias("components"))


def size_percentiles(assignment: DataFrame, at: Sequence[float] = (0.5, 0.9, 0.99)) -> DataFrame:
    return component_sizes(assignment).agg(F.percentile_approx("size", list(at), 10_000).alias("sizes"), F.max("size").alias("largest"), F.count(F.lit(1)).alias("components"))


def top_components(assignment: DataFrame, k: int) -> DataFrame:
    return component_sizes(assignment).orderBy(F.desc("size"), "component").limit(k)


def rank_components(assignment: DataFrame, parts: int = 4) -> DataFrame:
    """Size ranks of components with equal treatment of ties, within the digit count of the size."""
    s = component_sizes(assignment).withColumn("band", F.length(F.col("size").cast("string")))
    w = Window.partitionBy("band").orderBy(F.desc("size"), "component")
    ties = Window.partitionBy("band").orderBy(F.desc("size"))
    return s.select("component", "size", "band", F.row_number().over(w).alias("row"), F.rank().over(ties).alias("rank"), F.dense_rank().over(ties).alias("dense"), F.ntile(parts).over(w).alias("tile"))


def count_nodes(assignment: DataFrame, approx: bool = False) -> DataFrame:
    f = F.approx_count_distinct if approx else F.count_distinct
    return assignment.agg(f("vertex").alias("vertices"), f("component").alias("components"))


def top_degrees(edges: DataFrame, k: int) -> DataFrame:
    from ccspark.operators.edges import degrees

    return degrees(edges).orderBy(F.desc("degree"), "v").limit(k)


def by_attributes(assignment: DataFrame, rows: DataFrame, vertex: str, columns: Sequence[str], how: str = "rollup") -> DataFrame:
    """Vertices and components by attributes of the vertices: ``rollup``, ``cube`` or ``sets`` (each column alone)."""
    j = assignment.join(rows.select(F.col(vertex).cast("long").alias("vertex"), *columns), "vertex")
    measures = [F.count(F.lit(1)).alias("vertices"), F.count_distinct("component").alias("components")]
    if how == "sets":
        return j.groupingSets([[F.col(c)] for c in columns], *[F.col(c) for c in columns]).agg(*measures)
    return (j.rollup if how == "rollup" else j.cube)(*columns).agg(*measures)


def skew(df: DataFrame, key: str) -> DataFrame:
    """Rows of the largest key against the mean, and the number of keys."""
    per = df.groupBy(key).agg(F.count(F.lit(1)).alias("n"))
    return per.agg(F.max("n").alias("most"), F.avg("n").alias("mean"), F.count(F.lit(1)).alias("keys"), (F.max("n") / F.avg("n")).alias("ratio"))


def density(stats: DataFrame) -> DataFrame:
    """Edge frequency between the nodes of each phase."""
    n = F.col("nodes_in").cast("double")
    return stats.select("method", "phase", "nodes_in", "edges_in", (F.col("edges_in") / (n * (n - 1) / 2)).alias("density"))


def relative_times(runs: DataFrame) -> DataFrame:
    """``graph, method, median_s, relative``: median of a method's runs over the least median on the graph."""
    m = runs.groupBy("graph", "method").agg(F.percentile("seconds", F.lit(0.5)).alias("median_s"))
    return m.withColumn("relative", F.col("median_s") / F.min("median_s").over(Window.partitionBy("graph")))


class Traffic:
    """Counts what stages send through shuffles, from the status store: rows, bytes and the stages that wrote any.

    Counts all of the application's stages since it was made or last taken, so one run at a time.
    """

    def __init__(self, spark):
        self.sc, self.seen = spark.sparkContext, -1
        self.stages()

    def stages(self) -> list:
        """Stages that ended since the last call."""
        self.sc._jsc.sc().listenerBus().waitUntilEmpty(60_000)
        gateway = self.sc._gateway
        found, out = self.sc._jsc.sc().statusStore().stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList()), []
        for i in range(found.size()):
            if (stage := found.apply(i)).stageId() <= self.seen:
                break
            out.append(stage)
        self.seen = max([self.seen, *(s.stageId() for s in out)])
        return out

    def take(self) -> dict[str, int]:
        wrote = [(s.shuffleWriteRecords(), s.shuffleWriteBytes()) for s in self.stages()]
        wrote = [x for x in wrote if x[0]]
        return {"exchanges": len(wrote), "records": sum(x[0] for x in wrote), "bytes": sum(x[1] for x in wrote)}

    def received(self) -> dict[str, float]:
        """Of the stages since the last call: bytes that the busiest task read, over the mean of its stage's tasks."""
        gateway = self.sc._gateway
        at = gateway.new_array(gateway.jvm.double, 1)
        at[0] = 1.0
        worst = {"bytes": 0.0, "ratio": 1.0}
        for s in self.stages():
            if s.shuffleReadBytes() and (tasks := self.sc._jsc.sc().statusStore().taskSummary(s.stageId(), s.attemptId(), at)).isDefined():
                most = tasks.get().shuffleReadMetrics().readBytes().apply(0)
                worst = max(worst, {"bytes": most, "ratio": most * s.numTasks() / s.shuffleReadBytes()}, key=lambda x: x["bytes"])
        return worst


def density_bound(before: tuple[int, int], after: tuple[int, int], alpha: float) -> dict[str, float]:
    """Edge frequency among the nodes (``nodes, edges``) after an absorbed phase, against alpha squared over the edges before."""
    n, m = after
    return {"density": 2 * m / (n * (n - 1)) if n > 1 else 1.0, "bound": min(1.0, alpha * alpha / before[1])}
