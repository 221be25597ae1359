"""Relabelling, composition of phase maps and canonical names."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def relabel_edges(edges: DataFrame, label: DataFrame, strategy: str | None = None, salt: int = 0) -> DataFrame:
    """Canonical edges between the nodes of a map ``v, node``; loops and duplicates go.

    ``strategy``: a join hint (``merge``, ``shuffle_hash``, ``broadcast``) or None for Catalyst's choice.
    ``salt`` > 1 deals the edges of each vertex to so many parts and copies the label to each: for a
    hub where AQE's split of skewed partitions isn't at hand.
    """
    a, b = (label.select(F.col("v").alias(end), F.col("node").alias(f"{end}_node")) for end in ("src", "dst"))
    if strategy:
        a, b = a.hint(strategy), b.hint(strategy)
    on = lambda end: [end, "part"] if salt > 1 else [end]
    if salt > 1:
        parts = F.explode(F.array(*[F.lit(i) for i in range(salt)])).alias("part")
        a, b = a.select("*", parts), b.select("*", parts)
        edges = edges.withColumn("part", F.pmod(F.xxhash64("src", "dst"), F.lit(salt)).cast("int"))
    out = edges.join(a, on("src")).join(b, on("dst"))
    return (
        out.select(F.least("src_node", "dst_node").alias("src"), F.greatest("src_node", "dst_node").alias("dst"))
        .where("src < dst")
        .dropDuplicates(["src", "dst"])
    )


def split_isolated(nodes: DataFrame, edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Nodes (column ``v``) that edges still touch, and those that none does: their component is whole."""
    ends = edges.select(F.explode(F.array("src", "dst")).alias("v"))
    return nodes.join(ends, "v", "left_semi"), nodes.join(ends, "v", "left_anti")


def compose_back(maps: list[DataFrame]) -> DataFrame:
    """Vertices of the first map with the node they end in; a node that a later map lacks stays."""
    out = maps[-1]
    for earlier in reversed(maps[:-1]):
        later = out.select(F.col("v").alias("node"), F.col("node").alias("last"))
        out = earlier.join(later, "node", "left").select("v", F.coalesce("last", "node").alias("node"))
    return out


def canonical_min(assignment: DataFrame) -> DataFrame:
    """``vertex, component``: each component takes the name of its lowest vertex."""
    low = assignment.groupBy("node").agg(F.min("v").alias("component"))
    return assignment.join(low, "node").select(F.col("v").alias("vertex"), "component")
