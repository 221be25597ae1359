"""Large-node absorption: after a phase, small nodes near a large one join it."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ccspark.functions.priority import Priority
from ccspark.operators.edges import symmetrise


@dataclass(frozen=True)
class Schedule:
    """The size from which a node counts as large, phase by phase."""

    kind: str
    values: tuple[float, ...] = field(default=())

    @staticmethod
    def explicit(values) -> Schedule:
        return Schedule("explicit", tuple(values))

    @staticmethod
    def squared(first: float) -> Schedule:
        return Schedule("squared", (first,))

    @staticmethod
    def mean_degree(div: float = 4) -> Schedule:
        return Schedule("mean_degree", (div,))

    def alpha(self, phase: int, nodes: int, edges: int) -> int:
        if self.kind == "explicit":
            return max(1, int(self.values[min(phase, len(self.values) - 1)]))
        if self.kind == "squared":
            return max(1, int(min(self.values[0] ** (2**phase), nodes)))
        return max(1, int(2 * edges / max(nodes, 1) / self.values[0]))


def large_nodes(label: DataFrame, alpha: int) -> DataFrame:
    """Nodes with at least alpha members: ``node, size``."""
    return label.groupBy("node").agg(F.count(F.lit(1)).alias("size")).where(F.col("size") >= alpha)


def kth_largest(label: DataFrame, prio: Priority, phase: int, alpha: int) -> DataFrame:
    """The alpha-th largest member priority of each large node: ``node, key``.

    The rank filter plans as a group limit before the exchange, so a giant cluster sends
    at most alpha rows from each task.
    """
    ranked = label.select("node", prio.of(F.col("v"), phase).alias("key")).withColumn("r", F.row_number().over(Window.partitionBy("node").orderBy(F.desc("key"))))
    return ranked.where((F.col("r") <= alpha) & (F.col("r") == alpha)).select("node", "key")


def absorb_small(edges: DataFrame, label: DataFrame, prio: Priority, phase: int, alpha: int, large_moves: bool = False) -> DataFrame:
    """The label map after absorption; ``edges`` are canonical edges between the nodes.

    Keys of different clusters differ (they are priorities of different members), so the
    greatest key names its node by a small map.
    """
    keys = kth_largest(label, prio, phase, alpha)
    sym = symmetrise(edges)
    offer = keys.select(F.col("node").alias("src"), "key")
    one = sym.join(offer, "src").groupBy("dst").agg(F.max("key").alias("key")).select(F.col("dst").alias("node"), "key")
    seen = one.unionByName(keys).groupBy("node").agg(F.max("key").alias("key"))
    two = sym.join(seen.withColumnRenamed("node", "src"), "src").groupBy("dst").agg(F.max("key").alias("key")).select(F.col("dst").alias("node"), "key")
    best = seen.unionByName(two).groupBy("node").agg(F.max("key").alias("key"))
    if not large_moves:
        best = best.join(keys.select("node"), "node", "left_anti")
    moved = best.join(keys.select("key", F.col("node").alias("to")), "key").select("node", "to")
    return label.join(moved, "node", "left").select("v", F.coalesce("to", "node").alias("node"))
