"""Label maps of one phase over symmetric edges (``src, dst``).

All minima run over primitive longs, so that they plan as hash aggregates with partial
sums before the exchange; a hub sends at most one row from each task.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ccspark.functions.priority import Priority


def closed_min(sym: DataFrame, prio: Priority, phase: int = 0) -> DataFrame:
    """Smallest priority in the closed neighbourhood: ``v, m``."""
    best = sym.groupBy("src").agg(F.min(prio.of(F.col("dst"), phase)).alias("m"))
    return best.select(F.col("src").alias("v"), F.least(F.col("m"), prio.of(F.col("src"), phase)).alias("m"))


def closed_min_by_struct(sym: DataFrame, prio: Priority, phase: int = 0) -> DataFrame:
    """As :func:`closed_min`, by a minimum over (priority, vertex) structs, which plans as a sort aggregate: for comparison."""
    best = sym.groupBy("src").agg(F.min(F.struct(prio.of(F.col("dst"), phase).alias("p"), F.col("dst").alias("d"))).alias("m"))
    return best.select(F.col("src").alias("v"), F.least(F.col("m.p"), prio.of(F.col("src"), phase)).alias("m"))


def two_hop_min(sym: DataFrame, prio: Priority, phase: int = 0) -> DataFrame:
    """Smallest priority within two hops: ``v, label``.

    Neighbours' closed minima cover the vertex itself and its neighbours as well.
    """
    near = closed_min(sym, prio, phase).withColumnRenamed("v", "src")
    return sym.join(near, "src").groupBy("dst").agg(F.min("m").alias("label")).select(F.col("dst").alias("v"), "label")


def lowest_neighbour(sym: DataFrame, prio: Priority, phase: int = 0) -> DataFrame:
    """The neighbour (self excluded) of lowest priority: ``v, parent``; the inverse order names it without a join."""
    return sym.groupBy("src").agg(F.min(prio.of(F.col("dst"), phase)).alias("p")).select(F.col("src").alias("v"), prio.owner(F.col("p"), phase).alias("parent"))


def mutual_roots(parent: DataFrame, prio: Priority, phase: int = 0) -> DataFrame:
    """Each chain ends in a pair that points at each other; its end of lower priority becomes a root."""
    other = parent.select(F.col("v").alias("parent"), F.col("parent").alias("grand"))
    pinned = (F.col("grand") == F.col("v")) & (prio.of(F.col("v"), phase) < prio.of(F.col("parent"), phase))
    return parent.join(other, "parent").select("v", F.when(pinned, F.col("v")).otherwise(F.col("parent")).alias("parent"))


def jump_pointers(rooted: DataFrame, scratch, tag: str = "jump") -> tuple[DataFrame, int]:
    """Roots by doubling, until no pointer changes; returns the map and the number of steps."""
    cur, steps = scratch.write(rooted, f"{tag}-0"), 0
    while True:
        step = cur.alias("a").join(cur.select(F.col("v").alias("parent"), F.col("parent").alias("next")), "parent").select("v", F.col("next").alias("parent"), (F.col("next") != F.col("parent")).cast("int").alias("moved"))
        out, seen = scratch.observed(step, f"{tag}-{steps + 1}", moved=F.sum("moved"))
        scratch.drop(f"{tag}-{steps}")
        cur = out.select("v", "parent")
        if not seen["moved"]:
            return cur, steps
        steps += 1


def chase_lookup(rooted: DataFrame, max_rows: int = 2_000_000) -> DataFrame:
    """Roots by direct lookup: ``v, parent, hops`` (lookups made); the whole map is sent to each task and followed there.

    Only for maps of at most ``max_rows`` rows (16 bytes each); larger ones raise, and the caller doubles instead.
    """
    import numpy as np

    rows = rooted.limit(max_rows + 1).toArrow()
    if rows.num_rows > max_rows:
        raise ValueError(f"parent map has over {max_rows} rows; use jump_pointers")
    v, p = rows.column("v").to_numpy(), rows.column("parent").to_numpy()
    order = np.argsort(v, kind="stable")
    sent = rooted.sparkSession.sparkContext.broadcast((v[order], p[order]))

    def follow(batches):
        import pyarrow as pa

        keys, to = sent.value
        for b in batches:
            at = b.column("parent").to_numpy()
            hops = np.ones(len(at), np.int32)
            while len(at):
                nxt = to[np.searchsorted(keys, at)]
                moved = nxt != at
                if not moved.any():
                    break
                hops += moved
                at = nxt
            yield pa.RecordBatch.from_arrays([b.column("v"), pa.array(at, pa.int64()), pa.array(hops)], names=["v", "parent", "hops"])

    return rooted.select("v", "parent").mapInArrow(follow, "v long, parent long, hops int")


def chain_depth(parent: DataFrame, scratch, tag: str = "depth") -> int:
    """Longest number of steps from a vertex to the pair in which its chain ends (doubling with lengths)."""
    other = parent.select(F.col("v").alias("parent"), F.col("parent").alias("grand"))
    inpair = parent.join(other, "parent").select("v", F.when(F.col("grand") == F.col("v"), F.col("v")).otherwise(F.col("parent")).alias("parent"))
    cur = scratch.write(inpair.withColumn("d", (F.col("v") != F.col("parent")).cast("long")), f"{tag}-0")
    step = 0
    while True:
        nxt = cur.alias("a").join(cur.select(F.col("v").alias("parent"), F.col("parent").alias("pp"), F.col("d").alias("dd")), "parent").select("v", F.col("pp").alias("parent"), (F.col("d") + F.col("dd")).alias("d"), (F.col("dd") > 0).cast("int").alias("moved"))
        step += 1
        out, seen = scratch.observed(nxt, f"{tag}-{step}", moved=F.sum("moved"), deepest=F.max("d"))
        cur = out.select("v", "parent", "d")
        if not seen["moved"]:
            return int(seen["deepest"] or 0)
