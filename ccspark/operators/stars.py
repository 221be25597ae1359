"""Star operations of the alternating baseline, over canonical edges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ccspark.functions.priority import Priority
from ccspark.operators.edges import simplify, symmetrise
from ccspark.operators.labels import closed_min

_ORDER = Priority("identity")


def large_star(edges: DataFrame) -> DataFrame:
    """Each vertex links its larger neighbours to the minimum of its closed neighbourhood."""
    sym = symmetrise(edges)
    low = closed_min(sym, _ORDER).withColumnRenamed("v", "src")
    return simplify(sym.where("dst > src").join(low, "src").select(F.col("dst").alias("src"), F.col("m").alias("dst")))


def small_star(edges: DataFrame) -> DataFrame:
    """Each vertex links its smaller neighbours and itself to the minimum of them."""
    down = symmetrise(edges).where("dst < src")
    low = down.groupBy("src").agg(F.min("dst").alias("m"))
    moved = down.join(low, "src").select(F.col("dst").alias("src"), F.col("m").alias("dst"))
    return simplify(moved.unionByName(low.select("src", F.col("m").alias("dst"))))


def large_star_run(edges: DataFrame, scratch, same, tag: str, lookup: bool = False, lookup_rows: int = 0) -> tuple[DataFrame, int, int]:
    """Large-stars until nothing changes, or one pass by pointers to local minima (``lookup``): edges, steps, lookups.

    Pointers are looked up in the map itself while it has at most ``lookup_rows`` rows, else doubled.
    """
    if lookup:
        from ccspark.operators.labels import chase_lookup, jump_pointers

        sym, hops = symmetrise(edges), 0
        low, n = scratch.counted(closed_min(sym, _ORDER).select("v", F.col("m").alias("parent")), f"{tag}-low")
        if n <= lookup_rows:
            root, seen = scratch.observed(chase_lookup(low, lookup_rows), f"{tag}-chase", hops=F.sum("hops"))
            hops, steps = seen["hops"] or 0, 1
        else:
            root, steps = jump_pointers(low, scratch, f"{tag}-chase")
        to = root.select(F.col("v").alias("dst"), F.col("parent").alias("m"))
        moved = sym.where("dst < src").join(to, "dst").select("src", F.col("m").alias("dst"))
        return scratch.write(simplify(moved), f"{tag}-run"), steps, hops
    cur, k = edges, 0
    while True:
        nxt = scratch.write(large_star(cur), f"{tag}-large{k}")
        k += 1
        if same(cur, nxt):
            return nxt, k, 0
        cur = nxt
