"""Uses of an assignment: one row a component, members, levels of single linkage, components of many small graphs."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ccspark.operators.finish import _spanning
from ccspark.plans.runner import connected_components


def dedupe(rows: DataFrame, assignment: DataFrame, key: str) -> DataFrame:
    """Rows whose vertex names its component."""
    heads = assignment.where("vertex = component").select(F.col("vertex").alias(key))
    return rows.join(heads, key, "left_semi")


def members(assignment: DataFrame, max_size: int) -> DataFrame:
    """``component, members`` of components of at most ``max_size`` vertices; larger ones stay as rows of the assignment."""
    sizes = assignment.groupBy("component").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") <= max_size)
    return assignment.join(sizes, "component", "left_semi").groupBy("component").agg(F.sort_array(F.collect_list("vertex")).alias("members"))


def levels(edges: DataFrame, weight: str, thresholds: Sequence[float], **options) -> DataFrame:
    """Single linkage: ``level, threshold, vertex, component`` for falling thresholds, each level over the nodes of the one before."""
    out, named = None, None
    for i, t in enumerate(sorted(thresholds, reverse=True)):
        e = edges.where(F.col(weight) >= t).select("src", "dst")
        if named is not None:
            a, b = (named.select(F.col("vertex").alias(x), F.col("component").alias(f"{x}_c")) for x in ("src", "dst"))
            e = e.join(a, "src", "left").join(b, "dst", "left").select(F.coalesce("src_c", "src").alias("src"), F.coalesce("dst_c", "dst").alias("dst"))
        found = connected_components(e, **options).assignment
        if named is None:
            named = found
        else:
            up = found.select(F.col("vertex").alias("component"), F.col("component").alias("higher"))
            moved = named.join(up, "component", "left").select("vertex", F.coalesce("higher", "component").alias("component"))
            fresh = found.join(named.select("vertex"), "vertex", "left_anti")
            named = moved.unionByName(fresh)
        level = named.select(F.lit(i).alias("level"), F.lit(float(t)).alias("threshold"), "vertex", "component")
        out = level if out is None else out.unionByName(level)
    return out


def per_block(edges: DataFrame, key: str) -> DataFrame:
    """``key, vertex, component`` for many small graphs, each in one task: blocks must fit in memory."""

    def one(k, table):
        import pyarrow as pa

        parts = list(_spanning(table.select(["src", "dst"]).to_batches(), False))
        t = pa.Table.from_batches(parts, schema=pa.schema([("v", pa.int64()), ("node", pa.int64())])) if parts else pa.table({"v": pa.array([], pa.int64()), "node": pa.array([], pa.int64())})
        return pa.table({key: pa.array([k[0].as_py()] * t.num_rows, pa.int64()), "vertex": t.column("v"), "component": t.column("node")})

    return edges.select(F.col(key).cast("long").alias(key), "src", "dst").groupBy(key).applyInArrow(one, f"{key} long, vertex long, component long")
