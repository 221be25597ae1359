"""Synthetic graphs over ``spark.range``; the same seed gives the same edges whatever the partitions."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ccspark.operators.edges import simplify


def _pairs(df: DataFrame, src, dst) -> DataFrame:
    return simplify(df.select(src.cast("long").alias("src"), dst.cast("long").alias("dst")))


def path(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(max(0, n - 1)).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))


def cycles(spark: SparkSession, n: int, parts: int = 1) -> DataFrame:
    """``parts`` cycles of ``n // parts`` vertices each."""
    k = n // parts
    i = F.col("id")
    return _pairs(spark.range(k * parts), i, i - F.pmod(i, F.lit(k)) + F.pmod(i + 1, F.lit(k)))


def star(spark: SparkSession, leaves: int) -> DataFrame:
    return spark.range(1, leaves + 1).select(F.lit(0).cast("long").alias("src"), F.col("id").alias("dst"))


def clique(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("src"), F.explode(F.sequence(F.col("id") + 1, F.lit(n).cast("long"))).alias("dst")).where(f"dst < {n}")


def grid(spark: SparkSession, rows: int, columns: int) -> DataFrame:
    i = F.col("id")
    both = spark.range(rows * columns).select(i.alias("src"), F.explode(F.array(F.when(F.pmod(i, F.lit(columns)) < columns - 1, i + 1), F.when(i + columns < rows * columns, i + columns))).alias("dst"))
    return both.where("dst is not null")


def gnp(spark: SparkSession, n: int, degree: float | None = None, seed: int = 0, first: int = 0) -> DataFrame:
    """Random graph of mean degree ``degree`` (4 ln n by default): each of as many draws is a uniform pair.

    Pairs are drawn by hash, independently; duplicates and loops go, which at such densities leaves the
    independent-edge law up to lower order terms.
    """
    degree = 4 * math.log(max(n, 2)) if degree is None else degree
    end = lambda k: F.pmod(F.xxhash64("id", F.lit(seed), F.lit(k)), F.lit(n)) + first
    return _pairs(spark.range(int(n * degree / 2)), end(0), end(1))


def gnp_plus(spark: SparkSession, n: int, kind: str = "path", seed: int = 0) -> DataFrame:
    """The relaxed class: a random graph with a fixed path or star added."""
    extra = path(spark, n) if kind == "path" else star(spark, n - 1)
    return simplify(gnp(spark, n, seed=seed).unionByName(extra))


def gnp_blocks(spark: SparkSession, sizes: list[int], seed: int = 0) -> DataFrame:
    """Disjoint random graphs of the given sizes."""
    out, first = None, 0
    for i, n in enumerate(sizes):
        part = gnp(spark, n, seed=seed + i, first=first)
        out = part if out is None else out.unionByName(part)
        first += n
    return out


def forest_mix(spark: SparkSession, n: int, extra: float = 1.0, block: int = 1000, seed: int = 0) -> DataFrame:
    """Many components of uneven shape: random recursive trees of ``block`` vertices, chains between some, ``extra * n`` random edges inside blocks."""
    i, base = F.col("id"), F.col("id") - F.pmod("id", F.lit(block))
    at = F.pmod("id", F.lit(block))
    parent = base + F.when(F.pmod(F.xxhash64(base, F.lit(seed)), F.lit(4)) == 0, at - 1).otherwise(F.pmod(F.xxhash64("id", F.lit(seed), F.lit(1)), F.greatest(at, F.lit(1))))
    trees = spark.range(n).where(at > 0).select(i.alias("src"), parent.alias("dst"))
    joints = spark.range(block, n, block).where(F.pmod(F.xxhash64("id", F.lit(seed), F.lit(2)), F.lit(3)) > 0).select(i.alias("src"), (i - block).alias("dst"))
    end = lambda k: F.pmod(F.xxhash64("id", F.lit(seed), F.lit(k)), F.lit(block))
    more = spark.range(int(n * extra)).select((F.pmod("id", F.lit(n)) - F.pmod("id", F.lit(block))).alias("b"), end(3).alias("x"), end(4).alias("y")).where(F.pmod(F.xxhash64("b", F.lit(seed)), F.lit(4)) != 0)
    return _pairs(trees.unionByName(joints).unionByName(more.select((F.col("b") + F.col("x")).alias("src"), (F.col("b") + F.col("y")).alias("dst"))), F.col("src"), F.col("dst"))


KINDS = {"path": path, "cycles": cycles, "star": star, "clique": clique, "gnp": gnp}
