"""Similarity of vectors: as Column expressions, and as joins of a whole table with itself in blocks."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLOCK = 4096


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def similar_pairs(df: DataFrame, key: str, vector: str, threshold: float, block: int = BLOCK) -> DataFrame:
    """``src, dst`` of all pairs with cosine >= threshold, exactly: each block of vectors is compared with all rows.

    The block bounds what is sent to the tasks; the work is quadratic, so this is for tables of moderate size.
    :func:`banded_pairs` is the way beyond it.
    """
    rows = df.select(F.col(key).cast("long").alias("k"), F.col(vector).cast("array<double>").alias("x")).where("k is not null and x is not null")
    out, held = [], []

    def flush():
        keys = np.array([r["k"] for r in held])
        table = np.array([r["x"] for r in held])
        sent = df.sparkSession.sparkContext.broadcast((keys, table, np.linalg.norm(table, axis=1)))

        def work(batches):
            import pyarrow as pa

            ids, vectors, norms = sent.value
            for b in batches:
                if not b.num_rows:
                    continue
                k = b.column("k").to_numpy()
                x = np.array(b.column("x").to_pylist())
                r, c = np.nonzero((k[:, None] < ids[None, :]) & (x @ vectors.T >= threshold * np.linalg.norm(x, axis=1)[:, None] * norms[None, :]))
                yield pa.RecordBatch.from_arrays([pa.array(k[r]), pa.array(ids[c])], names=["src", "dst"])

        out.append(rows.mapInArrow(work, "src long, dst long"))
        held.clear()

    for r in rows.toLocalIterator():
        held.append(r)
        if len(held) == block:
            flush()
    if held:
        flush()
    return reduce(DataFrame.unionByName, out) if out else df.sparkSession.createDataFrame([], "src long, dst long")


def banded_pairs(df: DataFrame, key: str, vector: str, threshold: float, dims: int, bands: int = 16, bits: int = 8, seed: int = 11) -> DataFrame:
    """Pairs that agree in the signs of all random hyperplanes of some band, settled by exact cosine. May miss pairs."""
    planes = np.random.default_rng(seed).standard_normal((bands * bits, dims))
    rows = df.select(F.col(key).cast("long").alias("k"), F.col(vector).cast("array<double>").alias("x"))
    sign = lambda p: (dot(F.col("x"), F.array(*[F.lit(float(v)) for v in p])) >= 0).cast("int")
    codes = [F.concat_ws("", F.lit(f"{b}:"), *[sign(planes[b * bits + i]) for i in range(bits)]) for b in range(bands)]
    dealt = rows.select("k", "x", F.explode(F.array(*codes)).alias("code"))
    a, b = dealt.select(F.col("k").alias("src"), F.col("x").alias("x"), "code"), dealt.select(F.col("k").alias("dst"), F.col("x").alias("y"), "code")
    return a.join(b, "code").where("src < dst").where(cosine(F.col("x"), F.col("y")) >= threshold).select("src", "dst").distinct()
