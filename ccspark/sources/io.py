"""Tables, edge lists, adjacency lists; sinks in the usual formats."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", src: str = "src", dst: str = "dst", header: bool = True) -> tuple[DataFrame, DataFrame]:
    """Edges of a CSV, TSV, whitespace text, JSON lines, ORC or Parquet file, and the rows that are no pair of longs.

    In text and TSV or CSV without header the first two fields are the ends.
    """
    if fmt in ("csv", "tsv"):
        raw = spark.read.option("header", header).option("sep", "\t" if fmt == "tsv" else ",").csv(path)
        a, b = (F.col(src), F.col(dst)) if header else (F.col(raw.columns[0]), F.col(raw.columns[1]))
    elif fmt == "text":
        raw = spark.read.text(path)
        parts = F.split(F.trim("value"), r"\s+")
        a, b = F.get(parts, F.lit(0)), F.get(parts, F.lit(1))
    elif fmt == "json":
        raw = spark.read.schema(f"{src} string, {dst} string").json(path)
        a, b = F.col(src), F.col(dst)
    elif fmt in ("orc", "parquet"):
        raw = spark.read.format(fmt).load(path)
        a, b = F.col(src).cast("string"), F.col(dst).cast("string")
    else:
        raise ValueError(f"unknown format {fmt}")
    both = raw.select(a.try_cast("long").alias("src"), b.try_cast("long").alias("dst"), F.to_json(F.struct("*")).alias("row"))
    good = both.where("src is not null and dst is not null").select("src", "dst")
    return good, both.where("src is null or dst is null").select("row")


def read_adjacency(spark: SparkSession, path: str, sep: str = r"\s+") -> DataFrame:
    """Lines ``vertex neighbour neighbour ...``; a line of one field has no edges."""
    parts = F.split(F.trim("value"), sep)
    rows = spark.read.text(path).select(F.get(parts, F.lit(0)).try_cast("long").alias("src"), F.explode(F.slice(parts, F.lit(2), F.greatest(F.size(parts) - 1, F.lit(0)))).alias("d"))
    return rows.select("src", F.col("d").try_cast("long").alias("dst")).where("src is not null and dst is not null")


def write(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite", partition_by: Sequence[str] = (), sort_by: Sequence[str] = ()) -> None:
    out = df.sortWithinPartitions(*sort_by) if sort_by else df
    writer = out.write.mode(mode).format(fmt)
    if fmt == "csv":
        writer = writer.option("header", True)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def page(df: DataFrame, order_by: Sequence[str], limit: int, offset: int = 0) -> DataFrame:
    """Rows ``offset .. offset + limit`` in a total order (give columns that tell all rows apart)."""
    return df.orderBy(*order_by).offset(offset).limit(limit)


def put_edges(df: DataFrame, table: str, buckets: int) -> DataFrame:
    """Symmetric edges as a table bucketed and sorted by ``src``: aggregates and joins on it need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(table)
    return df.sparkSession.table(table)
