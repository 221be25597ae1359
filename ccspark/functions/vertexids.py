"""Vertex ids for entities of several tables, for strings and for JSON values."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The kinds of entities.
KINDS = {"customer": 1, "part": 2, "order": 3, "supplier": 4, "nation": 5, "region": 6}


def encode(kind: str, key: Column) -> Column:
    """``key * 8 + kind``: distinct for entities of different tables below 2^60."""
    return key.cast("long") * 8 + KINDS[kind]


def kind_of(v: Column) -> Column:
    return F.pmod(v, F.lit(8)).cast("int")


def key_of(v: Column) -> Column:
    return F.shiftright(v, 3)


def dictionary(df: DataFrame, columns: list[str], scratch) -> DataFrame:
    """``value, id``: dense ids of the distinct values in their order.

    Values are dealt by range and written; an id is the rank in the part plus the sizes of the
    parts before it, of which there are as many as parts.
    """
    values = df.select(F.explode(F.array(*[F.col(c).cast("string") for c in columns])).alias("value")).where("value is not null").distinct()
    dealt = scratch.write(values.repartitionByRange("value").withColumn("part", F.spark_partition_id()), "dictionary")
    from pyspark.sql import Window

    sizes = dealt.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    before = sizes.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before"))
    rank = F.row_number().over(Window.partitionBy("part").orderBy("value"))
    return dealt.withColumn("r", rank).join(F.broadcast(before), "part").select("value", (F.col("before") + F.col("r") - 1).cast("long").alias("id"))


def hashed(value: Column) -> Column:
    """A long for a string key; :func:`collisions` tells whether two keys share one."""
    return F.xxhash64(value)


def collisions(df: DataFrame, column: str) -> DataFrame:
    return df.select(column).distinct().groupBy(F.xxhash64(column).alias("id")).agg(F.count(F.lit(1)).alias("n")).where("n > 1")


def from_json(column: Column, path: str) -> Column:
    return F.get_json_object(column, path)
