"""Scratch tables that cut lineage and survive the loss of an executor.

Every intermediate frame is written as Parquet under the folder that the cluster
names in ``spark.checkpoint.dir`` and read back. A private folder is chosen only
when the setting is absent and the master is local (tests on one machine).
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator, Sequence
from contextlib import contextmanager

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """Folder for intermediate tables: the cluster's own, else one private to this run."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not named and not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return (named or f"{tempfile.gettempdir()}/ccspark-checkpoints").rstrip("/")


_open: list[list[Scratch]] = []


@contextmanager
def transient() -> Iterator[None]:
    """Deletes, at its end, the tables of all scratch folders that were made within: for work whose result is written elsewhere."""
    _open.append([])
    try:
        yield
    finally:
        for scratch in _open.pop():
            scratch.drop()


class Scratch:
    """One run's folder of intermediate tables.

    ``write`` returns the reread frame; ``counted`` also returns the row count that the
    writing job observed, so that no second job is needed. ``drop`` deletes a table.
    """

    def __init__(self, spark: SparkSession, name: str = "run", run_id: str | None = None):
        """run_id: a name to come back to after a failure; by default no other run has it."""
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{name}-{run_id or uuid.uuid4().hex}"
        if _open and run_id is None:
            _open[-1].append(self)

    def path(self, table: str) -> str:
        return f"{self.root}/{table}"

    def write(self, df: DataFrame, table: str, partition_by: Sequence[str] = ()) -> DataFrame:
        writer = df.write.mode("overwrite")
        if partition_by:
            writer = writer.partitionBy(*partition_by)
        writer.parquet(self.path(table))
        return self.spark.read.schema(df.schema).parquet(self.path(table))

    def observed(self, df: DataFrame, table: str, **measures) -> tuple[DataFrame, dict]:
        """Write and reread; the measures (aggregate columns by name) come from the same job."""
        seen = Observation(f"{table}-{uuid.uuid4().hex[:8]}")
        out = self.write(df.observe(seen, *[c.alias(k) for k, c in measures.items()]), table)
        return out, seen.get

    def counted(self, df: DataFrame, table: str) -> tuple[DataFrame, int]:
        out, seen = self.observed(df, table, rows=F.count(F.lit(1)))
        return out, seen["rows"]

    def has(self, table: str) -> bool:
        """Whether the table was written to its end."""
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path(table)}/_SUCCESS")
        return path.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(path)

    def read(self, table: str) -> DataFrame:
        return self.spark.read.parquet(self.path(table))

    def drop(self, table: str = "") -> None:
        jvm = self.spark._jvm
        path = jvm.org.apache.hadoop.fs.Path(self.path(table) if table else self.root)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)
