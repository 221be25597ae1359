"""Components kept up to date as batches of edges arrive."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ccspark.plans.runner import connected_components
from ccspark.plans.store import Scratch


class AssignmentStore:
    """Versions of an assignment (``vertex, component``) in the run's folder; a batch id is applied once."""

    def __init__(self, spark: SparkSession, scratch: Scratch | None = None, keep: int = 2, **options):
        self.spark, self.scratch, self.keep, self.options = spark, scratch or Scratch(spark, "stream"), keep, options
        self.version, self.applied = 0, set()
        self.current = self.scratch.write(spark.createDataFrame([], "vertex long, component long"), "v0")

    def merge(self, edges: DataFrame, batch_id: int) -> None:
        """Ends are mapped to their components; components of the small batch graph rename the old ones that it joins."""
        if batch_id in self.applied:
            return
        e = self.scratch.write(edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).where("src is not null and dst is not null"), f"batch-{batch_id}")
        old = self.current
        a, b = (old.select(F.col("vertex").alias(x), F.col("component").alias(f"{x}_c")) for x in ("src", "dst"))
        mapped = e.join(a, "src", "left").join(b, "dst", "left").select(F.coalesce("src_c", "src").alias("src"), F.coalesce("dst_c", "dst").alias("dst"))
        found = connected_components(mapped, **self.options).assignment
        to = found.select(F.col("vertex").alias("component"), F.col("component").alias("joined"))
        moved = old.join(to, "component", "left").select("vertex", F.coalesce("joined", "component").alias("component"))
        ends = e.select(F.explode(F.array("src", "dst")).alias("vertex")).distinct().join(old.select("vertex"), "vertex", "left_anti")
        fresh = ends.join(found, "vertex").select("vertex", "component")
        self.version += 1
        self.current = self.scratch.write(moved.unionByName(fresh), f"v{self.version}")
        self.applied.add(batch_id)
        if self.version > self.keep:
            self.scratch.drop(f"v{self.version - self.keep - 1}")


def merge_batches(stream: DataFrame, store: AssignmentStore, checkpoint: str, trigger: dict | None = None):
    """Starts a query that merges each micro-batch of ``src, dst`` into the store."""
    return stream.writeStream.foreachBatch(lambda df, i: store.merge(df, i)).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def read_edges(spark: SparkSession, folder: str, schema: str = "src long, dst long", per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_batch).parquet(folder)


def rate_edges(spark: SparkSession, per_second: int, vertices: int, seed: int = 0) -> DataFrame:
    """Pseudo-random edges from the rate source."""
    rate = spark.readStream.format("rate").option("rowsPerSecond", per_second).load()
    end = lambda k: F.pmod(F.xxhash64("value", F.lit(seed), F.lit(k)), F.lit(vertices))
    return rate.select(F.col("timestamp").alias("ts"), end(0).alias("src"), end(1).alias("dst"))


def start(df: DataFrame, name: str, mode: str = "append", trigger: dict | None = None, checkpoint: str | None = None):
    """A query into the memory table ``name``."""
    w = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(**(trigger or {"availableNow": True}))
    return (w.option("checkpointLocation", checkpoint) if checkpoint else w).start()
