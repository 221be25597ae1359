"""Shared rules: null text is empty text, white space is the six ASCII characters; and how batch functions use memory."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: The white-space characters (space, tab, line feed, vertical tab, form feed, carriage return).
WHITE = " \t\n\x0b\x0c\r"
WHITE_RUN = r"[\x20\x09-\x0D]+"
#: What an executor gathers for a Python task at once: some of it is held three times over outside the heap.
BATCH_BYTES = 4 << 20
_BATCH_CONF = "spark.sql.execution.arrow.maxBytesPerBatch"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = "abcdefghijklmnopqrstuvwxyz"


def text_of(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def ascii_lower(c: Column) -> Column:
    """A-Z only; other letters stay."""
    return F.translate(c, UPPER, LOWER)


def words_of(c: Column) -> Column:
    return F.array_remove(F.split(c, WHITE_RUN), "")


def dense_ids(rows: DataFrame, columns: list[str], scratch, table: str = "dense") -> DataFrame:
    """The rows with ``id``, their rank by the columns (which tell all rows apart), without any task that sees all of them.

    Rows are dealt by range and written; an id is the rank in its part plus the sizes of the parts before it.
    """
    dealt = scratch.write(rows.repartitionByRange(*columns).withColumn("_part", F.spark_partition_id()), table)
    sizes = dealt.groupBy("_part").agg(F.count(F.lit(1)).alias("n"))
    before = sizes.select(F.col("_part"), (F.sum("n").over(Window.orderBy("_part")) - F.col("n")).alias("_before"))
    rank = F.row_number().over(Window.partitionBy("_part").orderBy(*columns))
    return dealt.withColumn("_rank", rank).join(F.broadcast(before), "_part").withColumn("id", (F.col("_before") + F.col("_rank")).cast("long")).drop("_part", "_before", "_rank")


def scan_array(items: Column, zero: Column, step: Callable[[Column, Column], Column], emit: Callable[[Column, Column], Column], kind: str) -> Column:
    """What ``emit(state, item)`` (of type ``kind``) gives for each item of a running ``step(state, item)`` from ``zero``.

    A fold that appends copies its array each time; in blocks of the square root of the length this stays small:
    n ** 1.5 copies, some seconds for a hundred thousand items.
    """
    n = F.size(items)
    width = F.greatest(F.lit(1), F.ceil(F.sqrt(n)).cast("int"))
    blocks = F.transform(F.sequence(F.lit(0), F.floor((n - 1) / width).cast("int")), lambda b: F.slice(items, b * width + 1, width))

    def block(state, part):
        start = F.struct(state.alias("s"), F.array().cast(f"array<{kind}>").alias("out"))
        return F.aggregate(part, start, lambda a, x: F.struct(step(a["s"], x).alias("s"), F.concat(a["out"], F.array(emit(a["s"], x))).alias("out")))

    def join(a, part):
        once = F.transform(F.array(block(a["s"], part)), lambda r: F.struct(r["s"].alias("s"), F.concat(a["out"], F.array(r["out"])).alias("out")))
        return F.element_at(once, 1)

    start = F.struct(zero.alias("s"), F.array().cast(f"array<array<{kind}>>").alias("out"))
    return F.when(n > 0, F.flatten(F.aggregate(blocks, start, join)["out"])).otherwise(F.array().cast(f"array<{kind}>"))


def keep_columns(df: DataFrame, *names: str) -> DataFrame:
    """Only the named columns, so that extra columns of any name cannot clash with an operator's own."""
    return df.select(*names)


def split_hosts(url: Column) -> tuple[Column, Column]:
    """Host (lower case A-Z) and path of a url; both empty for null or without ``://``."""
    u = F.coalesce(url, F.lit(""))
    return ascii_lower(F.regexp_extract(u, r"(?s)^.*?://([^/?#]*)", 1)), F.regexp_extract(u, r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def small_batches(spark: SparkSession) -> None:
    """Bounds the bytes of a batch for the session's plans from here on, as they are planned when they run; a lower bound stays.

    Spark's own bounds are 10,000 rows and 64 MB. Rows of numbers don't reach this one.
    """
    if spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get(_BATCH_CONF)) > BATCH_BYTES:
        spark.conf.set(_BATCH_CONF, str(BATCH_BYTES))


def release() -> None:
    """Gives memory that this process no longer uses back to the machine, where the allocators can."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def lean(work: Callable[[Iterator], Iterator], rows: int = 0) -> Callable[[Iterator], Iterator]:
    """The batch function over batches of at most ``rows`` rows (0: as they come), which releases memory at its end.

    Python workers outlive their tasks, so what they keep would add up beside the next stage's.
    """

    def run(batches: Iterator) -> Iterator:
        def cut():
            for b in batches:
                for i in range(0, max(1, b.num_rows), rows or max(1, b.num_rows)):
                    yield b.slice(i, rows or b.num_rows)

        try:
            yield from work(cut())
        finally:
            release()

    return run
