"""``spark.read.format("cc_graph")``: path, star or cycle edges from a partitioned Python data source."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Span(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.kind, self.n, self.parts = options.get("kind", "path"), int(options.get("n", "0")), int(options.get("partitions", "4"))

    def partitions(self):
        step = -(-max(self.n, 1) // self.parts)
        return [_Span(i, min(i + step, self.n)) for i in range(0, self.n, step)] or [_Span(0, 0)]

    def read(self, span):
        for i in range(span.first, span.last):
            if self.kind == "path" and i + 1 < self.n:
                yield i, i + 1
            elif self.kind == "star" and i:
                yield 0, i
            elif self.kind == "cycle":
                yield min(i, (i + 1) % self.n), max(i, (i + 1) % self.n)


class GraphSource(DataSource):
    @classmethod
    def name(cls):
        return "cc_graph"

    def schema(self):
        return "src long, dst long"

    def reader(self, schema):
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(GraphSource)
