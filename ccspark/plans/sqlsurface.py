"""SQL entry points: views of a result, a table function, a grouped aggregate, a bounded recursive query."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def register(result, prefix: str) -> None:
    """Views ``<prefix>_assignment`` and ``<prefix>_stats``."""
    result.assignment.createOrReplaceTempView(f"{prefix}_assignment")
    result.stats_frame().createOrReplaceTempView(f"{prefix}_stats")


class _LocalComponents:
    """Components of the edges of one partition, given out when its rows end."""

    def __init__(self):
        self.up = {}

    def _root(self, x):
        while self.up.setdefault(x, x) != x:
            x = self.up[x]
        return x

    def eval(self, row):
        self.key = row["k"]
        a, b = self._root(row["src"]), self._root(row["dst"])
        self.up[max(a, b)] = min(a, b)

    def terminate(self):
        for v in list(self.up):
            yield self.key, v, self._root(v)


def register_functions(spark: SparkSession) -> None:
    """``local_components(TABLE(e) PARTITION BY k)`` and ``component_count(src, dst)``."""
    import pandas as pd

    spark.udtf.register("local_components", F.udtf(_LocalComponents, returnType="k long, vertex long, component long"))

    def component_count(src: pd.Series, dst: pd.Series) -> int:
        up = {}

        def root(x):
            while up.setdefault(x, x) != x:
                x = up[x]
            return x

        for a, b in zip(src, dst, strict=True):
            a, b = root(a), root(b)
            up[max(a, b)] = min(a, b)
        return sum(root(v) == v for v in list(up))

    component_count.__annotations__ = {"src": pd.Series, "dst": pd.Series, "return": int}
    spark.udf.register("component_count", F.pandas_udf(component_count, "long"))


def local_components(edges: DataFrame, key: str) -> DataFrame:
    spark = edges.sparkSession
    register_functions(spark)
    edges.select(F.col(key).cast("long").alias("k"), "src", "dst").createOrReplaceTempView("cc_blocks")
    return spark.sql("SELECT * FROM local_components(TABLE(cc_blocks) PARTITION BY k)")


def spread_sql(edges: DataFrame, depth: int) -> DataFrame:
    """Least label within ``depth`` hops by a recursive query of that depth: for tiny graphs of small diameter."""
    spark = edges.sparkSession
    edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).createOrReplaceTempView("cc_sym")
    return spark.sql(f"""
        WITH RECURSIVE walk(vertex, label, hops) AS (
            SELECT DISTINCT src, src, 0 FROM cc_sym
            UNION ALL
            SELECT s.dst, w.label, w.hops + 1 FROM walk w JOIN cc_sym s ON s.src = w.vertex WHERE w.hops < {int(depth)} AND w.label < s.dst)
        SELECT vertex, min(label) AS component FROM walk GROUP BY vertex""")
