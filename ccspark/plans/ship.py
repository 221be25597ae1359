"""Sends this package to the executors, where it may not be installed."""

from __future__ import annotations

import functools
import hashlib
import tempfile
import zipfile
from collections.abc import Callable
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_sent: set[tuple[str, str]] = set()


def ship(spark: SparkSession) -> None:
    """Once per application: a zip of the package's sources, served by Spark to each task."""
    root = Path(__file__).resolve().parent.parent
    files = sorted(root.rglob("*.py"))
    digest = hashlib.sha256(b"".join(f.read_bytes() for f in files)).hexdigest()[:16]
    key = (spark.sparkContext.applicationId, digest)
    if key in _sent:
        return
    path = Path(tempfile.mkdtemp()) / f"{root.name}-{digest}.zip"
    with zipfile.ZipFile(path, "w") as z:
        for f in files:
            z.write(f, f.relative_to(root.parent))
    spark.sparkContext.addPyFile(str(path))
    _sent.add(key)


def shipped(query: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    @functools.wraps(query)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return query(spark, sf_dir)

    return run
