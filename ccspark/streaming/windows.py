"""Event-time views of a stream: lateness, windows, duplicates, and running components of a key."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def with_lateness(df: DataFrame, ts: str, delay: str) -> DataFrame:
    """A watermark on the time column, cast to an instant first (tables hold times without a zone)."""
    return df.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)


def split_late(df: DataFrame, ts: str, bound) -> tuple[DataFrame, DataFrame]:
    """Rows of a batch on time and late against a bound that the caller carries."""
    return df.where(F.col(ts) >= bound), df.where(F.col(ts) < bound)


def window_components(df: DataFrame, kind: str, key: str, ts: str, size: str, slide: str | None = None) -> DataFrame:
    """Rows of a key in tumbling, sliding or session windows; a session is a component of links no longer than the gap."""
    if kind == "session":
        w = F.session_window(F.col(ts), size)
    else:
        w = F.window(F.col(ts), size, slide) if kind == "sliding" else F.window(F.col(ts), size)
    return df.groupBy(key, w.alias("w")).agg(F.count(F.lit(1)).alias("n"), F.min("event_id").alias("component"))


def dedupe(df: DataFrame, keys: list[str]) -> DataFrame:
    """First of equal rows within the watermark."""
    return df.dropDuplicatesWithinWatermark(keys)


def user_state(df: DataFrame, key: str = "user_id", ts: str = "ts", vertex: str = "event_id", gap_s: int = 7200) -> DataFrame:
    """``key, component, n``: the running component of each key, closed when a row comes later than the gap.

    State is the last instant, the least vertex and the count: constant in size for each key. Rows of a
    key within a batch are taken in time order.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(k, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last, low, n = state.get if state.exists else (None, None, 0)
        rows = pd.concat(list(frames)).sort_values([ts, vertex])
        out = []
        for t, v in zip(rows[ts].astype("int64").tolist() if str(rows[ts].dtype).startswith("int") else (rows[ts].astype("datetime64[us]").astype("int64")).tolist(), rows[vertex].tolist(), strict=True):
            if last is not None and t - last > gap_s * 1_000_000:
                out.append((k[0], low, n))
                low, n = None, 0
            low, n, last = v if low is None else min(low, v), n + 1, t
        state.update((last, low, n))
        out.append((k[0], low, n))
        yield pd.DataFrame(out, columns=[key, "component", "n"])

    return df.groupBy(key).applyInPandasWithState(step, f"{key} long, component long, n long", "last long, low long, n long", "update", GroupStateTimeout.NoTimeout)
