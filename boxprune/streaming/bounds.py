"""Bounds of a stream of events: mergeable aggregates over windows, joins of micro-batches, bounds by user."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def window_bounds(events: DataFrame, window, ts: str = "ts", value: str = "value", watermark: str | None = None) -> DataFrame:
    """window_start, n_rows, lo_0, hi_0; window is a Column such as F.window(…) or F.session_window(…).

    With a watermark, rows later than it are dropped and, in append mode, a window is final only once it has passed; a window
    used before that has stale bounds, which later rows can only widen.
    """
    if watermark:
        events = events.withWatermark(ts, watermark)
    out = events.groupBy(window.alias("w")).agg(F.count(F.lit(1)).alias("n_rows"), F.min(value).alias("lo_0"), F.max(value).alias("hi_0"))
    return out.select(F.col("w.start").alias("window_start"), "n_rows", "lo_0", "hi_0")


def tumbling(events: DataFrame, watermark: str | None = None) -> DataFrame:
    return window_bounds(events, F.window("ts", "1 day"), watermark=watermark)


def sliding(events: DataFrame, watermark: str | None = None) -> DataFrame:
    return window_bounds(events, F.window("ts", "1 day", "12 hours"), watermark=watermark)


def sessions(events: DataFrame, gap: str = "4 minutes", watermark: str | None = None) -> DataFrame:
    return window_bounds(events, F.session_window("ts", gap), watermark=watermark)


def knn_each_batch(stream: DataFrame, train: DataFrame, k: int, dims: int, sink: Callable[[DataFrame, int], None]):
    """A writer that joins every micro-batch of points against a static train side."""
    from boxprune.operators.join import knn

    return stream.writeStream.foreachBatch(lambda batch, number: sink(knn(batch, train, k, dims), number))


def user_bounds(stream: DataFrame, ttl_ms: int | None = None) -> DataFrame:
    """Running user_id, n_rows, lo, hi, as state of min, max and count by user that leaves after ttl_ms without rows."""
    import pandas as pd
    from pyspark.sql.streaming import StatefulProcessor

    class Bounds(StatefulProcessor):
        def init(self, handle):
            self.state = handle.getValueState("bounds", "n long, lo double, hi double", ttlDurationMs=ttl_ms)

        def handleInputRows(self, key, rows, timerValues):
            n, lo, hi = self.state.get() if self.state.exists() else (0, float("inf"), float("-inf"))
            for frame in rows:
                n, lo, hi = n + len(frame), min(lo, frame["value"].min()), max(hi, frame["value"].max())
            self.state.update((n, float(lo), float(hi)))
            yield pd.DataFrame({"user_id": [key[0]], "n_rows": [n], "lo": [lo], "hi": [hi]})

        def close(self):
            pass

    return stream.groupBy("user_id").transformWithStateInPandas(Bounds(), "user_id long, n_rows long, lo double, hi double", "Update", "ProcessingTime" if ttl_ms else "None")
