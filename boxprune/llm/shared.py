"""Plan helpers shared by the operators: reading tables, cutting lineage, checked broadcasts."""

from __future__ import annotations

import gc
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boxprune.sources.scratch import discard
from boxprune.sources.scratch import stored as _stored


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_cleaned = [0.0]


def stored(df: DataFrame) -> DataFrame:
    """As the core's ``stored``; at times it also lets Spark delete the shuffle files of finished steps, which hold until the
    driver collects garbage."""
    out = _stored(df)
    if time.monotonic() - _cleaned[0] > CLEAN_SECONDS:
        gc.collect()
        df.sparkSession.sparkContext._jvm.System.gc()
        _cleaned[0] = time.monotonic()
    return out


#: Seconds between two such collections.
CLEAN_SECONDS = 10.0

#: Rows of at most two longs that may be broadcast (32 MB); larger frames are joined by a shuffle.
BROADCAST_ROWS = 1_000_000


def small_side(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """Mark a stored frame of narrow rows for broadcast if it is counted to be small."""
    return F.broadcast(df) if df.count() <= rows else df


def blank_text(col: str = "text"):
    return F.coalesce(F.col(col), F.lit(""))


__all__ = ["BROADCAST_ROWS", "blank_text", "discard", "small_side", "stored", "table"]
