"""Joins against files on disk: what need not be read is decided from footers, before any row is read.

Points in files have columns id, x_0 …; a file is a partition and its path the partition's id.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from boxprune.functions.geometry import Box, contains, point
from boxprune.operators.join import join_kept
from boxprune.plans import prune
from boxprune.sources.manifest import from_files, from_rows, validated
from boxprune.sources.scratch import stored


def _path(col: str) -> Column:
    """Local paths are written with one, two or three slashes by different parts of Spark."""
    return F.regexp_replace(col, "^file:/+", "file:///")


def _points(files: DataFrame, dims: int) -> DataFrame:
    return files.select("id", _path("_metadata.file_path").alias("part_id"), *[f"x_{i}" for i in range(dims)])


def kept_files(spark: SparkSession, r: DataFrame, path: str, k: int, dims: int, rule: str = "counted", exclude_self: bool = False) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Manifest of r, manifest of the files under path from their footers, and the kept pairs."""
    origins = stored(validated(from_rows(r, dims), dims))
    train = stored(validated(from_files(spark, spark.read.parquet(path).inputFiles(), [f"x_{i}" for i in range(dims)]), dims).withColumn("part_id", _path("part_id")))
    return origins, train, stored(prune.keep_pairs(origins, train, k, dims, rule, "auto", exclude_self))


def knn_files(spark: SparkSession, r: DataFrame, path: str, k: int, dims: int, rule: str = "counted", exclude_self: bool = False) -> DataFrame:
    """The k nearest rows of the files under path for each row of r; only files that some origin partition keeps are opened.

    The names of kept files go to the driver, which holds the listing of all files anyway to plan a scan.
    """
    origins, train, pairs = kept_files(spark, r, path, k, dims, rule, exclude_self)
    names = [row[0] for row in pairs.select("part_id").distinct().collect()]
    read = spark.read.schema(spark.read.parquet(path).schema)
    s = _points(read.parquet(*names), dims) if names else _points(spark.read.parquet(path), dims).limit(0)
    return join_kept(r, s, pairs, k, dims, exclude_self, "block", origins=origins, train=train)


def files_skipped(spark: SparkSession, r: DataFrame, path: str, k: int, dims: int, rule: str = "counted") -> DataFrame:
    """One row: files and bytes under path, and how many of them the join reads."""
    _, _, pairs = kept_files(spark, r, path, k, dims, rule)
    kept = pairs.select(F.col("part_id").alias("path")).distinct().withColumn("kept", F.lit(True))
    sizes = spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").load(path)
    sizes = sizes.select(_path("path").alias("path"), "length")
    one = sizes.join(kept, "path", "left").agg(F.count(F.lit(1)).alias("files"), F.count("kept").alias("files_read"), F.sum("length").alias("bytes"), F.coalesce(F.sum(F.when(F.col("kept"), F.col("length"))), F.lit(0)).alias("bytes_read"))
    return one.select(F.lit(rule).alias("rule"), "*")


def range_scan(spark: SparkSession, r: DataFrame, path: str, k: int, dims: int) -> DataFrame:
    """Baseline: the rows within the box around all origins, widened by the farthest two-box cut-off. The box is one row of
    literals, so the reader's own statistics filter skips files and row groups."""
    origins = stored(validated(from_rows(r, dims), dims))
    train = stored(validated(from_files(spark, spark.read.parquet(path).inputFiles(), [f"x_{i}" for i in range(dims)]), dims))
    near = prune.prefiltered(origins, train, k, dims)
    reach = F.sqrt("cut") * (1 + 2.0**-40)
    ends = [f(e).alias(f"{n}_{i}") for i in range(dims) for f, e, n in ((F.min, F.col(f"o_lo_{i}") - reach, "lo"), (F.max, F.col(f"o_hi_{i}") + reach, "hi"))]
    box = near.agg(F.count_if(F.col("cut").isNull() | ~F.col("proof")).alias("open"), *ends).first()
    rows = _points(spark.read.parquet(path), dims)
    if box["open"] or box["lo_0"] is None:  # too few rows are certain, or a box without bounds: everything is read
        return rows
    return rows.where(contains(Box.literal([box[f"lo_{i}"] for i in range(dims)], [box[f"hi_{i}"] for i in range(dims)]), point("", dims)))
