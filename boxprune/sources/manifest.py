"""Manifests: one row a partition with its bounds on every axis and its row count."""

from __future__ import annotations

from collections.abc import Iterable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from boxprune.functions.geometry import Box, is_valid


def bounds(dims: int) -> list[Column]:
    return [F.count(F.lit(1)).alias("n_rows"), *[f(f"x_{i}").alias(f"{n}_{i}") for i in range(dims) for f, n in ((F.min, "lo"), (F.max, "hi"))]]


def real_points(points: DataFrame, dims: int) -> DataFrame:
    """Rows with a null or NaN coordinate are not points."""
    return points.dropna(subset=[f"x_{i}" for i in range(dims)])


def from_rows(points: DataFrame, dims: int, part: str = "part_id") -> DataFrame:
    """part_id, n_rows, lo_0, hi_0, …; partial aggregates make the shuffle a row a partition and task."""
    return real_points(points, dims).groupBy(F.col(part).alias("part_id")).agg(*bounds(dims))


def validated(manifest: DataFrame, dims: int) -> DataFrame:
    """Adds ``usable``: only such boxes may be skipped or prove a skip."""
    return manifest.where("n_rows > 0").withColumn("usable", is_valid(Box.of("", dims)))


def widen(manifest: DataFrame, dims: int, share: float) -> DataFrame:
    """Bounds loosened by a share of each side."""
    out = manifest
    for i in range(dims):
        side = (F.col(f"hi_{i}") - F.col(f"lo_{i}")) * share
        out = out.withColumns({f"lo_{i}": F.col(f"lo_{i}") - side, f"hi_{i}": F.col(f"hi_{i}") + side})
    return out.select(*manifest.columns)


def filtered_counts(points: DataFrame, predicate: Column, dims: int, part: str = "part_id") -> DataFrame:
    """Exact rows of each partition under a predicate: a narrow scan of the predicate's and the key columns."""
    return real_points(points, dims).groupBy(F.col(part).alias("part_id")).agg(F.count_if(predicate).alias("n_rows"))


def with_counts(manifest: DataFrame, counts: DataFrame) -> DataFrame:
    """The manifest with exact counts in place of its upper bounds; partitions left empty go."""
    exact = counts.select(F.col("part_id").alias("counted_id"), F.col("n_rows").alias("exact"))
    return manifest.join(exact, F.col("part_id").eqNullSafe(F.col("counted_id"))).withColumn("n_rows", F.col("exact")).where("n_rows > 0").select(*manifest.columns)


def from_footers(spark: SparkSession, files: DataFrame, coords: Iterable[str]) -> DataFrame:
    """file_path, row_group, n_rows, n_nulls and bounds from parquet statistics, without reading rows.

    files: one column ``file_path``, of paths that the executors can open. A row group without statistics gets null
    bounds, so it is unusable and is always kept. n_rows is the number of rows without null; where several columns hold
    nulls it is the least that it can be, which proves no skip too many, and count_is_exact is false.
    """
    coords = list(coords)
    ends = ", ".join(f"lo_{i} double, hi_{i} double" for i in range(len(coords)))

    def job(batches):
        import pyarrow.fs as pafs
        import pyarrow.parquet as pq

        for b in batches:
            rows = []
            for path in b.column(0).to_pylist():
                if "://" in path and not path.startswith("file://"):
                    fs, inner = pafs.FileSystem.from_uri(path)
                else:
                    fs, inner = pafs.LocalFileSystem(), path.removeprefix("file://").replace("file:", "")
                with fs.open_input_file(inner) as f:
                    meta = pq.ParquetFile(f).metadata
                    for g in range(meta.num_row_groups):
                        group = meta.row_group(g)
                        by = {group.column(j).path_in_schema: group.column(j).statistics for j in range(group.num_columns)}
                        stats = [by.get(c) for c in coords]
                        good = [s is not None and s.has_min_max for s in stats]
                        nulls = [s.null_count if s is not None and s.has_null_count else 0 for s in stats]
                        exact = sum(n > 0 for n in nulls) <= 1
                        ranges = [float(v) if ok else None for s, ok in zip(stats, good, strict=True) for v in ((s.min, s.max) if ok else (None, None))]
                        rows.append((path, g, max(0, group.num_rows - sum(nulls)), exact, *ranges))
            names = ["file_path", "row_group", "n_rows", "count_is_exact", *[f"{e}_{i}" for i in range(len(coords)) for e in ("lo", "hi")]]
            types = [pa.string(), pa.int32(), pa.int64(), pa.bool_(), *[pa.float64()] * (2 * len(coords))]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(types)], names=names)

    return files.select("file_path").mapInArrow(job, f"file_path string, row_group int, n_rows long, count_is_exact boolean, {ends}")


def from_files(spark: SparkSession, paths: list[str], coords: Iterable[str], tasks: int = 200) -> DataFrame:
    """A manifest with one row a file (part_id is its path), from footers alone. ``paths`` is the listing that the reader
    itself holds on the driver. Writers that leave NaN out of statistics would have such rows counted: use from_rows for them."""
    coords = list(coords)
    files = spark.createDataFrame([(p,) for p in paths], "file_path string").repartition(max(1, min(tasks, len(paths))))
    groups = from_footers(spark, files, coords)
    ends = [F.when(F.count(c) == F.count(F.lit(1)), f(c)).alias(c) for i in range(len(coords)) for f, c in ((F.min, f"lo_{i}"), (F.max, f"hi_{i}"))]
    return groups.groupBy(F.col("file_path").alias("part_id")).agg(F.sum("n_rows").alias("n_rows"), *ends)
