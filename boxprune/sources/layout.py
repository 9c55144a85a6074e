"""Ways to deal points to partitions, and a writer of partitioned layouts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Cells an axis in a grid's partition number.
GRID_STRIDE = 1000


def cell(x: Column, width: float) -> Column:
    return F.floor(x / F.lit(float(width))).cast("bigint")


def grid(coords: list[Column], width: float) -> Column:
    """One number for the cells of all axes; axes may be negative."""
    number = cell(coords[0], width)
    for x in coords[1:]:
        number = number * GRID_STRIDE + cell(x, width)
    return number


def zorder(coords: list[Column], width: float, bits: int = 10) -> Column:
    """Bit-interleaved cells of non-negative axes."""
    cells = [cell(x, width) for x in coords]
    terms = [F.shiftleft(F.shiftright(c, b).bitwiseAND(1), b * len(cells) + i) for b in range(bits) for i, c in enumerate(cells)]
    out = terms[0]
    for t in terms[1:]:
        out = out.bitwiseOR(t)
    return out


def range_tiles(points: DataFrame, dims: int, per_axis: int, error: float = 0.001) -> DataFrame:
    """part_id from approximate quantiles of every axis; no global sort."""
    cuts = points.approxQuantile([f"x_{i}" for i in range(dims)], [j / per_axis for j in range(1, per_axis)], error)
    number = F.lit(0).cast("bigint")
    for i, axis in enumerate(cuts):
        tile = sum((F.when(F.col(f"x_{i}") >= F.lit(c), 1).otherwise(0) for c in axis), F.lit(0))
        number = number * per_axis + tile
    return points.withColumn("part_id", number)


def write_layout(points: DataFrame, path: str, partitions: int, sort_by: list[str]) -> None:
    """Range-partitioned, sorted files under one directory a part_id, for dynamic partition pruning."""
    points.repartitionByRange(partitions, "part_id").sortWithinPartitions("part_id", *sort_by).write.partitionBy("part_id").parquet(path)
