"""Site-relative line removal with DataFrame functions only.

For each host, the number of its pages that hold a line is divided by the host's page total; a line
on more than ``ratio`` of the pages, and on at least ``min_pages`` of them, is boilerplate and is
dropped wherever it occurs on that host. ``large`` adds a second (ratio, min_pages) for hosts with many
pages, where a lower share is evidence enough; a line that meets either is dropped. Lines are compared as written; lines without a
non-blank character are never counted and never dropped. Texts are otherwise unchanged.

Null text stays null, empty text stays empty, a null host is a host of its own, repeated rows count
as pages of their own, an empty table gives an empty result, further columns pass through.
"""

from __future__ import annotations

from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from boxprune.llm.shared import stored

RATIO = 0.3
MIN_PAGES = 3

#: Second rule of the pipeline. On hosts of 500 pages or more the shares of the given tables leave a gap between 0.05
#: (common sentences) and 0.08 (the line that stands on every tenth page); on hosts of 50, ten pages are a share of 0.2.
LARGE = (0.05, 10)

#: Boilerplate lines that may be broadcast (20 bytes each); beyond, documents are joined by a shuffle.
BROADCAST_LINES = 400_000


def _worded(line: Column) -> Column:
    return line.rlike("[^ \\t\\n\\x0B\\f\\r]")


def _line_key(line: Column) -> Column:
    """96 bits of digest and the length stand for a line."""
    return F.struct(F.xxhash64(line).alias("h1"), F.hash(line).alias("h2"), F.length(line).alias("len"))


def boilerplate(docs: DataFrame, text_col: str = "text", host_col: str = "source", ratio: float = RATIO, min_pages: int = MIN_PAGES, large: tuple[float, int] | None = None) -> DataFrame:
    """host, key, line_pages, host_pages of each boilerplate line.

    Counts are summed before the shuffle, so a line or host on every page costs a row a task.
    """
    rules = [(ratio, min_pages), *([large] if large else [])]
    enough = [(F.col("line_pages") >= m) & (F.col("line_pages") > F.lit(r) * F.col("host_pages")) for r, m in rules]
    pages = docs.groupBy(F.col(host_col).alias("page_host")).agg(F.count(F.lit(1)).alias("host_pages"))
    lines = docs.select(F.col(host_col).alias("host"), F.explode(F.array_distinct(F.split(F.col(text_col), "\n"))).alias("line"))
    counted = (
        lines.where(_worded(F.col("line"))).select("host", _line_key(F.col("line")).alias("key"))
        .groupBy("host", "key").agg(F.count(F.lit(1)).alias("line_pages")).where(F.col("line_pages") >= min(m for _, m in rules))
    )
    return (
        counted.join(pages, F.col("host").eqNullSafe(F.col("page_host")))
        .where(reduce(or_, enough))
        .select("host", "key", "line_pages", "host_pages")
    )


def drop_boilerplate(docs: DataFrame, text_col: str = "text", host_col: str = "source", ratio: float = RATIO, min_pages: int = MIN_PAGES, counts: bool = False, large: tuple[float, int] | None = None) -> DataFrame:
    """The documents with boilerplate lines removed; with ``counts`` also n_lines and n_dropped.

    A host has at most (lines a page) / (smallest ratio) boilerplate lines, so its list is short however many
    pages it has.
    """
    bad = stored(boilerplate(docs, text_col, host_col, ratio, min_pages, large))
    few = bad.count() <= BROADCAST_LINES
    by_host = bad.groupBy(F.col("host").alias("__boxprune_host")).agg(F.collect_list("key").alias("__boxprune_bad"))
    if few:
        by_host = F.broadcast(by_host)
    lines = F.split(F.col(text_col), "\n")
    kept = F.filter(lines, lambda x: ~F.array_contains(F.col("__boxprune_bad"), _line_key(x)) | ~_worded(x))
    out = docs.join(by_host, F.col(host_col).eqNullSafe(F.col("__boxprune_host")), "left")
    out = out.withColumn("__boxprune_kept", F.when(F.col("__boxprune_bad").isNotNull(), kept))
    text = F.when(F.col("__boxprune_kept").isNull(), F.col(text_col)).otherwise(F.array_join("__boxprune_kept", "\n"))
    total = F.coalesce(F.size(lines), F.lit(0))
    extra = [F.when(F.col(text_col).isNull(), 0).otherwise(total).cast("long").alias("n_lines"), F.when(F.col("__boxprune_kept").isNull(), 0).otherwise(total - F.size("__boxprune_kept")).cast("long").alias("n_dropped")] if counts else []
    return out.select(*[text.alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns], *extra)
