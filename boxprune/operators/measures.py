"""Cost and accuracy measures of kept pairs and of joins."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxprune.functions.dominance import dominates, witness
from boxprune.functions.geometry import Box, contains, dist_sq
from boxprune.plans.prune import _named, same


def pruning(pairs: DataFrame, origins: DataFrame, train: DataFrame, rule: str, k: int) -> DataFrame:
    """One row: kept and total pairs, train rows read over all origins, distance evaluations."""
    met = pairs.select("origin_id", "part_id").join(origins.select(F.col("part_id").alias("o_id"), F.col("n_rows").alias("n_o")), same("origin_id", "o_id")).join(train.select(F.col("part_id").alias("b_id"), F.col("n_rows").alias("n_b")), same("part_id", "b_id"))
    kept = met.agg(F.count(F.lit(1)).alias("kept_pairs"), F.coalesce(F.sum("n_b"), F.lit(0)).alias("rows_read"), F.coalesce(F.sum(F.col("n_o") * F.col("n_b")), F.lit(0)).alias("distance_evals"))
    total = origins.agg(F.count(F.lit(1)).alias("a")).crossJoin(train.agg(F.count(F.lit(1)).alias("b"))).select((F.col("a") * F.col("b")).alias("total_pairs"))
    return kept.crossJoin(total).select(F.lit(rule).alias("rule"), F.lit(k).alias("k"), "kept_pairs", "total_pairs", "rows_read", "distance_evals")


def rule_matrix(by_rule: dict[str, DataFrame]) -> DataFrame:
    """For each two rules, the pairs that both keep, only the first, only the second."""
    keys = ["origin_id", "part_id"]
    marked = reduce(lambda a, b: a.unionByName(b), [df.select(*keys, F.lit(name).alias("rule")) for name, df in by_rule.items()])
    flags = marked.groupBy(*keys).agg(*[F.bool_or(F.col("rule") == name).alias(name) for name in by_rule])
    names = list(by_rule)
    rows = F.array(*[F.struct(F.lit(a).alias("rule_a"), F.lit(b).alias("rule_b"), F.col(a).alias("in_a"), F.col(b).alias("in_b")) for i, a in enumerate(names) for b in names[i + 1 :]])
    each = flags.select(F.explode(rows).alias("r")).select("r.*")
    return each.groupBy("rule_a", "rule_b").agg(F.count_if(F.col("in_a") & F.col("in_b")).alias("both"), F.count_if(F.col("in_a") & ~F.col("in_b")).alias("only_a"), F.count_if(~F.col("in_a") & F.col("in_b")).alias("only_b"))


def recall(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Rows of the truth, rows also found at the same rank, mismatches."""
    hit = truth.select("origin_id", "rank", F.col("neighbour_id").alias("want")).join(found.select("origin_id", "rank", F.col("neighbour_id").alias("got")), ["origin_id", "rank"], "full")
    return hit.agg(F.count("want").alias("n_true"), F.count_if(F.col("want") == F.col("got")).alias("n_found"), F.count_if(~F.col("want").eqNullSafe(F.col("got"))).alias("mismatches"))


def needed_pairs(neighbours: DataFrame, r: DataFrame, s: DataFrame) -> DataFrame:
    """Pairs of partitions that contribute a neighbour."""
    a = r.select(F.col("id").alias("r_id"), F.col("part_id").alias("o"))
    b = s.select(F.col("id").alias("s_id"), "part_id")
    met = neighbours.join(a, F.col("origin_id") == F.col("r_id")).join(b, F.col("neighbour_id") == F.col("s_id"))
    return met.select(F.col("o").alias("origin_id"), "part_id").distinct()


def witness_failures(origins: DataFrame, train: DataFrame, dims: int) -> DataFrame:
    """Triples that are not dominated, and those whose witness points are not inside their boxes or prove nothing."""
    o, e, b = (Box.of(p, dims) for p in ("o_", "e_", "b_"))
    met = _named(origins, "o_", dims).crossJoin(_named(train, "e_", dims)).crossJoin(_named(train, "b_", dims)).where(~dominates(o, e, b))
    at, near, far = witness(o, e, b)
    good = contains(o, at) & contains(e, near) & contains(b, far) & (dist_sq(at, near) >= dist_sq(at, far))
    return met.agg(F.count(F.lit(1)).alias("not_dominated"), F.count_if(~good).alias("failures"))
