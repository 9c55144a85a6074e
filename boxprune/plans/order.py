"""The partial order of train boxes seen from an origin: edges, reduction, load order, waves."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from boxprune.functions.dominance import dominates
from boxprune.functions.geometry import Box, center, clearance_sq
from boxprune.plans.prune import _named


def edges(origins: DataFrame, train: DataFrame, dims: int) -> DataFrame:
    """(origin_id, near_id, far_id) for each dominated pair; for small manifests."""
    o, e, b = (Box.of(p, dims) for p in ("o_", "e_", "b_"))
    hit = _named(origins, "o_", dims).crossJoin(_named(train, "e_", dims)).join(_named(train, "b_", dims), dominates(o, e, b))
    return hit.select(F.col("o_id").alias("origin_id"), F.col("e_id").alias("near_id"), F.col("b_id").alias("far_id"))


def cover_edges(dag: DataFrame) -> DataFrame:
    """Edges that no two-step path implies."""
    a = dag.select("origin_id", "near_id", F.col("far_id").alias("mid"))
    b = dag.select("origin_id", F.col("near_id").alias("mid"), "far_id")
    return dag.join(a.join(b, ["origin_id", "mid"]).select("origin_id", "near_id", "far_id").distinct(), ["origin_id", "near_id", "far_id"], "left_anti")


def load_order(pairs: DataFrame, origins: DataFrame, train: DataFrame, dims: int) -> DataFrame:
    """A linear extension without the graph: by clearance from the origin's centre. A dominated box is farther from
    every point of the origin, so also from that one."""
    met = pairs.select(F.col("origin_id").alias("o_id"), F.col("part_id").alias("b_id")).join(_named(origins, "o_", dims), "o_id").join(_named(train, "b_", dims), "b_id")
    gap = clearance_sq(center(Box.of("o_", dims)), Box.of("b_", dims))
    rank = F.row_number().over(Window.partitionBy("o_id").orderBy("centre_gap", "b_id"))
    return met.withColumn("centre_gap", gap).select(F.col("o_id").alias("origin_id"), F.col("b_id").alias("part_id"), rank.alias("load_rank"))


def waves(nodes: DataFrame, dag: DataFrame) -> DataFrame:
    """(origin_id, part_id, wave): the longest chain that ends at each box. Rounds are as many as the longest chain."""
    from boxprune.sources.scratch import stored

    todo, done, wave = stored(nodes.select("origin_id", "part_id").distinct()), None, 0
    dag = stored(dag)
    while todo.limit(1).count():
        open_ = dag.join(todo.select("origin_id", F.col("part_id").alias("near_id")), ["origin_id", "near_id"], "left_semi").select("origin_id", F.col("far_id").alias("part_id")).distinct()
        now = todo.join(open_, ["origin_id", "part_id"], "left_anti").withColumn("wave", F.lit(wave))
        done = now if done is None else done.unionByName(now)
        done = stored(done)
        todo = stored(todo.join(open_, ["origin_id", "part_id"], "left_semi"))
        wave += 1
    return done if done is not None else todo.withColumn("wave", F.lit(0))


def violations(dag: DataFrame) -> DataFrame:
    """Counts of broken laws of a strict partial order; all are 0."""
    back = dag.select("origin_id", F.col("far_id").alias("near_id"), F.col("near_id").alias("far_id"))
    a = dag.select("origin_id", "near_id", F.col("far_id").alias("mid"))
    b = dag.select("origin_id", F.col("near_id").alias("mid"), "far_id")
    chained = a.join(b, ["origin_id", "mid"]).select("origin_id", "near_id", "far_id").distinct()
    keys = ["origin_id", "near_id", "far_id"]
    count = lambda df, law: df.agg(F.count(F.lit(1)).alias("violations")).select(F.lit(law).alias("law"), "violations")
    return count(dag.where("near_id = far_id"), "irreflexive").unionByName(count(dag.join(back, keys, "left_semi"), "asymmetric")).unionByName(count(chained.join(dag, keys, "left_anti"), "transitive"))
