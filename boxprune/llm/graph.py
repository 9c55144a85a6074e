"""Connected components of an edge frame, by label propagation with pointer jumping on stored tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxprune.llm.shared import stored


def components(edges: DataFrame) -> DataFrame:
    """node, comp (the smallest node reachable) for every node of edges (a long, b long), a stored frame that each round reads.

    Every round takes the least label among neighbours and then the label of that label, so the
    number of rounds grows with the logarithm of a component's width. It ends when both ends of every edge have one label.
    No component is gathered: a hub's neighbours are reduced before the shuffle.
    """
    edges = edges.select("a", "b")
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    labels = stored(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("comp")))
    while True:
        ends = edges.join(labels.select(F.col("node").alias("a"), F.col("comp").alias("ca")), "a").join(labels.select(F.col("node").alias("b"), F.col("comp").alias("cb")), "b")
        if ends.where("ca <> cb").isEmpty():
            return labels
        seen = both.join(labels.select(F.col("node").alias("b"), "comp"), "b").groupBy("a").agg(F.min("comp").alias("near"))
        near = labels.join(seen, F.col("node") == F.col("a")).select("node", F.least("comp", "near").alias("near"))
        jump = labels.select(F.col("node").alias("near"), F.col("comp").alias("far"))
        labels = stored(near.join(jump, "near").select("node", F.least("near", "far").alias("comp")))
