"""Table functions over manifests."""

from __future__ import annotations

from pyspark.sql import SparkSession


def register_prune(spark: SparkSession) -> None:
    """prune_partitions(TABLE(t) PARTITION BY o_id, k): kept (origin_id, part_id, dominator_rows) of one origin's train boxes.

    The table has o_id, b_id, b_n and the two-dimensional bounds of both sides; a partition is one origin's survivors.
    """
    from pyspark.sql.functions import udtf

    @udtf(returnType="origin_id bigint, part_id bigint, dominator_rows bigint")
    class PrunePartitions:
        def __init__(self):
            self.rows, self.k = [], 1

        def eval(self, row, k: int):
            self.rows.append(row.asDict())
            self.k = k

        def terminate(self):
            import numpy as np

            from boxprune.functions.dominance import score_block

            if not self.rows:
                return
            box = lambda r, p: [[r[f"{p}_{e}_{i}"] for i in range(2)] for e in ("lo", "hi")]
            near = np.array([box(r, "b") for r in self.rows], float)
            score = score_block(np.array(box(self.rows[0], "o"), float), near, near)
            mass = ((score > 0) * np.array([r["b_n"] for r in self.rows])[:, None]).sum(axis=0)
            for r, m in zip(self.rows, mass.tolist(), strict=True):
                if m < self.k:
                    yield r["o_id"], r["b_id"], int(m)

    spark.udtf.register("prune_partitions", PrunePartitions)
