"""Tables that cut lineage, in the folder that driver and executors share."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir. Where none is set, a temporary one in local mode; on a cluster that is an error,
    as every machine would write to a disk of its own."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="boxprune-")
        spark.sparkContext.setCheckpointDir(root)
    return root


def stored(df: DataFrame, *more: DataFrame) -> DataFrame:
    """Write a frame, or several one after the other, as a table in the shared folder and read it back.

    This cuts the lineage, survives the loss of executors, and gives the optimizer the true size,
    so that joins with it are broadcast only under the session's own threshold.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/stored-{uuid.uuid4().hex}"
    df.write.parquet(path)
    for one in more:
        release(spark)
        one.write.mode("append").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._stored_at = path
    return out


def release(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of finished steps, which hold until the driver collects garbage."""
    for _ in range(2):  # the first frees what holds the shuffles
        gc.collect()
        spark.sparkContext._jvm.System.gc()


def discard(*frames: DataFrame) -> None:
    """Delete stored tables that no later step reads."""
    for df in frames:
        spark = df.sparkSession
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(df._stored_at)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
