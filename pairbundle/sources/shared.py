"""Storage that the driver and all executors can reach."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The folder in ``spark.checkpoint.dir``; where it is unset (tests on one machine), a temporary folder that is then set."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = held.get() if held.isDefined() else None
    if not root:
        root = "file://" + tempfile.mkdtemp(prefix="pairbundle-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def shared_path(spark: SparkSession, label: str) -> str:
    """A fresh path under the shared folder."""
    return f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"


def staged(df: DataFrame, label: str, narrow: bool = False) -> DataFrame:
    """Write a table to the shared folder and read it again: cuts lineage and survives the loss of executors.

    ``narrow`` is for tables of a few columns that come out of a shuffle: tasks then write few files, some for each core of the
    cluster, instead of one for each shuffle partition."""
    spark = df.sparkSession
    path = shared_path(spark, label)
    out = df.coalesce(3 * spark.sparkContext.defaultParallelism) if narrow else df
    out.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
