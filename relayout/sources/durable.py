"""Intermediate tables that survive a lost executor: written to the folder that the cluster shares."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame


def durable(df: DataFrame, label: str = "step") -> DataFrame:
    spark = df.sparkSession
    root = spark.conf.get("spark.checkpoint.dir", None) or getattr(spark, "_relayout_durable", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        root = spark._relayout_durable = tempfile.mkdtemp(prefix="relayout-")
    path = f"{root}/relayout-{spark.sparkContext.applicationId}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._relayout_path = path
    return out


def drop(*written: DataFrame) -> None:
    """Deletes what durable() wrote, once nothing reads it any more."""
    for df in written:
        spark = df.sparkSession
        at = spark._jvm.org.apache.hadoop.fs.Path(df._relayout_path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
