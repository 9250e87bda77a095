"""Scratch tables in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch_path(spark: SparkSession, label: str) -> str:
    sc = spark.sparkContext
    root = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not root:  # on one machine, as in tests
        root = "file://" + tempfile.mkdtemp(prefix="balcut-")
        sc.setCheckpointDir(root)
    return f"{root.rstrip('/')}/balcut-graph/{sc.applicationId}/{label}-{uuid.uuid4().hex}"


def settled(df: DataFrame, label: str = "table") -> DataFrame:
    """Write and reread: cuts the lineage of loops and survives lost executors."""
    path = scratch_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
