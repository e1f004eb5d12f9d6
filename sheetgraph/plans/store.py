"""Intermediate tables in the folder that driver and executors share: they cut lineage and plan size."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """Under spark.checkpoint.dir; the local temp folder only where the session has none, as in tests."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = "file://" + os.path.join(tempfile.gettempdir(), "sheetgraph-checkpoints")
    return f"{base.rstrip('/')}/sheetgraph/plan-{uuid.uuid4().hex[:12]}"


def keep(df: DataFrame) -> DataFrame:
    """The rows as a parquet table in the shared folder."""
    path = shared_folder(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
