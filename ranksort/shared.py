"""The folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``, read from the session; only in local mode, where none is set, a temporary folder."""
    context = spark.sparkContext
    named = context.getConf().get("spark.checkpoint.dir") or context.getCheckpointDir()
    if not named:
        if not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        named = tempfile.mkdtemp(prefix="ranksort-")
        context.setCheckpointDir(named)
    return named.rstrip("/")


def scratch(spark: SparkSession, label: str) -> str:
    """A new folder name under the shared root; nothing is created."""
    return f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"


def keep(df: DataFrame) -> DataFrame:
    """Checkpoint: cuts the lineage, survives lost executors, and leaves rows in their partitions and order."""
    shared_root(df.sparkSession)
    return df.checkpoint()
