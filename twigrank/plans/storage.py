"""Shared storage for indexes, frontiers and cut lineage."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors reach: spark.checkpoint.dir, or one of ours where it is unset and all runs in one process (tests)."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors reach")
        folder = tempfile.mkdtemp(prefix="twigrank-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder


def stored(df: DataFrame, *partition_by: str) -> DataFrame:
    """df written as Parquet in the shared folder and read back; survives lost executors and ends the lineage."""
    path = f"{shared_dir(df.sparkSession)}/stored-{uuid.uuid4().hex}"
    writer = df.write.partitionBy(*partition_by) if partition_by else df.write
    writer.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def rows_at_most(df: DataFrame, limit: int) -> bool:
    """Whether df has at most `limit` rows; reads no more than it needs to tell."""
    return df.limit(limit + 1).count() <= limit
