"""Cutting lineage in the folder that the cluster shares."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder; a local one is set only where the session names none."""
    named, found = spark.conf.get("spark.checkpoint.dir", None), spark.sparkContext.getCheckpointDir()
    master = spark.sparkContext.master
    if not (named or found) and (not master.startswith("local") or master.startswith("local-cluster")):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not found:
        spark.sparkContext.setCheckpointDir(named or f"file://{tempfile.mkdtemp(prefix='lexfold-')}")
        found = spark.sparkContext.getCheckpointDir()
    return (named or found).rstrip("/")


def checkpointed(df: DataFrame) -> DataFrame:
    shared_dir(df.sparkSession)
    return df.checkpoint()


def written(df: DataFrame) -> DataFrame:
    """As checkpointed, in compressed files; for rows of long texts."""
    path = f"{shared_dir(df.sparkSession)}/written-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
