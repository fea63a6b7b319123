"""Tables in the shared folder: lineage cuts and saved indexes."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """A fresh path below spark.checkpoint.dir; a folder of our own only where that is unset, as in tests."""
    base = spark.conf.get("spark.checkpoint.dir", None) or "/tmp/checkpoints"
    return f"{base.rstrip('/')}/thriftvec-{uuid.uuid4().hex}"


def stored(df: DataFrame) -> DataFrame:
    """Write once, read back: later stages survive lost executors and don't recompute."""
    path = shared_folder(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
