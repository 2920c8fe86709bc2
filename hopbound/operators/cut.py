"""Lineage cuts: tables in the cluster's shared folder."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        found = tempfile.mkdtemp(prefix="hopbound-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


_WRITTEN: list[str] = []


def cut(df: DataFrame) -> DataFrame:
    """df written once as Parquet and read back. See clean()."""
    path = f"{shared_dir(df.sparkSession)}/layer-{uuid.uuid4().hex}"
    _WRITTEN.append(path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def is_empty(df: DataFrame) -> bool:
    return not df.take(1)


def clean(spark: SparkSession) -> None:
    """Delete the tables that cut() has made so far; frames that still read them are then of no use."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    while _WRITTEN:
        at = path(_WRITTEN.pop())
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
