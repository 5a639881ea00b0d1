"""Folders for tables between steps: below spark.checkpoint.dir, deleted when the driver's JVM ends."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def file_system(spark: SparkSession, path: str):
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def folder(spark: SparkSession, prefix: str = "engine") -> str:
    """A new folder that driver and executors share; a local one only for a local master without that setting."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = tempfile.gettempdir() + "/halo-scratch"
    path = f"{base.rstrip('/')}/{prefix}-{uuid.uuid4().hex}"
    fs, where = file_system(spark, path)
    fs.mkdirs(where)
    fs.deleteOnExit(where)
    return path


def remove(spark: SparkSession, path: str) -> None:
    fs, where = file_system(spark, path)
    fs.delete(where, True)


def stash(df: DataFrame, path: str) -> DataFrame:
    """Written and read again: a cut of the lineage that outlives executors."""
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
