"""Scratch folders that the driver and all executors share."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder below ``spark.checkpoint.dir``; a local session without that setting gets a temporary one."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = tempfile.gettempdir()
    return os.path.join(base, f"{name}-{uuid.uuid4().hex}")


def materialise(df: DataFrame, name: str) -> DataFrame:
    """``df`` written as Parquet and reread: the lineage is cut, and lost executors cost nothing of what stands before."""
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def stands(df: DataFrame) -> bool:
    """Whether what ``materialise`` wrote for ``df`` is still there."""
    spark = df.sparkSession
    at = spark._jvm.org.apache.hadoop.fs.Path(df._scratch)
    return bool(at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at))
