"""Tables that a driver loop reads again: written where all executors see them, so that no step computes the last one anew."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def work_folder(spark: SparkSession, name: str) -> str:
    """A new folder name that the driver and all executors share; a temporary one only where all are this machine."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    root = root or "file://" + os.path.join(tempfile.gettempdir(), "episodic-work")
    return f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def level_store(df: DataFrame, name: str) -> DataFrame:
    """df written to the folder in spark.checkpoint.dir and read back; where none is set (tests), kept in memory and disk."""
    spark = df.sparkSession
    if not spark.sparkContext.getConf().get("spark.checkpoint.dir"):
        return df.persist()
    path = work_folder(spark, f"level-{name}")
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
