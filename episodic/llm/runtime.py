"""Where intermediate tables live, and small helpers that every operator shares."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_WRITTEN: dict[str, SparkSession] = {}


def shared_folder(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir; where it is unset (tests on one machine) a temporary one."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return "file://" + os.path.join(tempfile.gettempdir(), "episodic-shared")


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: lineage ends here and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if not _WRITTEN:  # once, and after the session's own
        atexit.unregister(_sweep)
        atexit.register(_sweep)
    _WRITTEN[path] = spark
    return spark.read.schema(df.schema).parquet(path)


@contextmanager
def passing(*keep: str) -> Iterator[None]:
    """Deletes on leaving what is materialized inside, but for tables of the names in `keep`.

    For steps whose results are written themselves: a plan that leaves may read kept tables only. Without it, the
    intermediates of all steps of a long session would stay on disk side by side.
    """
    before = set(_WRITTEN)
    try:
        yield
    finally:
        for path in [p for p in _WRITTEN if p not in before]:
            if path.rpartition("/")[2].rpartition("-")[0] not in keep:
                _delete(_WRITTEN.pop(path), path)


def _delete(spark: SparkSession, path: str) -> None:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def _sweep() -> None:
    """Delete what this process has materialized and not yet deleted, at its end: results are lazy."""
    for path, spark in _WRITTEN.items():
        try:
            _delete(spark, path)
        except Exception:  # the session may be gone by then
            return
