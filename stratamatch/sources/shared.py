"""Tables in the folder that all executors share: they cut lineage and survive lost executors."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid
from contextlib import contextmanager
from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession

FREED = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; only a local session without it gets a folder of its own."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    # Only a local session lacks the setting; a cluster names its folder.
    if not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return _own_folder(spark.sparkContext.applicationId)


@lru_cache(None)
def _own_folder(application: str) -> str:
    return "file://" + tempfile.mkdtemp(prefix=f"stratamatch-{application}-")


def new_folder(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder, removed when the driver ends."""
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    atexit.register(_remove, spark, path)
    return path


@contextmanager
def freed_shuffles(spark: SparkSession):
    """Shuffle files of what runs inside go when it ends; else they stay until the driver collects its garbage."""
    before = spark.conf.get(FREED, "false")
    spark.conf.set(FREED, "true")
    try:
        yield
    finally:
        spark.conf.set(FREED, before)


def materialized(df: DataFrame, name: str, free: bool = False) -> DataFrame:
    """Write ``df`` once as Parquet and read it back: later uses do not compute it again. ``free``: the
    shuffle files of its making go at once."""
    path = new_folder(df.sparkSession, name)
    if free:
        with freed_shuffles(df.sparkSession):
            df.write.parquet(path)
    else:
        df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextmanager
def passing(df: DataFrame, name: str):
    """``df`` as a written table for one later write: its shuffles go at once, its files when the block ends."""
    path = new_folder(df.sparkSession, name)
    try:
        with freed_shuffles(df.sparkSession):
            df.write.parquet(path)
        yield df.sparkSession.read.schema(df.schema).parquet(path)
    finally:
        _remove(df.sparkSession, path)


def _remove(spark: SparkSession, path: str) -> None:
    try:
        target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # noqa: BLE001  the session has ended before; the folder's owner cleans it
        pass
