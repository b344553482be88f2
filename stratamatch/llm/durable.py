"""Tables in the shared folder, which cut lineage and survive lost executors."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..sources.shared import materialized, new_folder

__all__ = ["new_folder", "slices", "stored"]

#: Write a table once and read it back: later uses do not compute it again.
stored = materialized


def slices(df: DataFrame) -> int:
    """How many parts to deal work into: it grows with the scan and the session's setting."""
    spark = df.sparkSession
    scan = df._jdf.queryExecution().toRdd().getNumPartitions()
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * scan, 1)
