"""Loading of tables, declared schemas, sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

#: Declared schemas of text sources (no inference).
READINGS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def register(spark: SparkSession, folder: str, names=TABLES) -> None:
    """The tables as temporary views of the same names."""
    for name in names:
        table(spark, folder, name).createOrReplaceTempView(name)


def read_as(spark: SparkSession, kind: str, path: str, schema: str, **options) -> DataFrame:
    """CSV, JSON, ORC or Parquet with a declared schema."""
    return spark.read.format(kind).schema(schema).options(**options).load(path)


def read_jdbc(spark: SparkSession, url: str, name: str, column: str, low: int, high: int, parts: int, **options) -> DataFrame:
    """A database table read in ranges of a numeric column."""
    return spark.read.format("jdbc").options(url=url, dbtable=name, partitionColumn=column, lowerBound=str(low), upperBound=str(high), numPartitions=str(parts), **options).load()


def write_partitioned(df: DataFrame, path: str, by, sort=()) -> None:
    """Parquet in folders by low-cardinality columns, sorted inside files for min/max skipping."""
    out = df.repartition(*by) if by else df
    (out.sortWithinPartitions(*by, *sort) if sort else out).write.mode("overwrite").partitionBy(*by).parquet(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, by, sort=()) -> None:
    """A table bucketed by join keys: later joins and group-bys on them need no exchange."""
    writer = df.write.mode("overwrite").bucketBy(buckets, *by)
    (writer.sortBy(*sort) if sort else writer).saveAsTable(name)
