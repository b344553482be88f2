"""Integration in time: as-of and bucket joins, counts over a previous span."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_attach(facts: DataFrame, readings: DataFrame, by, ts: str, values, tolerance: int, tie: str | None = None) -> DataFrame:
    """Each fact with the latest reading of the same ``by`` at or before its time, not older
    than ``tolerance`` seconds (``ts`` is epoch seconds on both sides; equal times: the reading
    with the largest ``tie``). Unmatched facts keep nulls. Columns reading_<v> and reading_ts.

    Both sides are tagged and put into buckets of the tolerance's length; readings go to their
    own bucket and the next, so a bucket holds all that its facts can see and no site is one group."""
    width = max(int(tolerance), 1)
    bucket = F.floor(F.col(ts) / width).cast("long")
    value = F.struct(F.col(ts).alias("ts"), *(F.col(v).alias(v) for v in values))
    sent = readings.select(*by, F.explode(F.array(bucket, bucket + 1)).alias("_bucket"), F.col(ts).alias("_ts"), F.lit(0).alias("_fact"), F.col(tie or ts).alias("_tie"), value.alias("_value"))
    names = facts.columns
    asked = facts.select(*by, bucket.alias("_bucket"), F.col(ts).alias("_ts"), F.lit(1).alias("_fact"), F.struct(*names).alias("_row"))
    both = sent.unionByName(asked, allowMissingColumns=True)
    order = Window.partitionBy(*by, "_bucket").orderBy("_ts", "_fact", "_tie").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    last = F.last("_value", ignorenulls=True).over(order)
    got = both.withColumn("_last", last).where("_fact = 1")
    near = F.when(F.col("_ts") - F.col("_last.ts") <= tolerance, F.col("_last"))
    got = got.select("_row", near.alias("_last"))
    return got.select("_row.*", F.col("_last.ts").alias("reading_ts"), *(F.col(f"_last.{v}").alias(f"reading_{v}") for v in values))


def bucket_attach(facts: DataFrame, readings: DataFrame, by, ts: str, values, unit: int = 3600) -> DataFrame:
    """Each fact with the mean of each value over the readings of the same ``by`` and time bucket."""
    bucket = F.floor(F.col(ts) / unit).cast("long")
    means = readings.groupBy(*by, bucket.alias("bucket")).agg(*(F.avg(v).alias(f"mean_{v}") for v in values), F.count("*").alias("readings"))
    return facts.withColumn("bucket", bucket).join(means, [*by, "bucket"], "left")


def interval_pairs(facts: DataFrame, readings: DataFrame, by, ts: str, fact_id: str, reading_id: str, before: int) -> DataFrame:
    """All pairs of a fact and a reading of the same ``by`` with 0 <= fact time - reading time <=
    ``before``: an equi-join on buckets and an exact check."""
    width = max(before, 1)
    bucket = F.floor(F.col(ts) / width).cast("long")
    left = facts.select(*by, fact_id, F.col(ts).alias("f_ts"), F.explode(F.array(bucket, bucket - 1)).alias("_bucket"))
    right = readings.select(*by, reading_id, F.col(ts).alias("r_ts"), bucket.alias("_bucket"))
    return left.join(right, [*by, "_bucket"]).where((F.col("f_ts") >= F.col("r_ts")) & (F.col("f_ts") - F.col("r_ts") <= before)).drop("_bucket")


def prior_count(by, ts: str, seconds: int = 3600) -> Column:
    """Rows of the same ``by`` in [ts - seconds, ts - 1] (epoch seconds; the row itself is out)."""
    return F.count("*").over(Window.partitionBy(*by).orderBy(ts).rangeBetween(-seconds, -1))


def prior_count_bucketed(df: DataFrame, by, ts: str, name: str, seconds: int = 3600) -> DataFrame:
    """The same count where one key may hold a third of all rows: windows run over (key, time
    bucket) with the rows of the bucket before sent along."""
    bucket = F.floor(F.col(ts) / seconds).cast("long")
    own = df.withColumn("_bucket", bucket).withColumn("_own", F.lit(1))
    sent = df.withColumn("_bucket", bucket + 1).withColumn("_own", F.lit(0))
    count = F.count("*").over(Window.partitionBy(*by, "_bucket").orderBy(ts).rangeBetween(-seconds, -1))
    return own.unionByName(sent).withColumn(name, count).where("_own = 1").drop("_own", "_bucket")
