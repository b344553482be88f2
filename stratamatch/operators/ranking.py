"""Distributed ranks: ordered ranges with counts instead of one task for all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SAMPLE = 20_000


def range_cuts(df: DataFrame, order: list[str], ranges: int, sample: int = SAMPLE) -> list[tuple]:
    """Up to ``ranges`` - 1 cut points in lexicographic order of ``order``, from a bounded
    sample by hash; ranks do not depend on which cuts are found, only the evenness does."""
    if ranges <= 1:
        return []
    rows = sorted(tuple(r) for r in df.select(*order).orderBy(F.xxhash64(*order), *order).limit(sample).collect() if None not in tuple(r))
    return sorted({rows[len(rows) * i // ranges] for i in range(1, ranges)}) if rows else []


def range_of(order: list[str], cuts: list[tuple]) -> Column:
    """Number of cuts at or below the row: binary search in a literal array of structs."""
    if not cuts:
        return F.lit(0)
    bounds = F.array(*(F.struct(*(F.lit(v).alias(c) for c, v in zip(order, cut))) for cut in cuts))
    own = F.struct(*(F.col(c).alias(c) for c in order))
    steps = F.array(*(F.lit(2**i) for i in range(len(cuts).bit_length(), -1, -1)))
    return F.aggregate(steps, F.lit(0), lambda acc, s: F.when(F.get(bounds, acc + s - 1) <= own, acc + s).otherwise(acc))


def with_rank(df: DataFrame, order: list[str], name: str = "rank", ranges: int | None = None) -> DataFrame:
    """``df`` with the global rank (from 1) in ascending ``order``, which must be total. Rows are
    dealt to ordered ranges; a range's offset is the running sum of the range counts."""
    spark = df.sparkSession
    ranges = ranges or int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = df.withColumn("_range", range_of(order, range_cuts(df, order, ranges)))
    counts = dealt.groupBy("_range").agg(F.count("*").alias("_n"))
    offsets = counts.select("_range", (F.sum("_n").over(Window.orderBy("_range")) - F.col("_n")).alias("_before"))  # at most ``ranges`` rows
    inside = F.row_number().over(Window.partitionBy("_range").orderBy(*order))
    return dealt.withColumn("_inside", inside).join(F.broadcast(offsets), "_range").withColumn(name, F.col("_before") + F.col("_inside")).drop("_range", "_inside", "_before")


def exact_quantiles(df: DataFrame, name: str, points) -> list:
    """Quantiles by linear interpolation between neighbouring rows (None without rows). Ranks are
    distributed, and only the rows at the wanted ranks reach the driver. Action."""
    rows = df.select(F.col(name).alias("v")).where(F.col("v").isNotNull())
    n = rows.count()
    if not n:
        return [None for _ in points]
    at = [p * (n - 1) for p in points]
    ranks = sorted({int(x) + 1 for x in at} | {min(int(x) + 2, n) for x in at})
    values = {r["rank"]: r["v"] for r in with_rank(rows, ["v"]).where(F.col("rank").isin(ranks)).select("rank", "v").collect()}
    out = []
    for x in at:
        low, high = values[int(x) + 1], values[min(int(x) + 2, n)]
        out.append(low + (high - low) * (x - int(x)))
    return out
