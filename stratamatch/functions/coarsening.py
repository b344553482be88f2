"""Coarsening of covariates into bucket codes beside the original values."""

from __future__ import annotations

from math import ceil, log2

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def cut(column: Column, points) -> Column:
    """1 + number of cut points at or below the value; null values go to bucket 0."""
    points = list(points)
    if any(b <= a for a, b in zip(points, points[1:])):
        raise ValueError("cut points must rise")
    out = F.when(column.isNull(), 0)
    for i, p in enumerate(points):
        out = out.when(column < p, i + 1)
    return out.otherwise(len(points) + 1)


def equal_width(column: Column, k: int, low: float, high: float) -> Column:
    """k buckets of equal width over [low, high]; values outside go to the end buckets."""
    if k < 1 or high <= low:
        raise ValueError("need k >= 1 and low < high")
    at = F.floor((column - low) * k / (high - low)).cast("int") + 1
    return F.when(column.isNull(), 0).otherwise(F.greatest(F.lit(1), F.least(F.lit(k), at)))


def width_bucket(column: Column, width: int) -> Column:
    """floor(value / width)."""
    return F.floor(column / width).cast("int")


def rounded(column: Column, digits: int) -> Column:
    return F.round(column, digits)


def week(column: Column) -> Column:
    """Monday of the week as a date."""
    return F.date_trunc("week", column).cast("date")


def equal_frequency(df: DataFrame, name: str, k: int) -> list:
    """k - 1 cut points that split the rows evenly (exact quantiles from distributed ranks). Action."""
    from ..operators.ranking import exact_quantiles

    got = exact_quantiles(df, name, [i / k for i in range(1, k)])
    return sorted({x for x in got if x is not None})


def histogram_cuts(df: DataFrame, name: str, rule: str = "sturges") -> list[float]:
    """Equal-width cut points whose number follows a histogram rule: sturges, scott or fd."""
    n, low, high, sd = df.agg(F.count(name), F.min(name), F.max(name), F.stddev_samp(name)).first()
    if not n or low == high:
        return []
    if rule == "sturges":
        k = ceil(log2(n)) + 1
    elif rule in ("scott", "fd"):
        from ..operators.ranking import exact_quantiles

        if rule == "fd":
            q = exact_quantiles(df, name, (0.25, 0.75))
        width = 3.49 * sd / n ** (1 / 3) if rule == "scott" else 2 * (q[1] - q[0]) / n ** (1 / 3)
        k = max(1, ceil((high - low) / width)) if width > 0 else 1
    else:
        raise ValueError(rule)
    return [low + (high - low) * i / k for i in range(1, k)]
