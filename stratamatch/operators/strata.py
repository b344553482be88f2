"""Coarsened exact matching: strata of equal covariate codes that hold both arms.

Three plans with one result. ``groupby`` (default) adds up per stratum with partial
aggregation and joins the kept strata back; ``window`` computes the same over a
window, which sorts all rows; ``summarize`` never joins back, as effects and balance
need sums only. Keys are compared null-safely; a null code is a code.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.spec import UnitSpec, checked_treatment


def arm(treatment: str, value: int, column: str) -> Column:
    return F.when(F.col(treatment) == value, F.col(column))


def summarize(df: DataFrame, spec: UnitSpec) -> DataFrame:
    """Per stratum: keys, subclass (largest id), n, n1, n0, and for each outcome and measured
    covariate v: sum1_v, sum0_v. One aggregate over the rows with a defined treatment."""
    t = F.col(spec.treatment)
    sums = [F.sum(arm(spec.treatment, a, v)).alias(f"sum{a}_{v}") for v in dict.fromkeys((*spec.outcomes, *spec.measured)) for a in (1, 0)]
    return (
        checked_treatment(df, spec).groupBy(*spec.covariates)
        .agg(F.max(spec.id).alias("subclass"), F.count("*").alias("n"), F.count_if(t == 1).alias("n1"), F.count_if(t == 0).alias("n0"), *sums)
    )


def overlapping(summary: DataFrame) -> DataFrame:
    """Strata with both arms."""
    return summary.where("n1 > 0 and n0 > 0")


def cem(df: DataFrame, spec: UnitSpec, plan: str = "groupby") -> DataFrame:
    """The rows of ``df`` in strata with both arms, and their subclass (largest id of the stratum)."""
    rows = checked_treatment(df, spec)
    if plan == "window":
        w = Window.partitionBy(*spec.covariates)
        t = F.col(spec.treatment)
        out = rows.select("*", F.max(spec.id).over(w).alias("subclass"), F.min(t).over(w).alias("_low"), F.max(t).over(w).alias("_high"))
        return out.where("_low != _high").drop("_low", "_high")
    if plan != "groupby":
        raise ValueError(plan)
    return attach(rows, overlapping(summarize(df, UnitSpec(spec.id, spec.treatment, spec.covariates))), spec.covariates, {"subclass": "subclass"})


def attach(rows: DataFrame, strata: DataFrame, keys, columns: dict[str, str]) -> DataFrame:
    """Inner null-safe join of rows with one row per key; only ``columns`` (name: new name) come along."""
    side = strata.select(*(F.col(k).alias(f"_k{i}") for i, k in enumerate(keys)), *(F.col(a).alias(b) for a, b in columns.items()))
    if not keys:
        return rows.crossJoin(F.broadcast(side))  # one stratum, one row
    same = reduce(lambda a, b: a & b, (F.col(k).eqNullSafe(F.col(f"_k{i}")) for i, k in enumerate(keys)))
    return rows.join(side, same).drop(*(f"_k{i}" for i in range(len(keys))))


def exact_match(df: DataFrame, spec: UnitSpec) -> DataFrame:
    """Matching on original values: coarsening by identity."""
    return cem(df, spec)


def cem_shared(df: DataFrame, id_column: str, treatments, keys) -> DataFrame:
    """Strata of several treatments with the same covariates in one aggregate: treatment, subclass, n1, n0."""
    counts = [c for t in treatments for c in (F.max(F.when(F.col(t).isNotNull(), F.col(id_column))).alias(f"s_{t}"), F.count_if(F.col(t) == 1).alias(f"n1_{t}"), F.count_if(F.col(t) == 0).alias(f"n0_{t}"))]
    cells = df.groupBy(*keys).agg(*counts)
    each = F.array(*(F.struct(F.lit(t).alias("treatment"), F.col(f"s_{t}").alias("subclass"), F.col(f"n1_{t}").alias("n1"), F.col(f"n0_{t}").alias("n0")) for t in treatments))
    return cells.select(*keys, F.explode(each).alias("e")).select(*keys, "e.*").where("n1 > 0 and n0 > 0")


def overlap_report(summary: DataFrame) -> DataFrame:
    """Strata and rows, kept and dropped, and treated rows kept."""
    kept = (F.col("n1") > 0) & (F.col("n0") > 0)
    return summary.agg(
        F.count("*").alias("strata"), F.count_if(kept).alias("strata_kept"), F.coalesce(F.sum("n"), F.lit(0)).alias("rows"),
        F.coalesce(F.sum(F.when(kept, F.col("n"))), F.lit(0)).alias("rows_kept"), F.coalesce(F.sum(F.when(kept, F.col("n1"))), F.lit(0)).alias("treated_kept"),
    )
