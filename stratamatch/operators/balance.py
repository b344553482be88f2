"""Measures of balance and of sample size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spec import UnitSpec, checked_treatment
from .effects import difference
from .ranking import exact_quantiles
from .strata import arm, attach


def awmd(strata: DataFrame, covariates) -> DataFrame:
    """Absolute weighted mean difference of each covariate: strata's absolute differences of
    arm means, weighted by rows. One aggregate; columns awmd_<covariate>."""
    n = F.sum("n").cast("double")
    return strata.agg(*(F.try_divide(F.sum(F.col("n") * F.abs(difference(x))), n).alias(f"awmd_{x}") for x in covariates))


def awmd_pairs(pairs: DataFrame, units: DataFrame, id_column: str, covariates, groups: str = "pooled") -> DataFrame:
    """The same for matched pairs: ``pooled`` takes all pairs as one stratum (controls count as
    often as they are used), ``per_treated`` each treated unit with its controls."""
    x = list(covariates)
    t = units.select(F.col(id_column).alias("t_uid"), *(F.col(c).cast("double").alias(f"t_{c}") for c in x))
    c_side = units.select(F.col(id_column).alias("c_uid"), *(F.col(c).cast("double").alias(f"c_{c}") for c in x))
    each = pairs.select("t_uid", "c_uid").join(c_side, "c_uid").groupBy("t_uid").agg(F.count("*").alias("k"), *(F.sum(f"c_{c}").alias(f"c_{c}") for c in x)).join(t, "t_uid")
    if groups == "pooled":
        return each.agg(*(F.abs(F.avg(f"t_{c}") - F.sum(f"c_{c}") / F.sum("k")).alias(f"awmd_{c}") for c in x))
    weight = F.col("k") + 1
    return each.agg(*((F.sum(weight * F.abs(F.col(f"t_{c}") - F.col(f"c_{c}") / F.col("k"))) / F.sum(weight)).alias(f"awmd_{c}") for c in x))


def match_size(pairs: DataFrame) -> DataFrame:
    """Distinct treated and control units of matched pairs."""
    return pairs.agg(F.count_distinct("t_uid").alias("n1_matched"), F.count_distinct("c_uid").alias("n0_matched"))


def match_rates(n1: str, n0: str, all_treated: str):
    """Share of treated units matched and controls per treated, as expressions."""
    return [F.try_divide(F.col(n1).cast("double"), F.col(all_treated)).alias("treated_share"), F.try_divide(F.col(n0).cast("double"), F.col(n1)).alias("controls_per_treated")]


def moments(df: DataFrame, spec: UnitSpec, x: str) -> DataFrame:
    """Per arm: n, mean, variance (population) and skewness from sums of powers."""
    v = F.col(x).cast("double")
    rows = checked_treatment(df, spec).where(F.col(x).isNotNull())
    sums = rows.groupBy(F.col(spec.treatment).alias("t")).agg(F.count("*").alias("n"), F.avg(v).alias("mean"), F.avg(v * v).alias("m2"), F.avg(v * v * v).alias("m3"))
    var = F.col("m2") - F.col("mean") * F.col("mean")
    third = F.col("m3") - 3 * F.col("mean") * F.col("m2") + 2 * F.col("mean") * F.col("mean") * F.col("mean")
    return sums.select("t", "n", "mean", var.alias("variance"), F.try_divide(third, F.pow(F.abs(var), F.lit(1.5))).alias("skewness"))


def quantiles(df: DataFrame, spec: UnitSpec, x: str, points) -> DataFrame:
    """Exact quantiles of both arms and their differences: one row for each point. Action."""
    rows = checked_treatment(df, spec).select(spec.treatment, x)
    arms = [exact_quantiles(rows.where(F.col(spec.treatment) == a), x, points) for a in (1, 0)]
    table = [(float(p), *(None if v is None else float(v) for v in pair), None if None in pair else float(pair[0] - pair[1])) for p, *pair in zip(points, *arms)]
    return df.sparkSession.createDataFrame(table, "point double, treated double, control double, difference double")


def l1_histogram(df: DataFrame, spec: UnitSpec) -> DataFrame:
    """Half the sum over cells of the covariate codes of the absolute difference of the arms'
    relative frequencies: 0 for equal, 1 for disjoint arms."""
    t = F.col(spec.treatment)
    cells = checked_treatment(df, spec).groupBy(*spec.covariates).agg(F.count_if(t == 1).alias("a"), F.count_if(t == 0).alias("b"))
    whole = cells.agg(F.sum("a").alias("na"), F.sum("b").alias("nb"))
    gap = F.abs(F.try_divide(F.col("a").cast("double"), F.col("na")) - F.try_divide(F.col("b").cast("double"), F.col("nb")))
    return cells.crossJoin(F.broadcast(whole)).agg((F.sum(gap) / 2).alias("l1"))  # whole: one row


def balance_gap(df: DataFrame, spec: UnitSpec, strata, cells) -> DataFrame:
    """Largest gap, within any stratum with both arms, of the arms' relative frequencies of cells."""
    t = F.col(spec.treatment)
    fine = checked_treatment(df, spec).groupBy(*strata, *cells).agg(F.count_if(t == 1).alias("a"), F.count_if(t == 0).alias("b"))
    coarse = fine.groupBy(*strata).agg(F.sum("a").alias("na"), F.sum("b").alias("nb")).where("na > 0 and nb > 0")
    both = attach(fine, coarse, strata, {"na": "na", "nb": "nb"})
    return both.agg(F.max(F.abs(F.col("a") / F.col("na") - F.col("b") / F.col("nb"))).alias("gap"))
