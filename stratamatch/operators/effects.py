"""Average effects: naive, stratified, matched, per site, adjusted by regression.

All results are rows of (…, n, n1, n0, ate); empty input gives one row with n = 0
and a null effect.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.spec import UnitSpec, checked_treatment
from .strata import arm


def _mean(treatment, value, column):
    return F.try_divide(F.sum(arm(treatment, value, column)).cast("double"), F.count(arm(treatment, value, column)))


def naive_effect(df: DataFrame, spec: UnitSpec) -> DataFrame:
    """Difference of raw means of the arms (an effect only if treatment was randomised)."""
    t = F.col(spec.treatment)
    effects = [(_mean(spec.treatment, 1, y) - _mean(spec.treatment, 0, y)).alias(f"ate_{y}") for y in spec.outcomes]
    return checked_treatment(df, spec).agg(F.count("*").alias("n"), F.count_if(t == 1).alias("n1"), F.count_if(t == 0).alias("n0"), *effects)


def difference(y: str) -> Column:
    """Difference of a stratum's arm means."""
    return F.col(f"sum1_{y}").cast("double") / F.col("n1") - F.col(f"sum0_{y}").cast("double") / F.col("n0")


def stratified_effect(strata: DataFrame, outcomes, weights: str = "all", by=()) -> DataFrame:
    """Mean of the strata's differences, weighted by their rows (``all``) or treated rows
    (``treated``); ``strata`` holds summaries with both arms."""
    w = {"all": F.col("n"), "treated": F.col("n1")}[weights]
    effects = [F.try_divide(F.sum(w * difference(y)), F.sum(w).cast("double")).alias(f"ate_{y}") for y in outcomes]
    return strata.groupBy(*by).agg(*totals(), *effects)


def totals():
    return [F.count("*").alias("strata"), *(F.coalesce(F.sum(c), F.lit(0)).cast("long").alias(c) for c in ("n", "n1", "n0"))]


def standard_error(df: DataFrame, spec: UnitSpec, y: str) -> DataFrame:
    """Effect with its standard error: strata weights squared times the arms' sample variance
    of the mean; strata with a single unit in an arm add no variance."""
    t = F.col(spec.treatment)
    cells = checked_treatment(df, spec).groupBy(*spec.covariates).agg(
        F.count("*").alias("n"), F.count_if(t == 1).alias("n1"), F.count_if(t == 0).alias("n0"), *(F.sum(arm(spec.treatment, a, y)).alias(f"sum{a}_{y}") for a in (1, 0)),
        *(F.var_samp(arm(spec.treatment, a, y).cast("double")).alias(f"var{a}") for a in (1, 0)),
    ).where("n1 > 0 and n0 > 0")
    noise = F.coalesce(F.col("var1"), F.lit(0.0)) / F.col("n1") + F.coalesce(F.col("var0"), F.lit(0.0)) / F.col("n0")
    n = F.sum("n").cast("double")
    return cells.agg(*totals(), F.try_divide(F.sum(F.col("n") * difference(y)), n).alias(f"ate_{y}"), F.try_divide(F.sqrt(F.sum(F.col("n") * F.col("n") * noise)), n).alias(f"se_{y}"))


def matched_effect(pairs: DataFrame, units: DataFrame, id_column: str, outcome: str) -> DataFrame:
    """Mean over treated units of own outcome minus the mean of their controls' outcomes: the
    effect on the matched treated (equal to the average effect only if arms keep one ratio)."""
    t = units.select(F.col(id_column).alias("t_uid"), F.col(outcome).cast("double").alias("y1"))
    c = units.select(F.col(id_column).alias("c_uid"), F.col(outcome).cast("double").alias("y0"))
    each = pairs.select("t_uid", "c_uid").join(c, "c_uid").groupBy("t_uid").agg(F.avg("y0").alias("y0"), F.count("*").alias("k")).join(t, "t_uid")
    return each.agg(F.count("*").alias("n1"), F.coalesce(F.sum("k"), F.lit(0)).cast("long").alias("pairs"), F.avg(F.col("y1") - F.col("y0")).alias(f"ate_{outcome}"))


def effect_by(df: DataFrame, spec: UnitSpec, site: str) -> DataFrame:
    """Effect per site from strata that include the site, its treated share among all units with
    a defined treatment, and their product, the normalised effect."""
    from .strata import overlapping, summarize

    local = UnitSpec(spec.id, spec.treatment, (site, *(c for c in spec.covariates if c != site)), spec.outcomes)
    cells = summarize(df, local)
    share = cells.groupBy(site).agg((F.sum("n1").cast("double") / F.sum("n")).alias("treated_share"))
    out = stratified_effect(overlapping(cells), spec.outcomes, by=(site,)).join(share, site)
    return out.select("*", *((F.col(f"ate_{y}") * F.col("treated_share")).alias(f"normalised_{y}") for y in spec.outcomes))


def regression_adjusted_effect(df: DataFrame, spec: UnitSpec, outcome: str, covariate: str) -> DataFrame:
    """Coefficient of the treatment in a linear model of the outcome on treatment and one
    covariate, from one aggregate of moments."""
    rows = checked_treatment(df, spec).select(F.col(spec.treatment).cast("double").alias("t"), F.col(covariate).cast("double").alias("x"), F.col(outcome).cast("double").alias("y"))
    m = rows.where("x is not null and y is not null").agg(
        F.count("*").alias("n"), *(F.covar_samp(a, b).alias(f"{a}{b}") for a, b in ("tx", "ty", "xy")), F.var_samp("t").alias("tt"), F.var_samp("x").alias("xx")
    )
    slope = F.try_divide(F.col("ty") * F.col("xx") - F.col("xy") * F.col("tx"), F.col("tt") * F.col("xx") - F.col("tx") * F.col("tx"))
    return m.select("n", slope.alias("ate"))


def balanced_sample(df: DataFrame, spec: UnitSpec, order: Column, k: int = 1) -> DataFrame:
    """Per stratum m treated and k * m controls, m = min(n1, n0 div k), the first of each arm
    in the given (hash) order."""
    if k < 1:
        raise ValueError("k must be at least 1")
    rows = checked_treatment(df, spec)
    place = F.row_number().over(Window.partitionBy(*spec.covariates, spec.treatment).orderBy(order, spec.id))
    counts = summarize_counts(rows, spec).withColumn("m", F.least("n1", F.expr(f"n0 div {k}"))).where("m > 0")
    from .strata import attach

    out = attach(rows.withColumn("_place", place), counts, spec.covariates, {"m": "_m"})
    return out.where(F.col("_place") <= F.col("_m") * F.when(F.col(spec.treatment) == 1, 1).otherwise(k)).drop("_place", "_m")


def summarize_counts(rows: DataFrame, spec: UnitSpec) -> DataFrame:
    t = F.col(spec.treatment)
    return rows.groupBy(*spec.covariates).agg(F.count_if(t == 1).alias("n1"), F.count_if(t == 0).alias("n0"))
