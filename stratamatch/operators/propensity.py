"""Propensity scores: estimators, scoring by expressions, trimming."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.spec import UnitSpec, checked_treatment
from .strata import attach


def score_expr(weights: dict[str, float], intercept: float) -> Column:
    """Logistic score of a linear form, as a plain expression (no UDF when scoring)."""
    z = F.lit(float(intercept))
    for name, w in weights.items():
        z = z + F.lit(float(w)) * F.col(name).cast("double")
    return 1 / (1 + F.exp(-z))


def fit_propensity(df: DataFrame, spec: UnitSpec, numeric=(), categorical=(), max_iter: int = 50, reg: float = 0.0):
    """Logistic regression of the treatment; returns (score column, weights, intercept). Weights of
    a categorical value are keyed (column, value); unseen values count as the reference value.
    Action: one scan for each iteration over a materialized feature table."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    from ..sources.shared import materialized

    rows = checked_treatment(df, spec).dropna(subset=[spec.treatment, *numeric])
    levels = {c: [r[0] for r in rows.groupBy(c).count().orderBy(c).limit(1001).collect()] for c in categorical}
    for c, values in levels.items():
        if len(values) > 1000:
            raise ValueError(f"{c} has more than 1000 values; coarsen it first")
    terms = [(n, F.col(n).cast("double")) for n in numeric] + [((c, v), F.col(c).eqNullSafe(F.lit(v)).cast("double")) for c in categorical for v in levels[c][1:]]
    flat = rows.select(F.col(spec.treatment).cast("double").alias("label"), *(e.alias(f"x{i}") for i, (_, e) in enumerate(terms)))
    features = VectorAssembler(inputCols=[f"x{i}" for i in range(len(terms))], outputCol="features").transform(materialized(flat, "features"))
    model = LogisticRegression(maxIter=max_iter, regParam=reg, tol=1e-9).fit(features)
    z = F.lit(float(model.intercept))
    for (_, e), w in zip(terms, model.coefficients):
        z = z + F.lit(float(w)) * e
    return 1 / (1 + F.exp(-z)), dict(zip((k for k, _ in terms), map(float, model.coefficients))), float(model.intercept)


def fit_propensity_factorized(dimension: DataFrame, facts: DataFrame, on: str, treatment: str, numeric, max_iter: int = 50):
    """The logistic regression of a fact-side treatment on dimension columns without the join's
    rows: facts are counted per key and arm below the join, and each dimension row enters with
    these counts as weights. Returns (score column, weights, intercept), as the joined fit gives. Action."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    t = F.col(treatment)
    counts = facts.where(t.isNotNull()).groupBy(on, t.cast("double").alias("label")).agg(F.count("*").cast("double").alias("weight"))
    rows = VectorAssembler(inputCols=list(numeric), outputCol="features").transform(dimension.join(counts, on).select("label", "weight", *(F.col(c).cast("double").alias(c) for c in numeric)))
    model = LogisticRegression(maxIter=max_iter, tol=1e-9, weightCol="weight").fit(rows)
    weights = dict(zip(numeric, map(float, model.coefficients)))
    return score_expr(weights, float(model.intercept)), weights, float(model.intercept)


def cell_propensity(df: DataFrame, spec: UnitSpec) -> DataFrame:
    """Rows with ``ps``: treated share of their covariate cell."""
    t = F.col(spec.treatment)
    rows = checked_treatment(df, spec)
    cells = rows.groupBy(*spec.covariates).agg((F.count_if(t == 1) / F.count("*")).alias("ps"))
    return attach(rows, cells, spec.covariates, {"ps": "ps"})


def trim(df: DataFrame, score: str, low, high) -> DataFrame:
    """Rows whose score lies in [low, high]; the bounds stay."""
    return df.where((F.col(score) >= low) & (F.col(score) <= high))
