"""Frozen descriptions of units, treatments and join chains; they hold no data."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class UnitSpec:
    """Roles of columns: ``covariates`` are matched on (coarsened), ``measured`` are the
    original values whose balance is reported, ``outcomes`` are averaged."""

    id: str
    treatment: str
    covariates: tuple[str, ...]
    outcomes: tuple[str, ...] = ()
    measured: tuple[str, ...] = ()

    def __post_init__(self):
        if self.treatment in (*self.covariates, *self.outcomes):
            raise ValueError(f"{self.treatment} is the treatment and cannot be a covariate or outcome")
        if set(self.covariates) & set(self.outcomes):
            raise ValueError("an outcome cannot be a covariate")


@dataclass(frozen=True)
class TreatmentSet:
    """Several treatments over one relation, each with its covariates."""

    id: str
    covariates: dict[str, tuple[str, ...]]
    outcomes: tuple[str, ...] = ()

    def spec(self, treatment: str) -> UnitSpec:
        return UnitSpec(self.id, treatment, self.covariates[treatment], self.outcomes)

    def shared(self, group) -> tuple[str, ...]:
        """Covariates that all treatments of ``group`` have, in the order of the first."""
        first, *rest = group
        return tuple(c for c in self.covariates[first] if all(c in self.covariates[t] for t in rest))


@dataclass(frozen=True)
class Hop:
    """One relation of a chain: its rows, the join keys with the chain so far, and the
    (coarsened) covariates that become known with it."""

    name: str
    rows: DataFrame = field(compare=False)
    on: tuple[tuple[str, str], ...]
    covariates: tuple[str, ...] = ()


def checked_treatment(df: DataFrame, spec: UnitSpec) -> DataFrame:
    """Rows for which the treatment is defined; other values than 0 and 1 raise when read."""
    t = F.col(spec.treatment)
    bad = F.raise_error(F.concat(F.lit(f"{spec.treatment} must be 0, 1 or null, not "), t.cast("string")))
    return df.where(t.isNotNull()).withColumn(spec.treatment, F.when(t.isin(0, 1), t).otherwise(bad.cast("int")))


def violations(df: DataFrame, spec: UnitSpec) -> DataFrame:
    """One row of counts that are 0 for sound units: ids null or repeated, treatments
    other than 0, 1, null, and null outcomes of rows with a treatment."""
    ids = df.groupBy(spec.id).agg(F.count("*").alias("n"), F.sum(_flag(~F.col(spec.treatment).isin(0, 1))).alias("bad_treatment"), *(
        F.sum(_flag(F.col(y).isNull() & F.col(spec.treatment).isNotNull())).alias(f"null_{y}") for y in spec.outcomes))
    total = [F.coalesce(F.sum(c), F.lit(0)).cast("long").alias(c) for c in ("bad_treatment", *(f"null_{y}" for y in spec.outcomes))]
    return ids.agg(F.coalesce(F.sum(_flag(F.col(spec.id).isNull())), F.lit(0)).cast("long").alias("null_ids"), F.coalesce(F.sum(_flag(F.col("n") > 1)), F.lit(0)).cast("long").alias("repeated_ids"), *total)


def _flag(condition: Column) -> Column:
    return F.when(condition, 1).otherwise(0)
