"""Binary treatments as nullable 0/1 columns; null leaves a unit out of that treatment only."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column
from pyspark.sql import functions as F


def threshold_treatment(name: str, treated: str, control: str) -> Column:
    """1 where ``name`` meets ``treated`` (as "> 40"), 0 where it meets ``control``, else null."""
    return F.when(F.expr(f"{name} {treated}"), 1).when(F.expr(f"{name} {control}"), 0)


def predicate_treatment(condition: str) -> Column:
    return F.expr(condition).cast("int")


def binary_treatment(name: str) -> Column:
    return F.col(name).cast("int")


def conjunction(*parts) -> Column:
    """1 where all parts are 1, 0 where any is 0, else null (three-valued AND)."""
    columns = [F.col(p) if isinstance(p, str) else p for p in parts]
    every, none = columns[0] == 1, columns[0] == 0
    for c in columns[1:]:
        every, none = every & (c == 1), none | (c == 0)
    return F.when(every, 1).when(none, 0)


def enumerate_treatments(attributes, most: int | None = None) -> list[tuple[str, ...]]:
    """All conjunctions of one up to ``most`` of the dichotomised attributes."""
    n = len(attributes) if most is None else min(most, len(attributes))
    return [c for k in range(1, n + 1) for c in combinations(attributes, k)]
