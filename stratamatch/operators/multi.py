"""Several treatments over one relation: correlation, grouping, covariate factoring."""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.spec import TreatmentSet, UnitSpec
from .lattice import base_cuboid, roll_up, strata_of
from .strata import attach, overlapping, summarize


def phi_matrix(df: DataFrame, treatments) -> DataFrame:
    """For each pair: counts n11, n10, n01, n00 over rows where both are defined, and phi (null
    if a margin is 0). One scan, one aggregate of counters for all pairs."""
    pairs = list(combinations(treatments, 2))
    counters = [F.count_if((F.col(a) == x) & (F.col(b) == y)).alias(f"p{i}_{x}{y}") for i, (a, b) in enumerate(pairs) for x in (1, 0) for y in (1, 0)]
    row = df.agg(*counters)
    each = F.array(*(F.struct(F.lit(a).alias("t_a"), F.lit(b).alias("t_b"), *(F.col(f"p{i}_{x}{y}").alias(f"n{x}{y}") for x in (1, 0) for y in (1, 0))) for i, (a, b) in enumerate(pairs)))
    out = row.select(F.explode(each).alias("e")).select("e.*")
    d = {c: F.col(c).cast("double") for c in ("n11", "n10", "n01", "n00")}
    margins = F.sqrt((d["n11"] + d["n10"]) * (d["n01"] + d["n00"]) * (d["n11"] + d["n01"]) * (d["n10"] + d["n00"]))
    return out.withColumn("phi", F.try_divide(d["n11"] * d["n00"] - d["n10"] * d["n01"], margins))


def partition_treatments(phi: dict, treatments: TreatmentSet) -> list[tuple[tuple[str, ...], float]]:
    """The partition into groups of two or more with shared covariates whose sum of scores is
    largest; a group's score is the sum of absolute phi over its pairs divided by its size.
    If no such partition exists, treatments that fit nowhere stay alone with score 0. Above
    ten treatments groups are merged greedily."""
    names = sorted(treatments.covariates)

    def score(group):
        if len(group) < 2:
            return 0.0
        return sum(abs(phi.get((a, b), phi.get((b, a))) or 0.0) for a, b in combinations(group, 2)) / len(group)

    def fits(group):
        return len(group) >= 2 and bool(treatments.shared(group))

    if len(names) <= 10:
        found = list(_partitions(names))
        good = [p for p in found if all(fits(g) for g in p)]
        if not good:
            good = [p for p in found if all(fits(g) or len(g) == 1 for g in p)]
            fewest = min(sum(len(g) == 1 for g in p) for p in good)
            good = [p for p in good if sum(len(g) == 1 for g in p) == fewest]
        best = max(good, key=lambda p: (round(sum(map(score, p)), 12), [-len(p)]))
    else:
        best = [(n,) for n in names]
        while True:
            merges = [(score(tuple(sorted(a + b))) - score(a) - score(b), a, b) for a, b in combinations(best, 2) if fits(tuple(sorted(a + b)))]
            merges = [m for m in merges if m[0] > 0 or len(m[1]) == 1 or len(m[2]) == 1]
            if not merges:
                break
            _, a, b = max(merges)
            best = [g for g in best if g not in (a, b)] + [tuple(sorted(a + b))]
    return sorted(((tuple(g), score(tuple(g))) for g in best), key=lambda x: (-x[1], x[0]))


def _partitions(items):
    if not items:
        yield []
        return
    head, rest = items[0], items[1:]
    for p in _partitions(rest):
        yield [(head,), *p]
        for i in range(len(p)):
            yield [*p[:i], (head, *p[i]), *p[i + 1 :]]


def phi_values(df: DataFrame, treatments) -> dict:
    """phi by pair (action: one aggregate, k * (k - 1) / 2 rows)."""
    return {(r["t_a"], r["t_b"]): r["phi"] for r in phi_matrix(df, treatments).collect()}


def factor(df: DataFrame, treatments: TreatmentSet, group, plan: str = "groupby") -> DataFrame:
    """Rows of supergroups (equal shared covariates) in which at least one treatment of the
    group has both arms, with ``supersubclass``, the largest id of the supergroup."""
    keys = treatments.shared(group)
    if not keys:
        raise ValueError("the group shares no covariate")
    if plan == "window":
        from pyspark.sql import Window

        w = Window.partitionBy(*keys)
        out = df.select("*", F.max(treatments.id).over(w).alias("supersubclass"), *(f(t).over(w).alias(f"_{p}{i}") for i, t in enumerate(group) for p, f in (("a", F.min), ("b", F.max))))
        return out.where(" or ".join(f"_a{i} != _b{i}" for i in range(len(group)))).drop(*(f"_{p}{i}" for i in range(len(group)) for p in "ab"))
    cells = df.groupBy(*keys).agg(F.max(treatments.id).alias("supersubclass"), *(f(t).alias(f"_{p}{i}") for i, t in enumerate(group) for p, f in (("a", F.min), ("b", F.max))))
    kept = cells.where(" or ".join(f"_a{i} != _b{i}" for i in range(len(group))))
    return attach(df, kept, keys, {"supersubclass": "supersubclass"})


def factored_summary(view: DataFrame, treatments: TreatmentSet, group, treatment: str, keep=()) -> DataFrame:
    """Strata of one treatment on factored rows: supergroup and the treatment's own covariates."""
    own = tuple(c for c in treatments.covariates[treatment] if c not in treatments.shared(group))
    spec = UnitSpec(treatments.id, treatment, ("supersubclass", *own), treatments.outcomes)
    return overlapping(summarize(view, spec))


def cem_from_factored(view: DataFrame, treatments: TreatmentSet, group, treatment: str) -> DataFrame:
    """The matched rows of one treatment, as ``cem`` on all rows gives them."""
    own = tuple(c for c in treatments.covariates[treatment] if c not in treatments.shared(group))
    from .strata import cem

    return cem(view, UnitSpec(treatments.id, treatment, ("supersubclass", *own), treatments.outcomes))


def supergroups(group) -> Column:
    """Whether a supergroup's cell has both arms of at least one treatment of the group."""
    return reduce(lambda a, b: a | b, ((F.col(f"n1_{t}") > 0) & (F.col(f"n0_{t}") > 0) for t in group))


def supergroup_pruning(df: DataFrame, treatments: TreatmentSet, group, one_of: int = 16) -> float:
    """Share of rows in supergroups without overlap, from the whole supergroups of one in ``one_of``
    keys (by hash). Action: one aggregate of that part."""
    keys = treatments.shared(group)
    some = df.where(F.pmod(F.xxhash64(*keys), F.lit(one_of)) == 0)
    counts = [F.count_if(F.col(t) == a).alias(f"n{a}_{t}") for t in group for a in (1, 0)]
    kept, n = some.groupBy(*keys).agg(F.count("*").alias("n"), *counts).agg(F.sum(F.when(supergroups(group), F.col("n")).otherwise(0)), F.sum("n")).first()
    return 1 - kept / n if n else 0.0


def summaries_multi(df: DataFrame, treatments: TreatmentSet, partition, store, plan: str = "auto", least: float = 0.5) -> dict[str, DataFrame]:
    """Strata with both arms of every treatment, with work shared inside each group of the partition;
    ``store`` keeps what a group's treatments share. Treatments with the same covariates always
    come from one aggregate. For the others: ``rows`` (the group's factored rows), ``cells`` (the cells
    of the group's covariates, where supergroups without overlap go; for questions on few
    covariates with many rows a cell), ``each`` (an aggregate for each treatment), or ``auto``:
    factored rows if a sample of supergroups says that at least the share ``least`` of rows goes, else ``each``."""
    if plan not in ("auto", "cells", "rows", "each"):
        raise ValueError(plan)
    out = {}
    for group, _ in partition:
        dims, same = list(dict.fromkeys(c for t in group for c in treatments.covariates[t])), len({frozenset(treatments.covariates[t]) for t in group}) == 1
        how = "cells" if same and len(group) > 1 else "each" if len(group) < 2 else plan
        if how == "auto":
            how = "rows" if supergroup_pruning(df, treatments, group) >= least else "each"
        if how == "each":
            out |= {t: overlapping(summarize(df, treatments.spec(t))) for t in group}
        elif how == "rows":
            view = store(factor(df, treatments, group))
            out |= {t: factored_summary(view, treatments, group, t) for t in group}
        else:
            shared = list(treatments.shared(group))
            kept = cells = store(base_cuboid(df, dims, treatments.id, group, treatments.outcomes))
            if not same:
                kept = attach(cells, roll_up(cells.select(*shared, *(f"n{a}_{t}" for t in group for a in (1, 0))), shared, shared).where(supergroups(group)), shared, {})
            for t in group:
                keys = list(treatments.covariates[t])
                own = [c for c in cells.columns if c in dims or c == f"max_{t}" or c.startswith((f"n1_{t}", f"n0_{t}", f"sum1_{t}_", f"sum0_{t}_"))]
                out[t] = strata_of(kept if same else roll_up(kept.select(*own), keys, dims), t, keys, treatments.outcomes)
    return out
