"""Matching on base relations: strata that lack an arm are dropped before each join.

Covariates of later relations only refine the key, so a stratum without overlap on the
covariates known so far can never gain it; dropping its rows early leaves the final
result unchanged and joins fewer rows.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spec import Hop, UnitSpec
from .strata import attach, cem, overlapping, summarize


def joined(hops: list[Hop]) -> DataFrame:
    """The integrated table: the chain's relations joined in order."""
    return reduce(_hop, hops[1:], hops[0].rows)


def _hop(left: DataFrame, hop: Hop) -> DataFrame:
    on = [F.col(a) == hop.rows[b] for a, b in hop.on]
    out = left.join(hop.rows, on)
    for a, b in hop.on:
        if a == b:
            out = out.drop(hop.rows[b])
    return out


def ordered(hops: list[Hop], sizes: dict[str, int]) -> list[Hop]:
    """First relation first (it has the treatment), then always the smallest that joins to what is there."""
    out, rest = [hops[0]], list(hops[1:])
    known = set(hops[0].rows.columns)
    while rest:
        ready = [h for h in rest if all(a in known for a, _ in h.on)]
        if not ready:
            raise ValueError("a relation does not join to the chain")
        h = min(ready, key=lambda h: sizes.get(h.name, 1 << 62))
        rest.remove(h)
        out.append(h)
        known |= set(h.rows.columns)
    return out


def prune(rows: DataFrame, spec: UnitSpec) -> DataFrame:
    """Rows of strata with both arms (a semi-join with the kept keys)."""
    kept = overlapping(summarize(rows, UnitSpec(spec.id, spec.treatment, spec.covariates)))
    return attach(rows.where(F.col(spec.treatment).isNotNull()), kept, spec.covariates, {})


def cem_pushed(hops: list[Hop], spec: UnitSpec, first_id: str, store=lambda df: df) -> DataFrame:
    """The integrated result of ``cem``, with strata pruned before every join. ``first_id`` is
    the id of the first relation's rows; ``spec.id`` exists after the last hop. Matching reads its
    rows twice, so ``store`` may keep joined rows (the pruned ones only, with the columns that
    later steps need) instead of joining them again."""
    known, rows = (), hops[0].rows
    wanted = {spec.id, spec.treatment, *spec.covariates, *spec.outcomes, *(a for h in hops for a, _ in h.on), *(c for h in hops for c in h.covariates)}
    for hop in hops:
        if hop is not hops[0]:
            rows = _hop(rows, hop)
        known += hop.covariates
        last = hop is hops[-1]
        if hop is not hops[0] and (last or hop.covariates):
            rows = store(rows.select(*(c for c in rows.columns if c in wanted | {first_id})))
        if hop.covariates and not last:
            rows = prune(rows, UnitSpec(first_id, spec.treatment, known))
    return cem(rows, UnitSpec(spec.id, spec.treatment, known, spec.outcomes))


def pushdown_report(hops: list[Hop], spec: UnitSpec, first_id: str) -> DataFrame:
    """Rows before and after pruning at each step of the chain."""
    known, rows, out = (), hops[0].rows, None
    for step, hop in enumerate(hops, 1):
        if step > 1:
            rows = _hop(rows, hop)
        known += hop.covariates
        kept = prune(rows, UnitSpec(first_id, spec.treatment, known))
        one = rows.agg(F.count("*").alias("rows_in")).crossJoin(kept.agg(F.count("*").alias("rows_out")))  # one row each
        one = one.select(F.lit(step).alias("step"), F.lit(hop.name).alias("relation"), "rows_in", "rows_out")
        out = one if out is None else out.unionByName(one)
        rows = kept
    return out


def estimated_pruning(rows: DataFrame, spec: UnitSpec, one_of: int = 16) -> float:
    """Share of the first relation's rows that pruning drops, estimated from the whole strata of one
    in ``one_of`` keys (by hash), so that the aggregate holds that part of the strata only. With
    ``one_of`` 1 it is exact. Action."""
    some = rows.where(F.pmod(F.xxhash64(*spec.covariates), F.lit(one_of)) == 0) if one_of > 1 and spec.covariates else rows
    kept, n = summarize(some, spec).agg(F.sum(F.when((F.col("n1") > 0) & (F.col("n0") > 0), F.col("n")).otherwise(0)), F.sum("n")).first()
    if n is None and one_of > 1:  # no stratum was drawn: there are few
        return estimated_pruning(rows, spec, 1)
    return 1 - kept / n if n else 0.0


def cem_auto(hops: list[Hop], spec: UnitSpec, first_id: str, least: float = 0.3, one_of: int = 16) -> tuple[str, DataFrame]:
    """Push below the joins if the first relation alone loses at least that share of rows."""
    if estimated_pruning(hops[0].rows, UnitSpec(first_id, spec.treatment, hops[0].covariates), one_of) >= least:
        return "pushed", cem_pushed(hops, spec, first_id)
    return "integrated", cem(joined(hops), spec)
