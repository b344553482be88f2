"""Subclassification by quantiles of a score."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.spec import UnitSpec, checked_treatment
from .ranking import with_rank


def subclassify(df: DataFrame, spec: UnitSpec, score: str, n: int = 5, plan: str = "ranked") -> DataFrame:
    """Rows with ``quantile`` (1..n) in ascending (score, id), only quantiles with both arms, and
    ``subclass``, the largest id of the quantile. Plans: ``ranked`` (distributed, exact),
    ``ntile`` (one window over all rows; small inputs), ``approx`` (approximate cut points)."""
    if n < 1:
        raise ValueError("n must be at least 1")
    rows = checked_treatment(df, spec).where(F.col(score).isNotNull())
    if plan == "ntile":
        rows = rows.withColumn("quantile", F.ntile(n).over(Window.orderBy(score, spec.id)))
    elif plan == "ranked":
        total = F.broadcast(rows.agg(F.count("*").alias("_total")))
        ranked = with_rank(rows, [score, spec.id], "_rank").crossJoin(total)  # one row
        # The first total mod n quantiles have one row more.
        long, size = F.expr(f"_total % {n}"), F.expr(f"_total div {n}")
        head = long * (size + 1)
        at = F.col("_rank") - 1
        first = F.expr(f"(_rank - 1) div (_total div {n} + 1)")
        rest = F.expr(f"(_rank - 1 - (_total % {n}) * (_total div {n} + 1)) div greatest(_total div {n}, 1)") + long
        rows = ranked.withColumn("quantile", (F.when(at < head, first).otherwise(rest) + 1).cast("int")).drop("_rank", "_total")
    elif plan == "approx":
        cuts = rows.agg(F.percentile_approx(score, [i / n for i in range(1, n)], 10_000)).first()[0] if n > 1 else []
        from ..functions.coarsening import cut

        rows = rows.withColumn("quantile", cut(F.col(score), sorted(set(cuts or []))))
    else:
        raise ValueError(plan)
    t = F.col(spec.treatment)
    kept = rows.groupBy("quantile").agg(F.max(spec.id).alias("subclass"), F.min(t).alias("_low"), F.max(t).alias("_high")).where("_low != _high").select("quantile", "subclass")
    return rows.join(F.broadcast(kept), "quantile")  # n rows
