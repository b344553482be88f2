"""Streaming strata and effects; traffic over event-time windows; interval joins of streams."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.effects import stratified_effect
from ..operators.strata import overlapping, summarize
from ..plans.spec import UnitSpec


def live_strata(stream: DataFrame, spec: UnitSpec, sink: str, checkpoint: str):
    """Keep the strata summary of a stream of units as Parquet under ``sink``: each micro-batch
    adds its cells (one folder per batch, rewritten if the batch runs again). Returns the query."""

    def add(batch: DataFrame, number: int):
        summarize(batch, spec).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    return stream.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def current_strata(cells: DataFrame, spec: UnitSpec) -> DataFrame:
    """One summary from the batches' cells (they are additive)."""
    values = [c for c in cells.columns if c not in (*spec.covariates, "batch")]
    return cells.groupBy(*spec.covariates).agg(*((F.max(c) if c == "subclass" else F.sum(c)).alias(c) for c in values))


def current_effect(cells: DataFrame, spec: UnitSpec) -> DataFrame:
    return stratified_effect(overlapping(current_strata(cells, spec)), spec.outcomes)


def windowed_traffic(events: DataFrame, by, ts: str = "ts", length: str = "1 hour", slide: str | None = None, late: str | None = None) -> DataFrame:
    """Events per key and window, tumbling or sliding; ``late`` sets the watermark of a stream."""
    rows = events.withWatermark(ts, late) if late else events
    w = F.window(ts, length, slide) if slide else F.window(ts, length)
    return rows.groupBy(w.alias("w"), *by).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *by, "n")


def sessions(events: DataFrame, by, ts: str = "ts", gap: str = "30 minutes", late: str | None = None) -> DataFrame:
    """Sessions of a key: runs of events with gaps below ``gap``."""
    rows = events.withWatermark(ts, late) if late else events
    return rows.groupBy(F.session_window(ts, gap).alias("w"), *by).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *by, "n")


def join_streams(trips: DataFrame, readings: DataFrame, site: str, ts: str, before: str = "2 hours", late: str = "3 hours") -> DataFrame:
    """Trips with the readings of their site in the interval before them, both with watermarks."""
    t = trips.withWatermark(ts, late).select(*(F.col(c).alias(f"t_{c}") for c in trips.columns))
    r = readings.withWatermark(ts, late).select(*(F.col(c).alias(f"r_{c}") for c in readings.columns))
    near = F.expr(f"t_{site} = r_{site} and r_{ts} <= t_{ts} and r_{ts} >= t_{ts} - interval {before}")
    return t.join(r, near)


def running_counts(stream: DataFrame, spec: UnitSpec) -> DataFrame:
    """Arm counts per stratum for update or complete mode."""
    t = F.col(spec.treatment)
    return stream.where(t.isNotNull()).groupBy(*spec.covariates).agg(F.count_if(t == 1).alias("n1"), F.count_if(t == 0).alias("n0"))


def running_differences(stream: DataFrame, spec: UnitSpec, outcome: str) -> DataFrame:
    """Per stratum, after each micro-batch that touches it: arm counts so far and the difference
    of arm means (null while an arm is empty). State is four numbers a stratum; update mode."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    keys, treatment = list(spec.covariates), spec.treatment

    def update(key, frames, state):
        n1, n0, s1, s0 = state.get if state.exists else (0, 0, 0.0, 0.0)
        for f in frames:
            one, zero = f[f[treatment] == 1][outcome], f[f[treatment] == 0][outcome]
            n1, n0, s1, s0 = n1 + len(one), n0 + len(zero), s1 + float(one.sum()), s0 + float(zero.sum())
        state.update((n1, n0, s1, s0))
        yield pd.DataFrame({**{k: [v] for k, v in zip(keys, key)}, "n1": [n1], "n0": [n0], "difference": [s1 / n1 - s0 / n0 if n1 and n0 else None]})

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in stream.select(*keys).schema)
    rows = stream.where(F.col(treatment).isNotNull()).select(*keys, treatment, F.col(outcome).cast("double").alias(outcome))
    return rows.groupBy(*keys).applyInPandasWithState(update, f"{kinds}, n1 long, n0 long, difference double", "n1 long, n0 long, s1 double, s0 double", "update", GroupStateTimeout.NoTimeout)
