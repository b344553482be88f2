"""Blocking edges of a matching by scores, counted without making the edges within the caliper."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spec import UnitSpec, checked_treatment
from ..sources.shared import materialized
from .ranking import range_cuts, range_of

NONE = np.iinfo(np.int64).max


def _reach(ids, other, scores, rank_of, ranks):
    """Number of units of the other arm at ``scores`` whose id is below ``ids``, as (from, to) places in (score, id) order."""
    at = np.searchsorted(other["x"], scores, "left")
    end = np.searchsorted(other["x"], scores, "right")
    score_of = np.searchsorted(ranks, scores)
    inside = score_of < len(ranks)
    inside[inside] = ranks[score_of[inside]] == scores[inside]
    below = np.searchsorted(other["place"], score_of * (len(rank_of) + 1) + np.searchsorted(rank_of, ids), "left")
    return at, np.where(inside, np.clip(below, at, end), at)


def _arm(x, uid, far, mate):
    """One arm in (score, id) order. ``far``, ``mate``: distance and partner of its last edge, infinite if it has room."""
    order = np.lexsort((uid, x))
    arm = {"x": x[order], "uid": uid[order], "far": far[order], "mate": mate[order]}
    arm["ids"], arm["scores"] = np.unique(uid), np.unique(x)
    arm["place"] = np.searchsorted(arm["scores"], arm["x"]) * (len(arm["ids"]) + 1) + np.searchsorted(arm["ids"], arm["uid"])
    return arm


def _extreme(values, lo, hi, best):
    """``best`` (np.minimum or np.maximum) over values[lo:hi] of each pair, where it is not empty."""
    table = [values]
    while 2 ** len(table) <= len(values):
        half, last = 2 ** (len(table) - 1), table[-1]
        table.append(best(last[:-half], last[half:]))
    out, size = np.full(len(lo), np.nan), hi - lo
    level = np.frexp(np.maximum(size, 1).astype(float))[1] - 1
    for i, t in enumerate(table):
        own = np.flatnonzero((size > 0) & (level == i))
        out[own] = best(t[lo[own]], t[hi[own] - 2**i])
    return out


def count_blocking(t: dict, c: dict, caliper) -> int:
    """Pairs whose control is free or has a later edge and whose treated unit has room or holds a later one. Only units
    with such a pair are looked at one by one."""
    if not len(t["x"]) or not len(c["x"]):
        return 0
    total = 0
    # Strictly nearer than both last edges.
    t_far, c_far = np.minimum(t["far"], caliper), np.minimum(c["far"], caliper)
    x = t["x"]
    lo, mid, hi = np.searchsorted(c["x"], x - t_far, "right"), np.searchsorted(c["x"], x, "left"), np.searchsorted(c["x"], x + t_far, "left")
    lo, hi = np.minimum(lo, mid), np.maximum(hi, mid)
    some = (_extreme(c["x"] - c_far, mid, hi, np.minimum) < x) | (_extreme(c["x"] + c_far, lo, mid, np.maximum) > x)
    for i in np.flatnonzero(some & (t_far > 0)):
        near = slice(lo[i], hi[i])
        total += int((np.abs(c["x"][near] - x[i]) < c_far[near]).sum())
    # As near as the last edge of the control, then as that of the treated unit: ids decide.
    for own, other, both in ((c, t, True), (t, c, False)):
        place = np.empty(len(other["x"]), np.int64)
        place[np.lexsort((other["mate"], other["far"]))] = np.arange(len(place))
        for side in (1, -1):
            held = np.flatnonzero((own["far"] < caliper) & ((own["far"] > 0) | (side > 0)))
            d = own["far"][held]
            y = own["x"][held] + side * d
            at, end = _reach(own["mate"][held], other, y, other["ids"], other["scores"])
            most = _extreme(place.astype(float), at, end, np.maximum)
            open_ = np.flatnonzero(end > at)
            if not len(open_):
                continue
            back = np.empty(len(place), np.int64)
            back[place] = np.arange(len(place))
            top = back[most[open_].astype(np.int64)]
            later = (other["far"][top] > d[open_]) | (both & (other["far"][top] == d[open_]) & (other["mate"][top] > own["uid"][held[open_]]))
            for j in open_[later]:
                far, mate = other["far"][at[j] : end[j]], other["mate"][at[j] : end[j]]
                total += int(((far > d[j]) | (both & (far == d[j]) & (mate > own["uid"][held[j]]))).sum())
    return total


def blocking_edges(df: DataFrame, spec: UnitSpec, score: str, caliper, result: DataFrame, k: int) -> DataFrame:
    """One row ``blocking_edges``, as ``greedy_violations`` counts them among all edges within the caliper; scores are whole.
    Treated units are cut into ranges of the score, each with the controls within the caliper of it."""
    units = checked_treatment(df, spec).where(F.col(score).isNotNull())
    units = units.select(F.col(spec.id).cast("long").alias("uid"), F.col(spec.treatment).alias("t"), F.col(score).cast("double").alias("x"))
    last = F.max(F.struct("distance", "t_uid", "c_uid"))
    of_c = result.groupBy(F.col("c_uid").alias("uid")).agg(last.alias("m")).select("uid", F.lit(0).alias("t"), "m.distance", F.col("m.t_uid").alias("mate"))
    of_t = result.groupBy(F.col("t_uid").alias("uid")).agg(last.alias("m"), F.count("*").alias("n")).where(F.col("n") >= k)
    of_t = of_t.select("uid", F.lit(1).alias("t"), "m.distance", F.col("m.c_uid").alias("mate"))
    far = F.coalesce("distance", F.lit(float("inf"))).alias("far")
    rows = materialized(units.join(of_c.unionByName(of_t), ["uid", "t"], "left").select("uid", "t", "x", far, F.coalesce("mate", F.lit(NONE)).alias("mate")), "places")
    cuts = range_cuts(rows.select("x"), ["x"], int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))

    t = rows.where("t = 1").withColumn("r", range_of(["x"], cuts))
    low, high = (range_of([name], cuts) for name in ("_low", "_high"))
    c = rows.where("t = 0").withColumns({"_low": F.col("x") - caliper, "_high": F.col("x") + caliper}).withColumn("r", F.explode(F.sequence(low, high))).drop("_low", "_high")

    def count(part: pd.DataFrame) -> pd.DataFrame:
        arms = [_arm(*(part.loc[part["t"] == a, name].to_numpy() for name in ("x", "uid", "far", "mate"))) for a in (1, 0)]
        return pd.DataFrame({"n": [count_blocking(*arms, caliper)]})

    found = t.unionByName(c).groupBy("r").applyInPandas(count, "n long")
    # Edges of the result itself never block, even where a result holds a control twice.
    tt, cc = (rows.where(f"t = {a}").select(F.col("uid").alias(f"{p}_uid"), *(F.col(n).alias(f"{p}_{n}") for n in ("x", "far", "mate"))) for a, p in ((1, "t"), (0, "c")))
    d = F.abs(F.col("t_x") - F.col("c_x"))
    c_open = (F.col("c_far") > d) | ((F.col("c_far") == d) & (F.col("c_mate") > F.col("t_uid")))
    t_open = (F.col("t_far") > d) | ((F.col("t_far") == d) & (F.col("t_mate") > F.col("c_uid")))
    own = result.select("t_uid", "c_uid").distinct().join(tt, "t_uid").join(cc, "c_uid").where((d < F.lit(caliper)) & c_open & t_open)
    counts = found.unionByName(own.select(F.lit(-1).cast("long").alias("n")))
    return counts.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("blocking_edges"))
