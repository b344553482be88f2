"""Units: treatments, integration in time, samples, coarsening, scores."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.coarsening import cut, equal_frequency, equal_width
from ..functions.treatments import conjunction, enumerate_treatments
from ..operators.effects import stratified_effect
from ..operators.propensity import cell_propensity, fit_propensity, score_expr, trim
from ..operators.strata import overlapping, summarize
from ..operators.temporal import asof_attach, bucket_attach, interval_pairs, prior_count, prior_count_bucketed
from ..plans.spec import UnitSpec, violations
from ..sources.units import hash_sample, line_spec, line_units, scored_units, trips_and_readings
from . import query
from .oracle import SCORED, units

ALL = ("t_bulk", "t_disc", "t_urgent", "t_heavy", "t_combo", "t_rare")


@query(units("\nUNION ALL\n".join(f"SELECT '{t}' AS treatment, count({t}) AS defined, CAST(coalesce(sum({t}), 0) AS BIGINT) AS treated FROM units" for t in ALL)))
def unit_treatments(spark, folder):
    """Defined and treated rows of every treatment, by one aggregate."""
    row = line_units(spark, folder).agg(*(c for t in ALL for c in (F.count(t).alias(f"d_{t}"), F.coalesce(F.sum(t), F.lit(0)).cast("long").alias(f"s_{t}"))))
    each = F.array(*(F.struct(F.lit(t).alias("treatment"), F.col(f"d_{t}").alias("defined"), F.col(f"s_{t}").alias("treated")) for t in ALL))
    return row.select(F.explode(each).alias("e")).select("e.*")


@query(units("SELECT t_bulk, t_disc, t_combo, count(*) AS n FROM units GROUP BY ALL"))
def conjunction_counts(spark, folder):
    return line_units(spark, folder).groupBy("t_bulk", "t_disc", "t_combo").agg(F.count("*").alias("n"))


LATTICE = enumerate_treatments(("t_bulk", "t_disc", "t_urgent"))


@query(units("\nUNION ALL\n".join(f"SELECT '{','.join(c)}' AS treatment, {len(c)} AS size, count(*) FILTER ({' AND '.join(f'{t} = 1' for t in c)}) AS treated, count(*) FILTER ({' OR '.join(f'{t} = 0' for t in c)}) AS controls FROM units" for c in LATTICE)))
def treatment_lattice(spark, folder):
    """All conjunctions of three dichotomised attributes with the units in either arm, by one aggregate."""
    counts = [F.count_if(conjunction(*c) == a).alias(f"{p}_{i}") for i, c in enumerate(LATTICE) for a, p in ((1, "n1"), (0, "n0"))]
    each = F.array(*(F.struct(F.lit(",".join(c)).alias("treatment"), F.lit(len(c)).alias("size"), F.col(f"n1_{i}").alias("treated"), F.col(f"n0_{i}").alias("controls")) for i, c in enumerate(LATTICE)))
    return line_units(spark, folder).agg(*counts).select(F.explode(each).alias("e")).select("e.*")


@query(units("SELECT uid, y_rev - 10 * total // 100 AS y_net FROM units"))
def outcome_adjusted(spark, folder):
    """Derived outcome: own revenue less a part that is inherited from the order."""
    return line_units(spark, folder).select("uid", (F.col("y_rev") - F.expr("10 * total div 100")).alias("y_net"))


@query(units("SELECT uid, h FROM units WHERE h < 50"))
def sample_units(spark, folder):
    return hash_sample(line_units(spark, folder), 50).select("uid", "h")


@query("SELECT CAST(0 AS BIGINT) AS null_ids, CAST(0 AS BIGINT) AS repeated_ids, CAST(0 AS BIGINT) AS bad_treatment, CAST(0 AS BIGINT) AS null_y_rev, CAST(0 AS BIGINT) AS null_y_ret")
def unit_validation(spark, folder):
    return violations(line_units(spark, folder), line_spec())


TRIPS = """ev AS (SELECT *, CAST(user_id % 5 AS INTEGER) AS site, CAST(epoch(date_trunc('second', ts)) AS BIGINT) AS sec FROM events),
trips AS (SELECT * FROM ev WHERE event_type = 'purchase'), readings AS (SELECT * FROM ev WHERE event_type = 'error')"""
LATEST = TRIPS + """,
latest AS (SELECT t.event_id, t.site, t.user_id, t.value, t.sec, r.sec AS r_sec, r.value AS r_value
  FROM trips t LEFT JOIN (SELECT * FROM readings QUALIFY row_number() OVER (PARTITION BY site, sec ORDER BY event_id DESC) = 1) r
  ON t.site = r.site AND r.sec <= t.sec AND t.sec - r.sec <= 7200 QUALIFY row_number() OVER (PARTITION BY t.event_id ORDER BY r.sec DESC NULLS LAST) = 1)"""


def _asof(spark, folder):
    trips, readings, _ = trips_and_readings(spark, folder)
    return asof_attach(trips.select("event_id", "site", "user_id", "value", "sec"), readings.select("event_id", "site", "value", "sec"), ["site"], "sec", ["value"], 7200, tie="event_id")


@query(f"WITH {LATEST} SELECT event_id, site, sec, r_sec AS reading_ts, r_value AS reading_value FROM latest")
def asof_units(spark, folder):
    return _asof(spark, folder).select("event_id", "site", "sec", "reading_ts", "reading_value")


@query(f"""WITH {LATEST}, u AS (SELECT event_id AS uid, site, CAST(floor((sec % 86400) / 21600) AS INTEGER) AS part, CASE WHEN r_value > 60 THEN 1 WHEN r_value < 30 THEN 0 END AS t, CAST(round(value * 100) AS BIGINT) AS y FROM latest),
s AS (SELECT site, part, count(*) AS n, count(*) FILTER (t = 1) AS n1, count(*) FILTER (t = 0) AS n0, sum(y) FILTER (t = 1) AS s1, sum(y) FILTER (t = 0) AS s0 FROM u WHERE t IS NOT NULL GROUP BY ALL HAVING n1 > 0 AND n0 > 0)
SELECT count(*) AS strata, CAST(sum(n) AS BIGINT) AS n, CAST(sum(n1) AS BIGINT) AS n1, CAST(sum(n0) AS BIGINT) AS n0, round(sum(n * (CAST(s1 AS DOUBLE) / n1 - CAST(s0 AS DOUBLE) / n0)) / CAST(sum(n) AS DOUBLE) / 100, 6) AS ate_y FROM s""")
def ate_asof(spark, folder):
    """Effect of a high reading before a trip on its value, within site and quarter of the day."""
    t = F.when(F.col("reading_value") > 60, 1).when(F.col("reading_value") < 30, 0)
    u = _asof(spark, folder).select(F.col("event_id").alias("uid"), "site", F.floor((F.col("sec") % 86400) / 21600).cast("int").alias("part"), t.alias("t"), F.round(F.col("value") * 100).cast("long").alias("y"))
    spec = UnitSpec("uid", "t", ("site", "part"), ("y",))
    return stratified_effect(overlapping(summarize(u, spec)), ("y",)).withColumn("ate_y", F.round(F.col("ate_y") / 100, 6))


@query(f"WITH {TRIPS} SELECT t.event_id, t.site, CAST(t.sec // 3600 AS BIGINT) AS bucket, round(avg(r.value), 6) AS mean_value, nullif(count(r.value), 0) AS readings FROM trips t LEFT JOIN readings r ON t.site = r.site AND t.sec // 3600 = r.sec // 3600 GROUP BY ALL")
def bucket_units(spark, folder):
    trips, readings, _ = trips_and_readings(spark, folder)
    out = bucket_attach(trips.select("event_id", "site", "sec"), readings.select("site", "sec", "value"), ["site"], "sec", ["value"])
    return out.select("event_id", "site", "bucket", F.round("mean_value", 6).alias("mean_value"), "readings")


@query(f"""WITH {TRIPS} SELECT event_id, count(*) OVER (PARTITION BY site ORDER BY sec RANGE BETWEEN 3600 PRECEDING AND 1 PRECEDING) AS site_traffic,
count(*) OVER (PARTITION BY site, user_id ORDER BY sec RANGE BETWEEN 3600 PRECEDING AND 1 PRECEDING) AS carrier_traffic FROM ev""")
def traffic_features(spark, folder):
    """Events of the same site, and of the same site and user, in the hour before (hot keys split by time)."""
    _, _, events = trips_and_readings(spark, folder)
    rows = prior_count_bucketed(events.select("event_id", "site", "user_id", "sec"), ["site"], "sec", "site_traffic")
    return rows.withColumn("carrier_traffic", prior_count(["site", "user_id"], "sec")).select("event_id", "site_traffic", "carrier_traffic")


@query(f"WITH {TRIPS} SELECT t.event_id AS trip_id, r.event_id AS reading_id FROM trips t JOIN readings r ON t.site = r.site AND t.sec - r.sec BETWEEN 0 AND 1800")
def interval_join(spark, folder):
    trips, readings, _ = trips_and_readings(spark, folder)
    pairs = interval_pairs(trips.withColumnRenamed("event_id", "trip_id"), readings.withColumnRenamed("event_id", "reading_id"), ["site"], "sec", "trip_id", "reading_id", 1800)
    return pairs.select("trip_id", "reading_id")


@query(units("SELECT uid, CAST(CASE WHEN acct < 0 THEN 1 WHEN acct < 250000 THEN 2 WHEN acct < 500000 THEN 3 ELSE 4 END AS INTEGER) AS bucket FROM units"))
def coarsen_cutpoints(spark, folder):
    return line_units(spark, folder).select("uid", cut(F.col("acct"), (0, 250_000, 500_000)).alias("bucket"))


@query(units("SELECT bucket, count(*) AS n FROM (SELECT CAST(greatest(1, least(10, floor((acct + 100000) * 10 / 1200000) + 1)) AS INTEGER) AS bucket FROM units) GROUP BY 1"))
def coarsen_equal_width(spark, folder):
    return line_units(spark, folder).groupBy(equal_width(F.col("acct"), 10, -100_000, 1_100_000).alias("bucket")).agg(F.count("*").alias("n"))


@query(units("SELECT bucket, count(*) AS n FROM (SELECT CAST(1 + len(list_filter(q, lambda x: x <= total)) AS INTEGER) AS bucket FROM units, (SELECT quantile_cont(total, [0.25, 0.5, 0.75]) AS q FROM units)) GROUP BY 1"))
def coarsen_equal_freq(spark, folder):
    rows = line_units(spark, folder).select("total")
    return rows.groupBy(cut(F.col("total"), equal_frequency(rows, "total", 4)).alias("bucket")).agg(F.count("*").alias("n"))


@query(units("SELECT uid, round(1 / (1 + exp(-(-1 + 0.002 * size + 0.0000001 * total))), 9) AS ps FROM units"))
def ps_linear(spark, folder):
    return line_units(spark, folder).select("uid", F.round(score_expr({"size": 0.002, "total": 0.0000001}, -1.0), 9).alias("ps"))


@query(units("SELECT uid, round(avg(t_bulk) OVER (PARTITION BY p_brand, p_type, o_orderstatus), 9) AS ps FROM units WHERE t_bulk IS NOT NULL"))
def ps_cell(spark, folder):
    spec = UnitSpec("uid", "t_bulk", ("p_brand", "p_type", "o_orderstatus"))
    return cell_propensity(line_units(spark, folder), spec).select("uid", F.round("ps", 9).alias("ps"))


@query(units("SELECT uid, ps FROM scored WHERE ps BETWEEN 100000 AND 900000", SCORED))
def ps_trim(spark, folder):
    return trim(scored_units(line_units(spark, folder)), "ps", 100_000, 900_000).select("uid", "ps")


@query(units("SELECT count(*) AS n, CAST(0 AS BIGINT) AS off FROM scored", SCORED))
def ps_mean_calibration(spark, folder):
    """A fitted logistic score has the treated share as its mean (off: 1 if it misses by 1e-6)."""
    rows = scored_units(line_units(spark, folder)).withColumn("x1", F.col("total") / 1e7).withColumn("x2", F.col("size") / 10)
    score, _, _ = fit_propensity(rows, UnitSpec("uid", "t_bulk", ()), numeric=("x1", "x2"), categorical=("o_orderstatus",))
    gap = F.abs(F.avg(score) - F.avg("t_bulk"))
    return rows.agg(F.count("*").alias("n"), F.when(gap < 1e-6, 0).otherwise(1).cast("long").alias("off"))


