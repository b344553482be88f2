"""Operators that users of the methods need around them."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.strata import cem, overlapping, summarize
from ..plans.spec import UnitSpec
from ..sources.catalog import TABLES, table
from ..sources.units import TREATMENTS, line_spec, line_units, trips_and_readings
from ..streaming.live import sessions, windowed_traffic
from . import query
from .oracle import COARSE, strata, units


@query("\nUNION ALL\n".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def scan_counts(spark, folder):
    return reduce(DataFrame.unionByName, (table(spark, folder, t).agg(F.lit(t).alias("name"), F.count("*").alias("n")) for t in TABLES))


@query("SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity > 40 OR l_quantity < 20")
def filter_dead_zone(spark, folder):
    """The dead zone as a filter that reaches the scan."""
    return table(spark, folder, "lineitem").where("l_quantity > 40 or l_quantity < 20").select("l_orderkey", "l_linenumber", "l_quantity")


@query(units("SELECT t_disc, count(*) AS n FROM (SELECT a.t_disc FROM units a JOIN (SELECT t_disc, min(uid) AS m FROM units GROUP BY t_disc) b ON a.t_disc IS NOT DISTINCT FROM b.t_disc) GROUP BY t_disc"))
def null_safe_key(spark, folder):
    """Null keys join null keys."""
    from ..operators.strata import attach

    u = line_units(spark, folder).select("uid", "t_disc")
    return attach(u, u.groupBy("t_disc").agg(F.min("uid").alias("m")), ("t_disc",), {"m": "m"}).groupBy("t_disc").agg(F.count("*").alias("n"))


@query(units("SELECT uid, seq, l_orderkey, p_brand, p_type, c_mktsegment, o_orderstatus, site, t_bulk, t_disc, t_urgent, t_heavy, t_combo, t_rare, y_rev, y_ret, total, acct, tax, cx_total, cx_tax, datediff('day', DATE '1970-01-01', cx_week) AS week_day FROM units"))
def join_units(spark, folder):
    """The integrated units."""
    return line_units(spark, folder).select("uid", "seq", "l_orderkey", "p_brand", "p_type", "c_mktsegment", "o_orderstatus", "site", "t_bulk", "t_disc", "t_urgent", "t_heavy", "t_combo", "t_rare", "y_rev", "y_ret", "total", "acct", "tax", "cx_total", "cx_tax", F.unix_date("cx_week").cast("long").alias("week_day"))


@query(units(f"SELECT uid FROM units WHERE t_bulk IS NOT NULL WINDOW w AS (PARTITION BY {COARSE}, t_bulk IS NULL) QUALIFY min(t_bulk) OVER w = max(t_bulk) OVER w"))
def unmatched_units(spark, folder):
    """Units with a defined treatment that found no stratum with both arms (anti-join)."""
    u = line_units(spark, folder).where("t_bulk is not null")
    return u.select("uid").join(cem(u, line_spec()).select("uid"), "uid", "left_anti")


@query(units(f"SELECT uid FROM units WHERE t_bulk IS NOT NULL WINDOW w AS (PARTITION BY {COARSE}, t_bulk IS NULL) QUALIFY min(t_bulk) OVER w = max(t_bulk) OVER w"))
def dropped_except(spark, folder):
    """The same by a set operation."""
    u = line_units(spark, folder).where("t_bulk is not null")
    return u.select("uid").exceptAll(cem(u, line_spec()).select("uid"))


_MATCHED_UID = "SELECT uid FROM (SELECT uid, min({t}) OVER w AS a, max({t}) OVER w AS b FROM units WHERE {t} IS NOT NULL WINDOW w AS (PARTITION BY p_brand, p_type, c_mktsegment, cx_week)) WHERE a <> b"


@query(units(f"{_MATCHED_UID.format(t='t_bulk')} UNION {_MATCHED_UID.format(t='t_disc')}"))
def matched_union(spark, folder):
    """Units matched for at least one of two treatments."""
    u = line_units(spark, folder)
    keys = ("p_brand", "p_type", "c_mktsegment", "cx_week")
    return cem(u, UnitSpec("uid", "t_bulk", keys)).select("uid").union(cem(u, UnitSpec("uid", "t_disc", keys)).select("uid")).distinct()


@query("WITH ev AS (SELECT *, CAST(user_id % 5 AS INTEGER) AS site, CAST(epoch(date_trunc('second', ts)) AS BIGINT) AS sec FROM events) SELECT t.event_id FROM ev t WHERE event_type = 'purchase' AND NOT EXISTS (SELECT 1 FROM ev r WHERE r.event_type = 'error' AND r.site = t.site AND r.sec // 3600 = t.sec // 3600)")
def left_unmatched_readings(spark, folder):
    """Trips without a reading in their hour (outer join)."""
    trips, readings, _ = trips_and_readings(spark, folder)
    hour = F.floor(F.col("sec") / 3600).cast("long").alias("hour")
    have = readings.select("site", hour).distinct().withColumn("found", F.lit(1))
    return trips.select("event_id", "site", hour).join(have, ["site", "hour"], "left").where("found is null").select("event_id")


@query(units("SELECT CAST(GROUPING_ID(site, c_mktsegment) AS BIGINT) AS gid, site, c_mktsegment, count(*) AS n, count(*) FILTER (t_bulk = 1) AS n1 FROM units GROUP BY ROLLUP (site, c_mktsegment)"))
def rollup_sites(spark, folder):
    return line_units(spark, folder).rollup("site", "c_mktsegment").agg(F.grouping_id().alias("gid"), F.count("*").alias("n"), F.count_if(F.col("t_bulk") == 1).alias("n1")).select("gid", "site", "c_mktsegment", "n", "n1")


@query(units("SELECT site, o_orderstatus, p_type, count(*) AS n FROM units GROUP BY GROUPING SETS ((site), (o_orderstatus, p_type))"))
def grouping_sets_x(spark, folder):
    return line_units(spark, folder).groupingSets([[F.col("site")], [F.col("o_orderstatus"), F.col("p_type")]], "site", "o_orderstatus", "p_type").agg(F.count("*").alias("n"))


@query(units("SELECT t_bulk, count(*) FILTER (t_urgent = 0) AS urgent_0, count(*) FILTER (t_urgent = 1) AS urgent_1 FROM units WHERE t_bulk IS NOT NULL GROUP BY t_bulk"))
def contingency_table(spark, folder):
    """Pivot of two treatments."""
    out = line_units(spark, folder).where("t_bulk is not null").groupBy("t_bulk").pivot("t_urgent", [0, 1]).count()
    return out.select("t_bulk", F.coalesce("0", F.lit(0)).alias("urgent_0"), F.coalesce("1", F.lit(0)).alias("urgent_1"))


@query("WITH ev AS (SELECT *, CAST(epoch(date_trunc('second', ts)) AS BIGINT) AS sec FROM events) SELECT event_id, sec - lag(sec) OVER w AS gap, lead(event_type) OVER w AS next_type FROM ev WINDOW w AS (PARTITION BY user_id ORDER BY sec, event_id)")
def event_gaps(spark, folder):
    _, _, events = trips_and_readings(spark, folder)
    w = Window.partitionBy("user_id").orderBy("sec", "event_id")
    return events.select("event_id", (F.col("sec") - F.lag("sec").over(w)).alias("gap"), F.lead("event_type").over(w).alias("next_type"))


@query(units("SELECT subclass, n, round(abs(CAST(sum1_total AS DOUBLE) / n1 - CAST(sum0_total AS DOUBLE) / n0) / 100, 4) AS gap FROM strata ORDER BY n * abs(CAST(sum1_total AS DOUBLE) / n1 - CAST(sum0_total AS DOUBLE) / n0) DESC, subclass LIMIT 10", strata(values=("total",))))
def worst_strata_top10(spark, folder):
    """The ten strata that add most to the imbalance (a report)."""
    s = overlapping(summarize(line_units(spark, folder), UnitSpec("uid", "t_bulk", line_spec().covariates, (), ("total",))))
    gap = F.abs(F.col("sum1_total").cast("double") / F.col("n1") - F.col("sum0_total").cast("double") / F.col("n0"))
    return s.orderBy((F.col("n") * gap).desc(), "subclass").limit(10).select("subclass", "n", F.round(gap / 100, 4).alias("gap"))


@query("SELECT p_partkey, upper(substring(p_brand, 1, 3)) || '-' || lower(p_type) AS key, md5(p_brand) AS digest, CAST(regexp_extract(p_brand, '[0-9]+') AS VARCHAR) AS number FROM part")
def string_keys(spark, folder):
    p = table(spark, folder, "part")
    return p.select("p_partkey", F.concat_ws("-", F.upper(F.substring("p_brand", 1, 3)), F.lower("p_type")).alias("key"), F.md5(F.col("p_brand").cast("binary")).alias("digest"), F.regexp_extract("p_brand", "[0-9]+", 0).alias("number"))


@query("SELECT o_orderkey, CAST(datediff('day', DATE '1970-01-01', CAST(date_trunc('month', o_orderdate) AS DATE)) AS INTEGER) AS month_day, CAST(dayofweek(o_orderdate) AS INTEGER) + 1 AS dow, CAST(datediff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(year(o_orderdate) AS INTEGER) AS year FROM orders")
def date_keys(spark, folder):
    o = table(spark, folder, "orders")
    return o.select("o_orderkey", F.unix_date(F.date_trunc("month", "o_orderdate").cast("date")).alias("month_day"), F.dayofweek("o_orderdate").alias("dow"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).alias("days"), F.year("o_orderdate").alias("year"))


@query(units("\nUNION ALL\n".join(f"SELECT uid, '{t}' AS treatment, {t} AS t FROM units WHERE {t} IS NOT NULL" for t in TREATMENTS)))
def array_unpivot_treatments(spark, folder):
    """Treatments as rows (one pass)."""
    each = F.explode(F.array(*(F.struct(F.lit(t).alias("treatment"), F.col(t).alias("t")) for t in TREATMENTS)))
    return line_units(spark, folder).select("uid", each.alias("e")).select("uid", "e.*").where("t is not null")


@query(units("SELECT t AS treatment, CAST(sum(v) AS BIGINT) AS treated FROM (" + " UNION ALL ".join(f"SELECT '{t}' AS t, coalesce({t}, 0) AS v FROM units" for t in TREATMENTS) + ") GROUP BY t"))
def treatment_map(spark, folder):
    """Per-treatment counters in a map."""
    row = line_units(spark, folder).agg(F.map_from_arrays(F.array(*map(F.lit, TREATMENTS)), F.array(*(F.sum(F.coalesce(F.col(t), F.lit(0))) for t in TREATMENTS))).alias("m"))
    return row.select(F.explode("m").alias("treatment", "treated"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def json_covariate(spark, folder):
    return table(spark, folder, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))


def _corr_sql(a, b):
    return f"round(covar_pop(CAST({a} AS DOUBLE), CAST({b} AS DOUBLE)) / nullif((stddev_pop({a}) FILTER ({b} IS NOT NULL)) * (stddev_pop({b}) FILTER ({a} IS NOT NULL)), 0), 9)"


_PAIRS = (("t_bulk", "t_disc"), ("t_combo", "t_bulk"), ("t_urgent", "t_heavy"))


@query(units("SELECT " + ", ".join(f"{_corr_sql(a, b)} AS {a[2:]}_{b[2:]}" for a, b in _PAIRS) + " FROM units"))
def corr_pairs(spark, folder):
    """phi is the correlation of the pairwise complete columns; null without variance."""

    def corr(a, b):
        x, y = (F.when(F.col(q).isNotNull(), F.col(p)).cast("double") for p, q in ((a, b), (b, a)))
        return F.round(F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y)), 9)

    return line_units(spark, folder).agg(*(corr(a, b).alias(f"{a[2:]}_{b[2:]}") for a, b in _PAIRS))


def _epochs(df, *keys):
    e = lambda c: F.unix_timestamp(F.col(c).cast("timestamp")).alias(c)
    return df.select(e("start"), e("end"), *keys, "n")


_SEC = "CAST(epoch(ts) AS DOUBLE)"


@query(f"SELECT CAST(floor({_SEC} / 3600) * 3600 AS BIGINT) AS start, CAST(floor({_SEC} / 3600) * 3600 + 3600 AS BIGINT) AS \"end\", CAST(user_id % 5 AS INTEGER) AS site, count(*) AS n FROM events GROUP BY ALL")
def tumbling_traffic(spark, folder):
    _, _, events = trips_and_readings(spark, folder)
    return _epochs(windowed_traffic(events, ["site"]), "site")


@query(f"SELECT CAST(s AS BIGINT) AS start, CAST(s + 3600 AS BIGINT) AS \"end\", site, count(*) AS n FROM (SELECT CAST(user_id % 5 AS INTEGER) AS site, unnest([floor({_SEC} / 900) * 900, floor({_SEC} / 900) * 900 - 900, floor({_SEC} / 900) * 900 - 1800, floor({_SEC} / 900) * 900 - 2700]) AS s FROM events) GROUP BY ALL")
def sliding_traffic(spark, folder):
    _, _, events = trips_and_readings(spark, folder)
    return _epochs(windowed_traffic(events, ["site"], slide="15 minutes"), "site")


@query("""SELECT CAST(floor(epoch(min(ts))) AS BIGINT) AS start, user_id, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""")
def session_units(spark, folder):
    _, _, events = trips_and_readings(spark, folder)
    return _epochs(sessions(events, ["user_id"]), "user_id").select("start", "user_id", "n")


@query(units("SELECT t.site, p.uid, p.total FROM (SELECT DISTINCT site FROM units) t, LATERAL (SELECT uid, total FROM units u WHERE u.site = t.site AND u.t_bulk = 1 ORDER BY total DESC, uid LIMIT 3) p"))
def lateral_top_treated(spark, folder):
    """A lateral join: the three treated units of the highest price of each site."""
    u = line_units(spark, folder).select("site", "uid", "total", "t_bulk")
    sites = u.select("site").distinct().alias("t")
    best = u.alias("u").where(F.col("u.site") == F.col("t.site").outer()).where("u.t_bulk = 1").orderBy(F.desc("u.total"), "u.uid").limit(3)
    return sites.lateralJoin(best.select("u.uid", "u.total")).select("t.site", "uid", "total")


@query(units("SELECT p_type, true AS near FROM units GROUP BY p_type"))
def approximate_strata(spark, folder):
    """Distinct strata by a sketch, within a tenth of the exact number."""
    rows = line_units(spark, folder).select("p_type", F.struct("p_brand", "c_mktsegment", "o_orderstatus").alias("k"))
    out = rows.groupBy("p_type").agg(F.approx_count_distinct("k", 0.02).alias("a"), F.count_distinct("k").alias("n"))
    return out.select("p_type", (F.abs(F.col("a") - F.col("n")) <= F.greatest(F.col("n") / 10, F.lit(2))).alias("near"))


@query(units("SELECT DISTINCT p_brand, p_type FROM units WHERE t_bulk = 1 INTERSECT SELECT DISTINCT p_brand, p_type FROM units WHERE t_bulk = 0"))
def overlapping_keys(spark, folder):
    """Keys that both arms have, by a set operation."""
    u = line_units(spark, folder)
    return u.where("t_bulk = 1").select("p_brand", "p_type").intersect(u.where("t_bulk = 0").select("p_brand", "p_type"))
