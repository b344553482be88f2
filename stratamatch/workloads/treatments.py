"""Several treatments: correlation, factoring, lattice, preparation, sub-populations."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.treatments import conjunction
from ..operators.effects import stratified_effect
from ..operators.lattice import Lattice, base_cuboid, cube_baseline as cube, strata_of
from ..operators.multi import cem_from_factored, factor, partition_treatments, phi_matrix as phi, phi_values, summaries_multi
from ..operators.prepare import answer_online, answers, prepare, refresh, refreshed
from ..operators.strata import cem, cem_shared, overlapping, summarize
from ..sources.shared import materialized, new_folder
from ..sources.units import SHARED, TREATMENTS, line_treatments, line_units
from . import query
from .effects import REV, scaled
from .oracle import difference, strata, units

GROUP = ("t_bulk", "t_combo", "t_disc")
KEYS = {t: ", ".join(line_treatments().covariates[t]) for t in TREATMENTS}


@query(units("\nUNION ALL\n".join(f"""SELECT '{a}' AS t_a, '{b}' AS t_b, n11, n10, n01, n00, round((CAST(n11 AS DOUBLE) * n00 - CAST(n10 AS DOUBLE) * n01) / nullif(sqrt(CAST(n11 + n10 AS DOUBLE) * (n01 + n00) * (n11 + n01) * (n10 + n00)), 0), 9) AS phi
FROM (SELECT count(*) FILTER ({a} = 1 AND {b} = 1) AS n11, count(*) FILTER ({a} = 1 AND {b} = 0) AS n10, count(*) FILTER ({a} = 0 AND {b} = 1) AS n01, count(*) FILTER ({a} = 0 AND {b} = 0) AS n00 FROM units)""" for i, a in enumerate(TREATMENTS) for b in TREATMENTS[i + 1 :])))
def phi_matrix(spark, folder):
    return phi(line_units(spark, folder), TREATMENTS).withColumn("phi", F.round("phi", 9))


@query("SELECT * FROM (VALUES (1, 't_bulk'), (1, 't_combo'), (1, 't_disc'), (2, 't_heavy'), (2, 't_urgent')) AS v(group_id, treatment)")
def treatment_partition(spark, folder):
    """Groups of correlated treatments with shared covariates."""
    groups = partition_treatments(phi_values(line_units(spark, folder), TREATMENTS), line_treatments())
    return spark.createDataFrame([(i + 1, t) for i, (g, _) in enumerate(groups) for t in g], "group_id int, treatment string")


_FACTOR = f"""factored AS (SELECT *, max(uid) OVER w AS supersubclass FROM units WINDOW w AS (PARTITION BY {", ".join(SHARED)})
QUALIFY min(t_bulk) OVER w <> max(t_bulk) OVER w OR min(t_combo) OVER w <> max(t_combo) OVER w OR min(t_disc) OVER w <> max(t_disc) OVER w)"""


@query(units("SELECT uid, supersubclass FROM factored", _FACTOR))
def factored_view(spark, folder):
    return factor(line_units(spark, folder), line_treatments(), GROUP).select("uid", "supersubclass")


@query(units("SELECT uid, supersubclass FROM factored", _FACTOR))
def factored_view_window(spark, folder):
    return factor(line_units(spark, folder), line_treatments(), GROUP, plan="window").select("uid", "supersubclass")


def _each_sql(source="units", where="true"):
    return "\nUNION ALL\n".join(f"SELECT '{t}' AS treatment, uid, subclass FROM (SELECT uid, max(uid) OVER w AS subclass FROM {source} WHERE {t} IS NOT NULL AND ({where}) WINDOW w AS (PARTITION BY {KEYS[t]}) QUALIFY min({t}) OVER w <> max({t}) OVER w)" for t in GROUP)


@query(units(_each_sql()))
def cem_naive_multi(spark, folder):
    """Baseline: one independent matching per treatment."""
    u, ts = line_units(spark, folder), line_treatments()
    out = None
    for t in GROUP:
        one = cem(u, ts.spec(t)).select(F.lit(t).alias("treatment"), "uid", "subclass")
        out = one if out is None else out.unionByName(one)
    return out


@query(units(_each_sql()))
def mcem_each(spark, folder):
    """The same from factored rows."""
    ts = line_treatments()
    view = materialized(factor(line_units(spark, folder), ts, GROUP), "factored")
    out = None
    for t in GROUP:
        one = cem_from_factored(view, ts, GROUP, t).select(F.lit(t).alias("treatment"), "uid", "subclass")
        out = one if out is None else out.unionByName(one)
    return out


@query(units("\nUNION ALL\n".join(f"SELECT '{t}' AS treatment, p_brand, p_type, c_mktsegment, subclass, n1, n0 FROM s_{t}" for t in ("t_bulk", "t_urgent")), *(strata(t, "p_brand, p_type, c_mktsegment", values=(), name=f"s_{t}") for t in ("t_bulk", "t_urgent"))))
def cem_shared_x(spark, folder):
    """Treatments with the same covariates in one aggregate."""
    return cem_shared(line_units(spark, folder), "uid", ("t_bulk", "t_urgent"), ("p_brand", "p_type", "c_mktsegment"))


def _effects_sql(where="true", names=TREATMENTS, keys=KEYS):
    parts = [strata(t, keys[t], name=f"s_{t}", where=where) for t in names]
    rest = "\nUNION ALL\n".join(f"SELECT '{t}' AS treatment, count(*) AS strata, CAST(coalesce(sum(n), 0) AS BIGINT) AS n, round(sum(n * {difference('y_rev')}) / CAST(sum(n) AS DOUBLE) / 10000, 6) AS ate_y_rev FROM s_{t}" for t in names)
    return units(rest, *parts)


def _effect_rows(summaries):
    out = None
    for t, s in sorted(summaries.items()):
        one = scaled(stratified_effect(s, ("y_rev",)), **REV).select(F.lit(t).alias("treatment"), "strata", "n", "ate_y_rev")
        out = one if out is None else out.unionByName(one)
    return out


def _multi(spark, folder, ts, plan="auto"):
    u = materialized(_narrow(line_units(spark, folder), ts), "narrow")
    groups = partition_treatments(phi_values(u, TREATMENTS), ts)
    return _effect_rows(summaries_multi(u, ts, groups, lambda df: materialized(df, "shared"), plan))


@query(_effects_sql())
def cem_multi_effects(spark, folder):
    """Five treatments by correlation and grouping; the rows are joined once into a narrow table, and
    groups are factored where that drops rows."""
    return _multi(spark, folder, line_treatments())


@query(_effects_sql())
def cem_multi_effects_rows(spark, folder):
    """The same by factored rows."""
    return _multi(spark, folder, line_treatments(), "rows")


@query(_effects_sql())
def cem_multi_effects_cells(spark, folder):
    """The same by cells."""
    return _multi(spark, folder, line_treatments(), "cells")


_DAYS = {t: ", ".join(line_treatments(by_day=True).covariates[t]) for t in TREATMENTS}


@query(_effects_sql(keys=_DAYS))
def cem_multi_effects_days(spark, folder):
    """The same with the day of shipping: most supergroups have one arm and go."""
    return _multi(spark, folder, line_treatments(by_day=True))


@query(_effects_sql(keys=_DAYS))
def cem_naive_effects_days(spark, folder):
    """Baseline: one independent matching per treatment."""
    u, ts = line_units(spark, folder), line_treatments(by_day=True)
    return _effect_rows({t: overlapping(summarize(u, ts.spec(t))) for t in TREATMENTS})


def _narrow(units_of, ts):
    """The columns that matching on these treatments reads."""
    own = dict.fromkeys((ts.id, *ts.covariates, *(c for x in ts.covariates.values() for c in x), *ts.outcomes))
    return units_of.select(*own)


@query(_effects_sql())
def cem_naive_effects(spark, folder):
    u, ts = line_units(spark, folder), line_treatments()
    return _effect_rows({t: overlapping(summarize(u, ts.spec(t))) for t in TREATMENTS})


DIMS = ("p_brand", "c_mktsegment", "o_orderstatus")
_CELL = "CAST(GROUPING_ID(p_brand, c_mktsegment, o_orderstatus) AS BIGINT) AS grouping_id, p_brand, c_mktsegment, o_orderstatus, max(uid) AS max_id, count(*) AS n, count(*) FILTER (t_bulk = 1) AS n1_t_bulk, count(*) FILTER (t_bulk = 0) AS n0_t_bulk"
_CELLS = ("grouping_id", *DIMS, "max_id", "n", "n1_t_bulk", "n0_t_bulk")


def _lattice(spark, folder):
    u = line_units(spark, folder)
    return Lattice(base_cuboid(u, DIMS, "uid", ("t_bulk",)), DIMS, lambda df: materialized(df, "cuboid"))


@query(units(f"SELECT {_CELL} FROM units GROUP BY GROUPING SETS ((p_brand, c_mktsegment, o_orderstatus), (p_brand, c_mktsegment), (p_brand), (o_orderstatus), ())"))
def lattice_cells(spark, folder):
    """Asked cuboids, each rolled up from its smallest ancestor."""
    lat = _lattice(spark, folder)
    lat.build([("p_brand", "c_mktsegment"), ("p_brand",), ("o_orderstatus",), ()])
    return lat.cells().select(*_CELLS)


@query(units(f"SELECT {_CELL} FROM units GROUP BY CUBE (p_brand, c_mktsegment, o_orderstatus)"))
def cube_baseline(spark, folder):
    return cube(line_units(spark, folder), DIMS, "uid", ("t_bulk",)).select(*_CELLS)


@query(units("SELECT p_brand, c_mktsegment, subclass, n, n1, n0 FROM strata", strata(keys="p_brand, c_mktsegment", values=())))
def cem_lattice(spark, folder):
    """Strata of a treatment from the lattice."""
    return strata_of(_lattice(spark, folder).cuboid(("p_brand", "c_mktsegment")), "t_bulk", ("p_brand", "c_mktsegment"))


_CONJ = ("t_bulk", "t_disc", "t_urgent")


def _conjunctions():
    """(parts, covariates): a conjunction is matched on the union of its parts' covariates."""
    from ..functions.treatments import enumerate_treatments

    own = line_treatments().covariates
    return [(c, tuple(dict.fromkeys(x for t in c for x in own[t]))) for c in enumerate_treatments(_CONJ)]


def _conj_sql():
    out = []
    for c, keys in _conjunctions():
        one, zero = " AND ".join(f"{x} = 1" for x in c), " OR ".join(f"{x} = 0" for x in c)
        arms = "".join(f", CAST(sum(y_rev) FILTER ({w}) AS DOUBLE) AS s{a}, count(*) FILTER ({w}) AS n{a}" for a, w in ((1, f"({one})"), (0, f"({zero}) AND NOT coalesce({one}, false)")))
        out.append(f"SELECT '{','.join(c)}' AS treatment, '{','.join(keys)}' AS covariates, count(*) AS strata, CAST(coalesce(sum(n1), 0) AS BIGINT) AS n1, CAST(coalesce(sum(n0), 0) AS BIGINT) AS n0, round(sum((n1 + n0) * (s1 / n1 - s0 / n0)) / CAST(sum(n1 + n0) AS DOUBLE) / 10000, 6) AS ate_y_rev FROM (SELECT {', '.join(keys)}{arms} FROM units GROUP BY {', '.join(keys)}) WHERE n1 > 0 AND n0 > 0")
    return units("\nUNION ALL\n".join(out))


def conjunction_effects(units_of, names, conjunctions, outcome="y_rev"):
    """Effect of every conjunction of treatments on the union of its parts' covariates, from one
    base cuboid whose dimensions are all covariates and the treatments' values; cuboids of fewer
    dimensions come from their smallest ancestor."""
    covariates = list(dict.fromkeys(x for _, keys in conjunctions for x in keys))
    dims = (*covariates, *names)
    base = units_of.groupBy(*dims).agg(F.count("*").alias("n"), F.sum(outcome).alias("y"))
    lattice = Lattice(base, dims, lambda df: materialized(df, "cuboid"))
    lattice.build([(*keys, *c) for c, keys in conjunctions])
    out = None
    for c, keys in conjunctions:
        cells = lattice.cuboid((*keys, *c)).withColumn("t", conjunction(*c))
        arm = lambda a, v: F.sum(F.when(F.col("t") == a, F.col(v)))
        both = cells.groupBy(*keys).agg(*(F.coalesce(arm(a, "n"), F.lit(0)).alias(f"n{a}") for a in (1, 0)), *(arm(a, "y").alias(f"sum{a}_y") for a in (1, 0)))
        one = stratified_effect(both.where("n1 > 0 and n0 > 0").withColumn("n", F.col("n1") + F.col("n0")), ("y",))
        one = one.select(F.lit(",".join(c)).alias("treatment"), F.lit(",".join(keys)).alias("covariates"), "strata", "n1", "n0", F.round(F.col("ate_y") / 10000, 6).alias("ate_y_rev"))
        out = one if out is None else out.unionByName(one)
    return out


@query(_conj_sql())
def lattice_conjunctions(spark, folder):
    """All conjunctions of three treatments, each on the union of its parts' covariates."""
    return conjunction_effects(line_units(spark, folder), _CONJ, _conjunctions())


def _prepared(spark, folder, mode="factored"):
    path = new_folder(spark, "prepared")
    prepare(materialized(line_units(spark, folder), "units"), line_treatments(), path, mode)
    return path


@query(units("SELECT uid, supersubclass FROM factored", _FACTOR))
def prepared_rows(spark, folder):
    """Factored rows of the first group after preparation."""
    return spark.read.parquet(f"{_prepared(spark, folder)}/v1/rows-0").select("uid", "supersubclass")


@query(units(_each_sql()))
def prepared_matched(spark, folder):
    """The alternative preparation: matched rows of every treatment."""
    path, out = _prepared(spark, folder, "matched"), None
    for t in GROUP:
        one = spark.read.parquet(f"{path}/matched-{t}").select(F.lit(t).alias("treatment"), "uid", "subclass")
        out = one if out is None else out.unionByName(one)
    return out


KEY_WHERE, ROW_WHERE = "c_mktsegment = 'BUILDING'", "site = 'ASIA'"


def _answers(spark, folder, where):
    return _scaled_answers(answers(spark, _prepared(spark, folder), TREATMENTS, where))


def _scaled_answers(df):
    return scaled(df, **REV).select("treatment", "strata", "n", "ate_y_rev")


@query(_effects_sql(KEY_WHERE))
def subpop_key_predicate(spark, folder):
    """Sub-population by a covariate: answered from cells."""
    return _answers(spark, folder, KEY_WHERE)


@query(_effects_sql(ROW_WHERE))
def subpop_row_predicate(spark, folder):
    """Sub-population by another column: factored rows are filtered and grouped again."""
    return _answers(spark, folder, ROW_WHERE)


@query(_effects_sql("ship_date >= TIMESTAMP '1998-01-01'"))
def subpop_since(spark, folder):
    """A date bound inside a week is no function of the key: routed to rows."""
    return _answers(spark, folder, "ship_date >= timestamp_ntz'1998-01-01'")


@query(_effects_sql(ROW_WHERE))
def subpop_online(spark, folder):
    """Baseline without preparation."""
    u, ts, out = line_units(spark, folder), line_treatments(), None
    for t in TREATMENTS:
        one = scaled(answer_online(u, ts, t, ROW_WHERE), **REV).select(F.lit(t).alias("treatment"), "strata", "n", "ate_y_rev")
        out = one if out is None else out.unionByName(one)
    return out


@query(units("SELECT p_brand, c_mktsegment, o_orderstatus, count(*) AS n, count(*) FILTER (t_bulk = 1) AS n1_t_bulk, max(uid) AS max_id FROM units GROUP BY p_brand, c_mktsegment, o_orderstatus"))
def refreshed_cells(spark, folder):
    """Cells of the first part of the rows, and those of the rest added."""
    u = line_units(spark, folder)
    cells = base_cuboid(u.where("h < 700"), DIMS, "uid", ("t_bulk",))
    return refreshed(cells, u.where("h >= 700"), DIMS, "uid", ("t_bulk",)).select(*DIMS, "n", "n1_t_bulk", "max_id")


def _refreshed(spark, folder):
    """A folder prepared on the first part of the rows and refreshed with the rest."""
    u, path = materialized(line_units(spark, folder), "units"), new_folder(spark, "prepared")
    prepare(u.where("h < 700"), line_treatments(), path)
    refresh(spark, path, u.where("h >= 700"))
    return path


@query(_effects_sql())
def prepared_refresh(spark, folder):
    """Effects of all treatments after a refresh, as on rows prepared at once."""
    return _scaled_answers(answers(spark, _refreshed(spark, folder), TREATMENTS))


@query(_effects_sql(ROW_WHERE))
def prepared_refresh_rows(spark, folder):
    """A row predicate after a refresh: rows of supergroups that the new rows complete take part."""
    return _scaled_answers(answers(spark, _refreshed(spark, folder), TREATMENTS, ROW_WHERE))


@query(_effects_sql())
def prepared_effects(spark, folder):
    """Effects of all treatments from prepared strata."""
    return _scaled_answers(answers(spark, _prepared(spark, folder), TREATMENTS))


@query(units("""SELECT 'factoring' AS step, (SELECT count(*) FROM units) AS rows_in, (SELECT count(*) FROM factored) AS rows_out""", _FACTOR))
def pruning_report(spark, folder):
    """Rows that factoring keeps."""
    u = line_units(spark, folder)
    kept = factor(u, line_treatments(), GROUP).agg(F.count("*").alias("rows_out"))
    return u.agg(F.lit("factoring").alias("step"), F.count("*").alias("rows_in")).crossJoin(kept)  # one row each
