"""Effects and balance under the strata methods."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import balance, effects
from ..operators.effects import stratified_effect
from ..operators.strata import cem, exact_match as match_exactly, overlap_report as report, overlapping, summarize
from ..operators.subclass import subclassify
from ..operators.propensity import trim
from ..plans.spec import UnitSpec
from ..sources.units import document_units, line_spec, line_units, planted_units, scored_units
from . import query
from .oracle import COARSE, EXACT, PLANTED, SCORED, awmd, difference, effect, strata, totals, units

EM = ("p_partkey", "c_mktsegment", "tax", "o_orderstatus")


def scaled(df, **scales):
    """Outcomes back in their own units, rounded for comparison."""
    return df.select(*(F.round(F.col(c) / scales[c.split("_", 1)[1]], 4 if c.startswith("awmd") else 6).alias(c) if c.split("_", 1)[-1] in scales and c.split("_")[0] in ("ate", "awmd", "se", "normalised") else c for c in df.columns))


def _strata(spark, folder, t="t_bulk", keys=None, measured=("total", "acct"), overlap=True):
    spec = line_spec(t, keys, measured) if keys else line_spec(t, measured=measured)
    out = summarize(line_units(spark, folder), spec)
    return overlapping(out) if overlap else out


REV = {"y_rev": 10000.0, "y_ret": 1.0}


@query(units("""SELECT count(t_bulk) AS n, count(*) FILTER (t_bulk = 1) AS n1, count(*) FILTER (t_bulk = 0) AS n0,
round((avg(y_rev) FILTER (t_bulk = 1) - avg(y_rev) FILTER (t_bulk = 0)) / 10000, 6) AS ate_y_rev, round(avg(y_ret) FILTER (t_bulk = 1) - avg(y_ret) FILTER (t_bulk = 0), 6) AS ate_y_ret FROM units"""))
def ate_naive(spark, folder):
    return scaled(effects.naive_effect(line_units(spark, folder), line_spec()), **REV)


@query(units(f"SELECT {totals()}, {effect('y_rev', 10000.0)} FROM strata", strata()))
def ate_cem(spark, folder):
    return scaled(stratified_effect(_strata(spark, folder), ("y_rev",)), **REV)


@query(units(f"SELECT {totals()}, {effect('y_rev', 10000.0)}, {effect('y_ret', 1.0)} FROM strata", strata()))
def ate_two_outcomes(spark, folder):
    return scaled(stratified_effect(_strata(spark, folder), ("y_rev", "y_ret")), **REV)


@query(units(f"SELECT {totals()}, {effect('y_rev', 10000.0, 'n1')} FROM strata", strata()))
def att_cem(spark, folder):
    """Effect on the treated: strata weighted by their treated rows."""
    return scaled(stratified_effect(_strata(spark, folder), ("y_rev",), weights="treated"), **REV)


@query(units(f"SELECT {totals()}, {effect('y_rev', 10000.0)} FROM strata", strata(keys=EXACT)))
def ate_em(spark, folder):
    return scaled(stratified_effect(_strata(spark, folder, keys=EM), ("y_rev",)), **REV)


@query(units(f"""SELECT {totals()}, round(sum(n * {difference('y_rev')}) / CAST(sum(n) AS DOUBLE) / 10000, 4) AS ate_y_rev,
round(sqrt(sum(CAST(n AS DOUBLE) * n * (coalesce(v1, 0) / n1 + coalesce(v0, 0) / n0))) / CAST(sum(n) AS DOUBLE) / 10000, 4) AS se_y_rev FROM s""",
    f"""s AS (SELECT {COARSE}, count(*) AS n, count(*) FILTER (t_bulk = 1) AS n1, count(*) FILTER (t_bulk = 0) AS n0, CAST(sum(y_rev) FILTER (t_bulk = 1) AS BIGINT) AS sum1_y_rev, CAST(sum(y_rev) FILTER (t_bulk = 0) AS BIGINT) AS sum0_y_rev,
    var_samp(CAST(y_rev AS DOUBLE)) FILTER (t_bulk = 1) AS v1, var_samp(CAST(y_rev AS DOUBLE)) FILTER (t_bulk = 0) AS v0 FROM units WHERE t_bulk IS NOT NULL GROUP BY {COARSE} HAVING n1 > 0 AND n0 > 0)"""))  # fmt: skip
def ate_cem_se(spark, folder):
    out = effects.standard_error(line_units(spark, folder), line_spec(), "y_rev")
    return out.select("strata", "n", "n1", "n0", *(F.round(F.col(c) / 10000.0, 4).alias(c) for c in ("ate_y_rev", "se_y_rev")))


@query(units(f"""SELECT s.site, count(*) AS strata, CAST(sum(n) AS BIGINT) AS n, CAST(sum(n1) AS BIGINT) AS n1, CAST(sum(n0) AS BIGINT) AS n0, {effect('y_rev', 10000.0)}, {effect('y_ret', 1.0)}, round(any_value(share), 9) AS treated_share,
round(sum(n * {difference('y_rev')}) / CAST(sum(n) AS DOUBLE) * any_value(share) / 10000, 6) AS normalised_y_rev, round(sum(n * {difference('y_ret')}) / CAST(sum(n) AS DOUBLE) * any_value(share), 6) AS normalised_y_ret
FROM strata s JOIN (SELECT site, CAST(count(*) FILTER (t_bulk = 1) AS DOUBLE) / count(t_bulk) AS share FROM units GROUP BY site) w ON s.site = w.site GROUP BY s.site""", strata(keys="site, " + COARSE)))
def ate_by_site_normalized(spark, folder):
    out = effects.effect_by(line_units(spark, folder), line_spec(), "site")
    return scaled(out, **REV).withColumn("treated_share", F.round("treated_share", 9))


@query(units("""SELECT n, round((ty * xx - xy * tx) / (tt * xx - tx * tx) / 10000, 4) AS ate FROM (SELECT count(*) AS n, covar_samp(t, x) AS tx, covar_samp(t, y) AS ty, covar_samp(x, y) AS xy, var_samp(t) AS tt, var_samp(x) AS xx
FROM (SELECT CAST(t_bulk AS DOUBLE) AS t, CAST(size AS DOUBLE) AS x, CAST(y_rev AS DOUBLE) AS y FROM units WHERE t_bulk IS NOT NULL))"""))
def ate_regression_1cov(spark, folder):
    return effects.regression_adjusted_effect(line_units(spark, folder), line_spec(), "y_rev", "size").select("n", F.round(F.col("ate") / 10000, 4).alias("ate"))


@query(units("""SELECT uid, t_bulk FROM (SELECT uid, t_bulk, h, row_number() OVER (PARTITION BY p_brand, p_type, t_bulk ORDER BY h, uid) AS r,
least(count(*) FILTER (t_bulk = 1) OVER w, count(*) FILTER (t_bulk = 0) OVER w // 2) AS m FROM units WHERE t_bulk IS NOT NULL WINDOW w AS (PARTITION BY p_brand, p_type)) WHERE r <= m * CASE WHEN t_bulk = 1 THEN 1 ELSE 2 END"""))
def balanced_sample_match(spark, folder):
    """Two controls for each treated unit, drawn by hash within strata."""
    spec = UnitSpec("uid", "t_bulk", ("p_brand", "p_type"))
    return effects.balanced_sample(line_units(spark, folder), spec, F.col("h"), k=2).select("uid", "t_bulk")


QUANTILES = """trimmed AS (SELECT *, CAST(ntile({n}) OVER (ORDER BY {score}, uid) AS INTEGER) AS quantile FROM scored WHERE ps BETWEEN 100000 AND 900000),
kept AS (SELECT quantile, max(uid) AS subclass FROM trimmed GROUP BY 1 HAVING min(t_bulk) <> max(t_bulk))"""


def _subclasses(spark, folder, plan="ranked", n=5, score="ps"):
    rows = trim(scored_units(line_units(spark, folder)), "ps", 100_000, 900_000)
    return subclassify(rows, UnitSpec("uid", "t_bulk", ()), score, n, plan)


_IN_CLASS = "SELECT uid, quantile, subclass FROM trimmed JOIN kept USING (quantile)"


@query(units(_IN_CLASS, SCORED, QUANTILES.format(n=5, score="ps")))
def subclass_ntile5(spark, folder):
    return _subclasses(spark, folder, "ntile").select("uid", "quantile", "subclass")


@query(units(_IN_CLASS, SCORED, QUANTILES.format(n=5, score="ps")))
def subclass_ranked(spark, folder):
    return _subclasses(spark, folder).select("uid", "quantile", "subclass")


@query(units(_IN_CLASS, SCORED, QUANTILES.format(n=10, score="acct")))
def subclass_univariate(spark, folder):
    return _subclasses(spark, folder, n=10, score="acct").select("uid", "quantile", "subclass")


CLASS_STRATA = strata(keys="subclass", source="(SELECT * FROM trimmed JOIN kept USING (quantile))", values=("y_rev", "total", "acct")).replace(", max(uid) AS subclass", "")


def _class_strata(spark, folder):
    return summarize(_subclasses(spark, folder).withColumnRenamed("subclass", "class"), UnitSpec("uid", "t_bulk", ("class",), ("y_rev",), ("total", "acct")))


@query(units(f"SELECT {totals()}, {effect('y_rev', 10000.0)} FROM strata", SCORED, QUANTILES.format(n=5, score="ps"), CLASS_STRATA))
def ate_subclass(spark, folder):
    return scaled(stratified_effect(_class_strata(spark, folder), ("y_rev",)), **REV)


@query(units(f"SELECT {awmd('total', 100.0)}, {awmd('acct', 100.0)} FROM strata", SCORED, QUANTILES.format(n=5, score="ps"), CLASS_STRATA))
def awmd_subclass(spark, folder):
    return scaled(balance.awmd(_class_strata(spark, folder), ("total", "acct")), total=100.0, acct=100.0)


@query(units(f"SELECT {awmd('total', 100.0)}, {awmd('acct', 100.0)} FROM strata", "one AS (SELECT *, 1 AS k FROM units)", strata(keys="k", source="one", values=("total", "acct"))))
def awmd_raw(spark, folder):
    """Before matching: all rows are one stratum."""
    spec = UnitSpec("uid", "t_bulk", (), ("y_rev",), ("total", "acct"))
    return scaled(balance.awmd(summarize(line_units(spark, folder), spec), ("total", "acct")), total=100.0, acct=100.0)


@query(units(f"SELECT {awmd('total', 100.0)}, {awmd('acct', 100.0)} FROM strata", strata(values=("total", "acct"))))
def awmd_cem(spark, folder):
    return scaled(balance.awmd(_strata(spark, folder), ("total", "acct")), total=100.0, acct=100.0)


def _planted(spark, folder, kind, keys, y_scale):
    rows = planted_units(line_units(spark, folder), kind).withColumn("band_wide", F.expr("cast(total div 10000000 as int)")).withColumn("band_fine", F.expr("cast(total div 2500000 as int)"))
    spec = UnitSpec("uid", "t_bulk", keys, ("y",), ("total",))
    return rows, spec, overlapping(summarize(rows, spec))


BANDS = "banded AS (SELECT *, CAST(total // 10000000 AS INTEGER) AS band_wide, CAST(total // 2500000 AS INTEGER) AS band_fine FROM continuous)"


@query(units("""SELECT 'discrete' AS kind, round((avg(y) FILTER (t_bulk = 1) - avg(y) FILTER (t_bulk = 0)), 6) AS ate_y, count(*) AS n FROM discrete
UNION ALL SELECT 'continuous', round((avg(y) FILTER (t_bulk = 1) - avg(y) FILTER (t_bulk = 0)) / 100000, 6), count(*) FROM continuous""", PLANTED))
def planted_naive(spark, folder):
    """Raw differences under confounding; the planted effect is 5."""
    base = line_units(spark, folder)
    out = [effects.naive_effect(planted_units(base, kind), UnitSpec("uid", "t_bulk", (), ("y",))).select(F.lit(kind).alias("kind"), F.round(F.col("ate_y") / s, 6).alias("ate_y"), "n") for kind, s in (("discrete", 1.0), ("continuous", 100000.0))]
    return out[0].unionByName(out[1])


@query(units(f"SELECT {totals()}, {effect('y', 1.0)} FROM strata", PLANTED, strata(keys="tax", source="discrete", values=("y",))))
def planted_cem(spark, folder):
    return scaled(stratified_effect(_planted(spark, folder, "discrete", ("tax",), 1.0)[2], ("y",)), y=1.0)


@query(units(f"SELECT 'wide' AS bands, {totals()}, {effect('y', 100000.0)} FROM w UNION ALL SELECT 'fine', {totals()}, {effect('y', 100000.0)} FROM f", PLANTED, BANDS,
    strata(keys="band_wide", source="banded", values=("y",), name="w"), strata(keys="band_fine", source="banded", values=("y",), name="f")))
def planted_bands(spark, folder):
    """Finer buckets of a continuous confounder leave less bias."""
    out = [scaled(stratified_effect(_planted(spark, folder, "continuous", (f"band_{b}",), 0)[2], ("y",)), y=100000.0).select(F.lit(b).alias("bands"), "*") for b in ("wide", "fine")]
    return out[0].unionByName(out[1])


@query(units(f"SELECT 'wide' AS bands, {awmd('total', 100.0)} FROM w UNION ALL SELECT 'fine', {awmd('total', 100.0)} FROM f", PLANTED, BANDS,
    strata(keys="band_wide", source="banded", values=("total",), name="w"), strata(keys="band_fine", source="banded", values=("total",), name="f")))
def awmd_planted(spark, folder):
    out = [scaled(balance.awmd(_planted(spark, folder, "continuous", (f"band_{b}",), 0)[2], ("total",)), total=100.0).select(F.lit(b).alias("bands"), "*") for b in ("wide", "fine")]
    return out[0].unionByName(out[1])


@query(units("""SELECT t, n, round(m, 4) AS mean, round(v, 2) AS variance, round(s, 6) AS skewness FROM (SELECT t_bulk AS t, count(*) AS n, avg(x) AS m, avg(x * x) - avg(x) * avg(x) AS v,
(avg(x * x * x) - 3 * avg(x) * avg(x * x) + 2 * avg(x) * avg(x) * avg(x)) / pow(abs(avg(x * x) - avg(x) * avg(x)), 1.5) AS s FROM (SELECT t_bulk, CAST(size AS DOUBLE) AS x FROM units WHERE t_bulk IS NOT NULL) GROUP BY t_bulk)"""))
def imbalance_moments(spark, folder):
    out = balance.moments(line_units(spark, folder), line_spec(), "size")
    return out.select("t", "n", F.round("mean", 4).alias("mean"), F.round("variance", 2).alias("variance"), F.round("skewness", 6).alias("skewness"))


@query(units("""SELECT point, treated, control, treated - control AS difference FROM (SELECT unnest([0.1, 0.25, 0.5, 0.75, 0.9]::DOUBLE[]) AS point, unnest(quantile_cont(size, [0.1, 0.25, 0.5, 0.75, 0.9]) FILTER (t_bulk = 1)) AS treated,
unnest(quantile_cont(size, [0.1, 0.25, 0.5, 0.75, 0.9]) FILTER (t_bulk = 0)) AS control FROM units)"""))
def imbalance_quantiles(spark, folder):
    return balance.quantiles(line_units(spark, folder), line_spec(), "size", (0.1, 0.25, 0.5, 0.75, 0.9))


@query(units("""SELECT round(sum(abs(CAST(a AS DOUBLE) / na - CAST(b AS DOUBLE) / nb)) / 2, 9) AS l1 FROM (SELECT count(*) FILTER (t_bulk = 1) AS a, count(*) FILTER (t_bulk = 0) AS b FROM units WHERE t_bulk IS NOT NULL GROUP BY p_brand, p_type),
(SELECT count(*) FILTER (t_bulk = 1) AS na, count(*) FILTER (t_bulk = 0) AS nb FROM units)"""))
def imbalance_l1(spark, folder):
    return balance.l1_histogram(line_units(spark, folder), UnitSpec("uid", "t_bulk", ("p_brand", "p_type"))).select(F.round("l1", 9).alias("l1"))


@query(units("""SELECT round(max(abs(CAST(a AS DOUBLE) / na - CAST(b AS DOUBLE) / nb)), 9) AS gap FROM (SELECT *, sum(a) OVER w AS na, sum(b) OVER w AS nb FROM (SELECT p_brand, p_type, o_orderstatus, count(*) FILTER (t_bulk = 1) AS a, count(*) FILTER (t_bulk = 0) AS b
FROM units WHERE t_bulk IS NOT NULL GROUP BY ALL) WINDOW w AS (PARTITION BY p_brand, p_type)) WHERE na > 0 AND nb > 0"""))
def balance_gap(spark, folder):
    out = balance.balance_gap(line_units(spark, folder), UnitSpec("uid", "t_bulk", ()), ("p_brand", "p_type"), ("o_orderstatus",))
    return out.select(F.round("gap", 9).alias("gap"))


@query(units("""SELECT count(*) AS strata, count(*) FILTER (n1 > 0 AND n0 > 0) AS strata_kept, CAST(sum(n) AS BIGINT) AS "rows", CAST(sum(n) FILTER (n1 > 0 AND n0 > 0) AS BIGINT) AS rows_kept, CAST(sum(n1) FILTER (n1 > 0 AND n0 > 0) AS BIGINT) AS treated_kept FROM strata""", strata(overlap=False)))
def overlap_report(spark, folder):
    return report(_strata(spark, folder, overlap=False))


_MATCHED = f"SELECT uid, t_bulk, max(uid) OVER w AS subclass FROM units WHERE t_bulk IS NOT NULL WINDOW w AS (PARTITION BY {COARSE}) QUALIFY min(t_bulk) OVER w <> max(t_bulk) OVER w"


@query(units(_MATCHED))
def cem_window(spark, folder):
    return cem(line_units(spark, folder), line_spec(), "window").select("uid", "t_bulk", "subclass")


@query(units(_MATCHED))
def cem_groupby(spark, folder):
    return cem(line_units(spark, folder), line_spec()).select("uid", "t_bulk", "subclass")


@query(units(_MATCHED.replace(COARSE, EXACT)))
def exact_match(spark, folder):
    return match_exactly(line_units(spark, folder), line_spec(covariates=EM)).select("uid", "t_bulk", "subclass")


@query(units(f"SELECT {COARSE}, subclass, n, n1, n0, sum1_y_rev, sum0_y_rev FROM strata", strata()))
def cem_strata(spark, folder):
    return _strata(spark, folder).select(*line_spec().covariates, "subclass", "n", "n1", "n0", "sum1_y_rev", "sum0_y_rev")


@query("""WITH u AS (SELECT doc_id AS uid, toxic AS t, quality AS y, lang, CAST(floor(log2(greatest(n_chars, 1))) AS INTEGER) AS band FROM documents JOIN labels USING (doc_id)),
s AS (SELECT lang, band, count(*) AS n, count(*) FILTER (t = 1) AS n1, count(*) FILTER (t = 0) AS n0, sum(y) FILTER (t = 1) AS s1, sum(y) FILTER (t = 0) AS s0 FROM u GROUP BY ALL HAVING n1 > 0 AND n0 > 0)
SELECT count(*) AS strata, CAST(sum(n) AS BIGINT) AS n, CAST(sum(n1) AS BIGINT) AS n1, CAST(sum(n0) AS BIGINT) AS n0, round(sum(n * (CAST(s1 AS DOUBLE) / n1 - CAST(s0 AS DOUBLE) / n0)) / CAST(sum(n) AS DOUBLE), 6) AS ate_y FROM s""")
def ate_documents(spark, folder):
    spec = UnitSpec("uid", "t", ("lang", "band"), ("y",))
    return scaled(stratified_effect(overlapping(summarize(document_units(spark, folder), spec)), ("y",)), y=1.0)
