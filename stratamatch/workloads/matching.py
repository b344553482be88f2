"""Push-down, and comparison of methods."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators.balance import awmd, awmd_pairs, match_rates as rates
from ..operators.neighbours import match_sorted, nearest_sorted
from ..operators.pushdown import cem_pushed, joined, ordered, pushdown_report as report
from ..operators.propensity import fit_propensity, trim
from ..operators.strata import cem, overlapping, summarize
from ..operators.subclass import subclassify
from ..plans.spec import Hop, UnitSpec
from ..sources.catalog import table
from ..sources.shared import materialized
from ..sources.units import keyed_lines, line_spec, line_units, scored_units
from . import query
from .effects import EM, QUANTILES
from .oracle import COARSE, EDGES, EXACT, LINES, PAIRS, SCORED, strata, units

CHAIN = f"""WITH {LINES}, chain AS (SELECT l_orderkey * 1000 + seq AS uid, CASE WHEN p_size > 45 THEN 1 ELSE 0 END AS t, p_partkey, p_brand, p_type, CAST(floor(p_retailprice / 20) AS INTEGER) AS cx_retail, o_orderstatus, c_mktsegment
FROM lines JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey)"""
_CHAIN_KEYS = "p_brand, p_type, cx_retail, o_orderstatus, c_mktsegment"
_CHAIN_RESULT = f"{CHAIN} SELECT uid, t, max(uid) OVER w AS subclass FROM chain WINDOW w AS (PARTITION BY {_CHAIN_KEYS}) QUALIFY min(t) OVER w <> max(t) OVER w"
CHAIN_SPEC = UnitSpec("uid", "t", ("p_brand", "p_type", "cx_retail", "o_orderstatus", "c_mktsegment"))


def _store(df):
    return materialized(df, "joined")


def chain(spark, folder):
    """part (holds the treatment) - lineitem - orders - customer."""
    part = table(spark, folder, "part").select("p_partkey", F.expr("cast(p_size > 45 as int)").alias("t"), "p_brand", "p_type", F.floor(F.col("p_retailprice") / 20).cast("int").alias("cx_retail"))
    lines = keyed_lines(spark, folder).select("uid", "l_orderkey", "l_partkey")
    orders = table(spark, folder, "orders").select("o_orderkey", "o_custkey", "o_orderstatus")
    customer = table(spark, folder, "customer").select("c_custkey", "c_mktsegment")
    return [
        Hop("part", part, (), ("p_brand", "p_type", "cx_retail")), Hop("lineitem", lines, (("p_partkey", "l_partkey"),)),
        Hop("orders", orders, (("l_orderkey", "o_orderkey"),), ("o_orderstatus",)), Hop("customer", customer, (("o_custkey", "c_custkey"),), ("c_mktsegment",)),
    ]


@query(_CHAIN_RESULT)
def pushdown_integrated(spark, folder):
    """Baseline: join everything, then match."""
    return cem(joined(chain(spark, folder)), CHAIN_SPEC).select("uid", "t", "subclass")


@query(_CHAIN_RESULT)
def pushdown_cem(spark, folder):
    return cem_pushed(chain(spark, folder), CHAIN_SPEC, "p_partkey", _store).select("uid", "t", "subclass")


@query(_CHAIN_RESULT)
def pushdown_reordered(spark, folder):
    """Relations in the order of their sizes, as far as they join."""
    sizes = {h.name: table(spark, folder, h.name).count() for h in chain(spark, folder)}
    return cem_pushed(ordered(chain(spark, folder), sizes), CHAIN_SPEC, "p_partkey").select("uid", "t", "subclass")


ORDERS = """WITH o AS (SELECT o_orderkey, CASE WHEN o_orderpriority = '1-URGENT' THEN 1 ELSE 0 END AS t, o_orderstatus, CAST(date_trunc('week', o_orderdate) AS DATE) AS cx_week, CAST(floor(o_totalprice / 50000) AS INTEGER) AS cx_total FROM orders)"""


@query(f"{ORDERS} SELECT count(*) AS orders_kept, CAST(sum(t) AS BIGINT) AS treated_kept FROM (SELECT * FROM o WINDOW w AS (PARTITION BY o_orderstatus, cx_week, cx_total) QUALIFY min(t) OVER w <> max(t) OVER w)")
def pushdown_semi(spark, folder):
    """Orders that survive matching before any join (a semi-join with the kept strata)."""
    from ..functions.coarsening import week
    from ..operators.pushdown import prune

    o = table(spark, folder, "orders").select("o_orderkey", F.expr("cast(o_orderpriority = '1-URGENT' as int)").alias("t"), "o_orderstatus", week(F.col("o_orderdate")).alias("cx_week"), F.floor(F.col("o_totalprice") / 50000).cast("int").alias("cx_total"))
    kept = prune(o, UnitSpec("o_orderkey", "t", ("o_orderstatus", "cx_week", "cx_total")))
    return kept.agg(F.count("*").alias("orders_kept"), F.sum("t").alias("treated_kept"))


@query(f"""{CHAIN}, p1 AS (SELECT p_partkey, CASE WHEN p_size > 45 THEN 1 ELSE 0 END AS t, p_brand, p_type, CAST(floor(p_retailprice / 20) AS INTEGER) AS cx_retail FROM part),
k1 AS (SELECT * FROM p1 WINDOW w AS (PARTITION BY p_brand, p_type, cx_retail) QUALIFY min(t) OVER w <> max(t) OVER w),
c2 AS (SELECT chain.* FROM chain JOIN k1 USING (p_partkey)), k2 AS (SELECT * FROM c2 WINDOW w AS (PARTITION BY p_brand, p_type, cx_retail) QUALIFY min(t) OVER w <> max(t) OVER w),
k3 AS (SELECT * FROM k2 WINDOW w AS (PARTITION BY p_brand, p_type, cx_retail, o_orderstatus) QUALIFY min(t) OVER w <> max(t) OVER w),
k4 AS (SELECT * FROM k3 WINDOW w AS (PARTITION BY {_CHAIN_KEYS}) QUALIFY min(t) OVER w <> max(t) OVER w)
SELECT * FROM (SELECT 1 AS step, 'part' AS relation, (SELECT count(*) FROM p1) AS rows_in, (SELECT count(*) FROM k1) AS rows_out UNION ALL SELECT 2, 'lineitem', (SELECT count(*) FROM c2), (SELECT count(*) FROM k2)
UNION ALL SELECT 3, 'orders', (SELECT count(*) FROM k2), (SELECT count(*) FROM k3) UNION ALL SELECT 4, 'customer', (SELECT count(*) FROM k3), (SELECT count(*) FROM k4))""")
def pushdown_report(spark, folder):
    return report(chain(spark, folder), CHAIN_SPEC, "p_partkey")


_DAYS = f"""WITH {LINES}, o AS (SELECT l_orderkey * 1000 + seq AS uid, CASE WHEN o_orderpriority = '1-URGENT' THEN 1 ELSE 0 END AS t, o_orderstatus, CAST(o_orderdate AS DATE) AS cx_day, CAST(floor(o_totalprice / 50000) AS INTEGER) AS cx_total, p_brand
FROM lines JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey)
SELECT uid, t, max(uid) OVER w AS subclass FROM o WINDOW w AS (PARTITION BY o_orderstatus, cx_day, cx_total, p_brand) QUALIFY min(t) OVER w <> max(t) OVER w"""
DAY_SPEC = UnitSpec("uid", "t", ("o_orderstatus", "cx_day", "cx_total", "p_brand"))


def order_chain(spark, folder):
    """orders (holds the treatment; fine strata by day, most without overlap) - lineitem - part."""
    orders = table(spark, folder, "orders").select("o_orderkey", F.expr("cast(o_orderpriority = '1-URGENT' as int)").alias("t"), "o_orderstatus", F.col("o_orderdate").cast("date").alias("cx_day"), F.floor(F.col("o_totalprice") / 50000).cast("int").alias("cx_total"))
    return [
        Hop("orders", orders, (), ("o_orderstatus", "cx_day", "cx_total")), Hop("lineitem", keyed_lines(spark, folder).select("uid", "l_orderkey", "l_partkey"), (("o_orderkey", "l_orderkey"),)),
        Hop("part", table(spark, folder, "part").select("p_partkey", "p_brand"), (("l_partkey", "p_partkey"),), ("p_brand",)),
    ]


@query(_DAYS)
def pushdown_days_integrated(spark, folder):
    """Baseline of the next: join everything, then match."""
    return cem(joined(order_chain(spark, folder)), DAY_SPEC).select("uid", "t", "subclass")


@query(_DAYS)
def pushdown_days(spark, folder):
    """A second treatment and chain, where matching the first relation drops most of its rows."""
    return cem_pushed(order_chain(spark, folder), DAY_SPEC, "o_orderkey", _store).select("uid", "t", "subclass")


MEASURED = {"total": 100, "retail": 100, "acct": 100, "size": 1}
METHODS = ("raw", "nn_with_replacement", "nn_without_replacement", "subclass", "exact", "coarsened")


def _methods(rows, treatment, caliper=1000, low=100_000, high=900_000):
    """(method, n1, n0, awmd of each measured covariate) of six methods for units with the score ``ps``."""
    columns = dict.fromkeys(("uid", treatment, "ps", *MEASURED, *EM, *line_spec().covariates))
    rows = materialized(rows.select(*columns), "scored")
    spec = lambda *keys: UnitSpec("uid", treatment, keys, (), tuple(MEASURED))
    plain = UnitSpec("uid", treatment, ())
    classes = subclassify(trim(rows, "ps", low, high), plain, "ps", 5, "ranked").withColumnRenamed("subclass", "class")
    found = {}
    for name, pairs in (("nn_with_replacement", nearest_sorted(rows, plain, "ps", 1, caliper)), ("nn_without_replacement", match_sorted(rows, plain, "ps", 1, caliper, "refill"))):
        pairs = materialized(pairs, "pairs")
        found[name] = pairs.agg(F.count_distinct("t_uid").alias("n1"), F.count_distinct("c_uid").alias("n0")), awmd_pairs(pairs, rows, "uid", tuple(MEASURED))
    for name, units_of, keys in (("raw", rows, ()), ("subclass", classes, ("class",)), ("exact", rows, EM), ("coarsened", rows, line_spec().covariates)):
        s = overlapping(summarize(units_of, spec(*keys)))
        found[name] = s.agg(F.coalesce(F.sum("n1"), F.lit(0)).alias("n1"), F.coalesce(F.sum("n0"), F.lit(0)).alias("n0")), awmd(s, tuple(MEASURED))
    out = None
    for name in METHODS:
        sizes, gaps = found[name]
        one = sizes.crossJoin(F.broadcast(gaps)).select(F.lit(name).alias("method"), "n1", "n0", *(F.round(F.col(f"awmd_{x}") / scale, 4).alias(f"awmd_{x}") for x, scale in MEASURED.items()))  # one row each
        out = one if out is None else out.unionByName(one)
    return out


def _methods_sql(treatment, rest="SELECT * FROM methods"):
    own = lambda sql: sql.replace("t_bulk", treatment)
    gap = ", ".join(f"round(abs(avg(t.{x}) - avg(c.{x})) / {scale}, 4) AS awmd_{x}" for x, scale in MEASURED.items())
    parts = [f"SELECT '{name}' AS method, count(DISTINCT t_uid) AS n1, count(DISTINCT c_uid) AS n0, {gap} FROM {pairs} JOIN scored t ON t.uid = t_uid JOIN scored c ON c.uid = c_uid" for name, pairs in (("nn_with_replacement", "wr"), ("nn_without_replacement", "nr"))]
    gap = ", ".join(f"round(sum(n * abs(CAST(sum1_{x} AS DOUBLE) / n1 - CAST(sum0_{x} AS DOUBLE) / n0)) / CAST(sum(n) AS DOUBLE) / {scale}, 4) AS awmd_{x}" for x, scale in MEASURED.items())
    tables = {"raw": ("k", "(SELECT *, 1 AS k FROM scored)"), "subclass": ("subclass", "(SELECT * FROM trimmed JOIN kept USING (quantile))"), "exact": (EXACT, "scored"), "coarsened": (COARSE, "scored")}
    parts += [f"SELECT '{name}', CAST(coalesce(sum(n1), 0) AS BIGINT), CAST(coalesce(sum(n0), 0) AS BIGINT), {gap} FROM s_{name}" for name in tables]
    groups = [strata(treatment, keys, source, tuple(MEASURED), f"s_{name}").replace(", max(uid) AS subclass", "") for name, (keys, source) in tables.items()]
    return units(rest, own(SCORED), own(EDGES.format(caliper=1000)), f"wr AS ({PAIRS['with_replacement'].format(k=1)})", f"nr AS ({PAIRS['refill'].format(k=1)})", own(QUANTILES.format(n=5, score="ps")), *groups, "methods AS (" + "\nUNION ALL ".join(parts) + ")")


def _bulk(spark, folder):
    return _methods(scored_units(line_units(spark, folder)), "t_bulk")


@query(_methods_sql("t_bulk"))
def method_comparison(spark, folder):
    """Matched sizes and imbalance of all measured covariates by six methods."""
    return _bulk(spark, folder)


@query(_methods_sql("t_rare"))
def method_comparison_rare(spark, folder):
    """The same for the rare treatment."""
    return _methods(scored_units(line_units(spark, folder), "t_rare"), "t_rare")


@query()
def method_comparison_fitted(spark, folder):
    """The same for the rare treatment with a score fitted on the covariates (logistic regression)."""
    return _methods(fitted_units(line_units(spark, folder), "t_rare"), "t_rare")


def fitted_units(base, treatment):
    """Units with a defined treatment and their fitted score in whole micro-units."""
    rows = base.where(F.col(treatment).isNotNull())
    for x, scale in (("total", 5e7), ("acct", 1e6), ("retail", 1e5), ("size", 50)):
        rows = rows.withColumn(f"x_{x}", F.col(x) / scale)
    rows = materialized(rows, "units")
    score, _, _ = fit_propensity(rows, UnitSpec("uid", treatment, ()), numeric=("x_total", "x_acct", "x_retail", "x_size"), categorical=("o_orderstatus", "c_mktsegment"))
    return rows.withColumn("ps", F.round(1e6 * score).cast("long"))


@query(_methods_sql("t_bulk", "SELECT method, n1, n0 FROM methods WHERE method <> 'raw'"))
def match_sizes(spark, folder):
    return _bulk(spark, folder).where("method != 'raw'").select("method", "n1", "n0")


@query(_methods_sql("t_bulk", "SELECT method, round(CAST(n1 AS DOUBLE) / (SELECT count(*) FROM scored WHERE t_bulk = 1), 9) AS treated_share, round(CAST(n0 AS DOUBLE) / nullif(n1, 0), 9) AS controls_per_treated FROM methods WHERE method <> 'raw'"))
def match_rates(spark, folder):
    out = _bulk(spark, folder)
    whole = F.broadcast(out.where("method = 'raw'").select(F.col("n1").alias("treated")))  # one row
    out = out.where("method != 'raw'").crossJoin(whole).select("method", *rates("n1", "n0", "treated"))
    return out.select("method", *(F.round(c, 9).alias(c) for c in ("treated_share", "controls_per_treated")))
