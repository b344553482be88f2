"""Building blocks of the SQL that checks the workloads (DuckDB over the same tables)."""

from __future__ import annotations

LINES = """lines AS (SELECT *, CAST(row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice, l_quantity) AS INTEGER) AS seq FROM lineitem)"""

UNITS = f"""{LINES},
base AS (SELECT l_orderkey * 1000 + seq AS uid, seq, l_orderkey, p_partkey, l_shipdate AS ship_date, p_brand, p_type, c_mktsegment, o_orderstatus, r_name AS site,
  CASE WHEN l_quantity > 40 THEN 1 WHEN l_quantity < 20 THEN 0 END AS t_bulk,
  CASE WHEN l_discount >= 0.075 THEN 1 WHEN l_discount <= 0.045 THEN 0 END AS t_disc,
  CASE WHEN o_orderpriority = '1-URGENT' THEN 1 ELSE 0 END AS t_urgent,
  CASE WHEN p_size > 35 AND p_retailprice > 930 THEN 1 ELSE 0 END AS t_heavy,
  CAST(round(l_extendedprice * 100) AS BIGINT) * (100 - CAST(round(l_discount * 100) AS BIGINT)) AS y_rev,
  CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END AS y_ret,
  CAST(round(o_totalprice * 100) AS BIGINT) AS total, CAST(round(p_retailprice * 100) AS BIGINT) AS retail, CAST(round(c_acctbal * 100) AS BIGINT) AS acct,
  CAST(round(l_tax * 100) AS BIGINT) AS tax, p_size AS size,
  CAST(floor(o_totalprice / 50000) AS INTEGER) AS cx_total, CAST(floor(round(l_tax * 100) / 3) AS INTEGER) AS cx_tax, CAST(date_trunc('week', l_shipdate) AS DATE) AS cx_week,
  CAST((l_orderkey * 7919 + seq * 104729) % 1000 AS INTEGER) AS h
  FROM lines JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN customer ON o_custkey = c_custkey
  JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey),
combos AS (SELECT *, CASE WHEN t_bulk = 1 AND t_disc = 1 THEN 1 WHEN t_bulk = 0 OR t_disc = 0 THEN 0 END AS t_combo FROM base),
units AS (SELECT *, CASE WHEN t_combo = 1 AND t_urgent = 1 THEN 1 WHEN t_combo = 0 OR t_urgent = 0 THEN 0 END AS t_rare FROM combos)"""

COARSE = "p_brand, p_type, c_mktsegment, o_orderstatus, cx_total"
EXACT = "p_partkey, c_mktsegment, tax, o_orderstatus"

PLANTED = """flat AS (SELECT *, CASE WHEN tax >= 5 THEN 800 WHEN tax >= 3 THEN 500 ELSE 200 END AS pr_d, 100 + 800 * total / 50000000 AS pr_c FROM units WHERE t_bulk IS NOT NULL),
discrete AS (SELECT *, tax * 10 + 5 * t_bulk AS y FROM flat WHERE (t_bulk = 1 AND h < pr_d) OR (t_bulk = 0 AND h >= pr_d)),
continuous AS (SELECT *, total + 500000 * t_bulk AS y FROM flat WHERE (t_bulk = 1 AND h < pr_c) OR (t_bulk = 0 AND h >= pr_c))"""

SCORED = """scored AS (SELECT *, CAST(round(1e6 / (1 + exp(-(-3 + 5 * total / 100 / 500000 + 1.0 * size / 50 - acct / 100 / 10000)))) AS BIGINT) AS ps
  FROM units WHERE t_bulk IS NOT NULL)"""

EDGES = """edges AS (SELECT t.uid AS t_uid, c.uid AS c_uid, CAST(abs(t.ps - c.ps) AS DOUBLE) AS distance FROM scored t JOIN scored c ON t.t_bulk = 1 AND c.t_bulk = 0 AND abs(t.ps - c.ps) < {caliper})"""

#: Pairs of each method over ``edges``.
PAIRS = {
    "with_replacement": "SELECT *, CAST(row_number() OVER (PARTITION BY t_uid ORDER BY distance, c_uid) AS INTEGER) AS rnk FROM edges QUALIFY rnk <= {k}",
    "single_pass": "SELECT t_uid, c_uid, distance, rnk FROM (SELECT *, row_number() OVER (PARTITION BY c_uid ORDER BY distance, t_uid) AS c, CAST(row_number() OVER (PARTITION BY t_uid ORDER BY distance, c_uid) AS INTEGER) AS rnk FROM edges) WHERE c = 1 AND rnk <= {k}",
    "refill": "SELECT * FROM (SELECT *, CAST(row_number() OVER (PARTITION BY t_uid ORDER BY distance, c_uid) AS INTEGER) AS rnk FROM (SELECT * FROM edges QUALIFY row_number() OVER (PARTITION BY c_uid ORDER BY distance, t_uid) = 1)) WHERE rnk <= {k}",
}


def units(rest: str, *more: str) -> str:
    """``WITH units, more`` and the final query."""
    return "WITH " + ",\n".join((UNITS, *more)) + "\n" + rest


def strata(t: str = "t_bulk", keys: str = COARSE, source: str = "units", values=("y_rev", "y_ret"), name: str = "strata", where: str = "true", overlap: bool = True) -> str:
    sums = "".join(f", CAST(sum({v}) FILTER ({t} = {a}) AS BIGINT) AS sum{a}_{v}" for v in values for a in (1, 0))
    both = f" HAVING count(*) FILTER ({t} = 1) > 0 AND count(*) FILTER ({t} = 0) > 0" if overlap else ""
    return f"""{name} AS (SELECT {keys}, max(uid) AS subclass, count(*) AS n, count(*) FILTER ({t} = 1) AS n1, count(*) FILTER ({t} = 0) AS n0{sums}
  FROM {source} WHERE {t} IS NOT NULL AND ({where}) GROUP BY {keys}{both})"""


def difference(y: str) -> str:
    return f"(CAST(sum1_{y} AS DOUBLE) / n1 - CAST(sum0_{y} AS DOUBLE) / n0)"


def effect(y: str, scale: float, weight: str = "n") -> str:
    return f"round(sum({weight} * {difference(y)}) / CAST(sum({weight}) AS DOUBLE) / {scale}, 6) AS ate_{y}"


def totals() -> str:
    return "count(*) AS strata, CAST(coalesce(sum(n), 0) AS BIGINT) AS n, CAST(coalesce(sum(n1), 0) AS BIGINT) AS n1, CAST(coalesce(sum(n0), 0) AS BIGINT) AS n0"


def awmd(x: str, scale: float) -> str:
    return f"round(sum(n * abs({difference(x)})) / CAST(sum(n) AS DOUBLE) / {scale}, 4) AS awmd_{x}"
