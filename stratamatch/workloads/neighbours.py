"""Nearest-neighbour matching on scored units, distances, vectors."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import distances
from ..operators.balance import awmd_pairs
from ..operators.effects import matched_effect
from ..operators.neighbours import (
    candidate_pairs,
    greedy_violations_by_score,
    listed_pairs,
    match_sorted,
    measured_pairs,
    nearest_by_scores,
    nearest_mahalanobis,
    nearest_sorted,
    nearest_vectors,
    theta_pairs,
)
from ..plans.spec import UnitSpec
from ..sources.catalog import table
from ..sources.shared import materialized
from ..sources.units import line_units, scored_units, written_codes, written_scores
from ..sqlapi import distance_udf
from . import query
from .oracle import EDGES, PAIRS, SCORED, units

SPEC = UnitSpec("uid", "t_bulk", ())
SPEC_T = UnitSpec("uid", "t", ())
_E = EDGES.format(caliper=1000)
_NARROW = EDGES.format(caliper=200)


def _pairs(mode, k=1):
    return f"pairs AS ({PAIRS[mode].format(k=k)})"


def rows(spark, folder):
    return scored_units(line_units(spark, folder))


def edges(spark, folder, caliper=1000):
    return candidate_pairs(rows(spark, folder), SPEC, "ps", caliper)


@query(units("SELECT t_uid, c_uid, distance FROM edges", SCORED, _E))
def nn_candidates(spark, folder):
    """The band join, of lists of ids that share a score."""
    return listed_pairs(written_scores(spark, folder), SPEC, "ps", 1000)


@query(units("SELECT t_uid, c_uid, distance FROM edges", SCORED, _NARROW))
def nn_theta_baseline(spark, folder):
    """The nested-loop join of units that bands replace."""
    return theta_pairs(written_scores(spark, folder), SPEC, "ps", 200)


@query(units(PAIRS["with_replacement"].format(k=1), SCORED, _E))
def nnmwr_k1(spark, folder):
    return nearest_sorted(rows(spark, folder), SPEC, "ps", 1, caliper=1000)


@query(units(PAIRS["with_replacement"].format(k=3), SCORED, _E))
def nnmwr_k3(spark, folder):
    """The window plan: the edges that decide, then the first ones of each score."""
    return nearest_by_scores(rows(spark, folder), SPEC, "ps", 3, 1000)


@query(units(PAIRS["with_replacement"].format(k=3), SCORED, _E))
def nnmwr_antijoin(spark, folder):
    """The anti-join plan: the controls before each edge are counted by a self-join of the edges that decide."""
    return nearest_by_scores(rows(spark, folder), SPEC, "ps", 3, 1000, plan="antijoin")


@query(units(PAIRS["with_replacement"].format(k=3), SCORED, _E))
def nnmwr_sorted(spark, folder):
    return nearest_sorted(rows(spark, folder), SPEC, "ps", 3, caliper=1000)


@query()
def nnmwr_no_caliper(spark, folder):
    """Without a caliper every treated unit finds a control; only the sorted plan does not multiply units."""
    return nearest_sorted(rows(spark, folder), SPEC, "ps", 1)


@query(units(PAIRS["with_replacement"].format(k=1), SCORED, "edges AS (SELECT t.uid AS t_uid, c.uid AS c_uid, CAST(abs(t.ps - c.ps) AS DOUBLE) AS distance FROM scored t JOIN scored c ON t.t_bulk = 1 AND c.t_bulk = 0 AND t.c_mktsegment = c.c_mktsegment AND abs(t.ps - c.ps) < 5000)"))
def nnmwr_within_block(spark, folder):
    return nearest_by_scores(rows(spark, folder), SPEC, "ps", 1, 5000, ("c_mktsegment",))


@query(units("SELECT t_uid, c_uid, distance, CAST(rnk AS INTEGER) AS rnk FROM (SELECT *, rank() OVER (PARTITION BY t_uid ORDER BY distance) AS rnk FROM edges) WHERE rnk <= 2", SCORED, _E))
def rank_ties(spark, folder):
    """All controls at the k-th distance."""
    return nearest_by_scores(rows(spark, folder), SPEC, "ps", 2, 1000, ties="all")


@query(units(PAIRS["single_pass"].format(k=3), SCORED, _E))
def nnmnr_single_pass(spark, folder):
    return match_sorted(rows(spark, folder), SPEC, "ps", 3, 1000, "single_pass")


@query(units(PAIRS["refill"].format(k=3), SCORED, _E))
def nnmnr_refill(spark, folder):
    return match_sorted(rows(spark, folder), SPEC, "ps", 3, 1000, "refill")


def _scan_sql(k, order, extra=""):
    """The sequential scan of edges in a total order, one edge a step."""
    return units(f"""SELECT t_uid, c_uid, distance, CAST(row_number() OVER (PARTITION BY t_uid ORDER BY distance, c_uid) AS INTEGER) AS rnk FROM scan WHERE ok""", SCORED, _E,
        f"o AS MATERIALIZED (SELECT edges.*, row_number() OVER (ORDER BY {order}) AS i FROM edges {extra})",
        f"""scan AS (SELECT CAST(0 AS BIGINT) AS i, CAST([] AS BIGINT[]) AS cs, CAST([] AS BIGINT[]) AS ts, CAST(NULL AS BIGINT) AS t_uid, CAST(NULL AS BIGINT) AS c_uid, CAST(NULL AS DOUBLE) AS distance, false AS ok
UNION ALL SELECT i, CASE WHEN a THEN list_append(cs, c_uid) ELSE cs END, CASE WHEN a THEN list_append(ts, t_uid) ELSE ts END, t_uid, c_uid, distance, a
FROM (SELECT o.i, o.t_uid, o.c_uid, o.distance, s.cs, s.ts, NOT list_contains(s.cs, o.c_uid) AND len(list_filter(s.ts, lambda x: x = o.t_uid)) < {k} AS a FROM scan s JOIN o ON o.i = s.i + 1))""").replace("WITH ", "WITH RECURSIVE ", 1)  # fmt: skip


@query()
def nnmnr_greedy(spark, folder):
    """The sequential greedy scan, by lists of ids of each score."""
    return match_sorted(rows(spark, folder), SPEC, "ps", 3, 1000, "greedy")


@query()
def nnmnr_greedy_by_score(spark, folder):
    """Greedy with the treated units in descending order of score, each taking its nearest free control."""
    return match_sorted(rows(spark, folder), SPEC, "ps", 1, 1000, "greedy_by_score")


@query("SELECT CAST(0 AS BIGINT) AS controls_reused, CAST(0 AS BIGINT) AS treated_over, CAST(0 AS BIGINT) AS blocking_edges")
def nnmnr_greedy_violations(spark, folder):
    units_of = materialized(rows(spark, folder).select("uid", "t_bulk", "ps"), "scored")
    return greedy_violations_by_score(units_of, SPEC, "ps", 1000, materialized(match_sorted(units_of, SPEC, "ps", 1, 1000, "greedy"), "greedy"), 1)


def _effect_sql(mode):
    return units("""SELECT count(*) AS n1, CAST(sum(k) AS BIGINT) AS pairs, round(avg(y1 - y0) / 10000, 6) AS ate_y_rev FROM (SELECT t_uid, count(*) AS k, avg(CAST(c.y_rev AS DOUBLE)) AS y0, any_value(CAST(t.y_rev AS DOUBLE)) AS y1
FROM pairs JOIN scored t ON t.uid = t_uid JOIN scored c ON c.uid = c_uid GROUP BY t_uid)""", SCORED, _E, _pairs(mode, 3))


def _effect(spark, folder, pairs):
    out = matched_effect(pairs, rows(spark, folder), "uid", "y_rev")
    return out.withColumn("ate_y_rev", F.round(F.col("ate_y_rev") / 10000, 6))


@query(_effect_sql("with_replacement"))
def ate_nnmwr(spark, folder):
    return _effect(spark, folder, nearest_sorted(rows(spark, folder), SPEC, "ps", 3, caliper=1000))


@query(_effect_sql("refill"))
def ate_nnmnr(spark, folder):
    return _effect(spark, folder, match_sorted(rows(spark, folder), SPEC, "ps", 3, 1000, "refill"))


def _awmd_sql(mode):
    return units("SELECT round(abs(a - b) / 100, 4) AS awmd_total, round(abs(c - d) / 100, 4) AS awmd_acct FROM (SELECT avg(t1) AS a, sum(c1) / sum(k) AS b, avg(t2) AS c, sum(c2) / sum(k) AS d FROM (SELECT t_uid, count(*) AS k, sum(CAST(c.total AS DOUBLE)) AS c1, sum(CAST(c.acct AS DOUBLE)) AS c2, any_value(CAST(t.total AS DOUBLE)) AS t1, any_value(CAST(t.acct AS DOUBLE)) AS t2 FROM pairs JOIN scored t ON t.uid = t_uid JOIN scored c ON c.uid = c_uid GROUP BY t_uid))", SCORED, _E, _pairs(mode, 3))


def _awmd(spark, folder, pairs):
    out = awmd_pairs(pairs, rows(spark, folder), "uid", ("total", "acct"))
    return out.select(*(F.round(F.col(c) / 100, 4).alias(c) for c in out.columns))


@query(_awmd_sql("with_replacement"))
def awmd_nnmwr(spark, folder):
    return _awmd(spark, folder, nearest_sorted(rows(spark, folder), SPEC, "ps", 3, caliper=1000))


@query(_awmd_sql("single_pass"))
def awmd_nnmnr_single_pass(spark, folder):
    return _awmd(spark, folder, match_sorted(rows(spark, folder), SPEC, "ps", 3, 1000, "single_pass"))


@query(_awmd_sql("refill"))
def awmd_nnmnr_refill(spark, folder):
    return _awmd(spark, folder, match_sorted(rows(spark, folder), SPEC, "ps", 3, 1000, "refill"))


@query(units("SELECT round(sum(w * abs(t1 - c1 / k)) / sum(w) / 100, 4) AS awmd_total FROM (SELECT t_uid, count(*) AS k, count(*) + 1 AS w, sum(CAST(c.total AS DOUBLE)) AS c1, any_value(CAST(t.total AS DOUBLE)) AS t1 FROM pairs JOIN scored t ON t.uid = t_uid JOIN scored c ON c.uid = c_uid GROUP BY t_uid)", SCORED, _E, _pairs("with_replacement", 3)))
def awmd_nnmwr_per_treated(spark, folder):
    """Each treated unit with its controls as one stratum."""
    out = awmd_pairs(nearest_sorted(rows(spark, folder), SPEC, "ps", 3, caliper=1000), rows(spark, folder), "uid", ("total",), groups="per_treated")
    return out.select(F.round(F.col("awmd_total") / 100, 4).alias("awmd_total"))


@query(units("SELECT t_uid, c_uid FROM (SELECT t.uid AS t_uid, c.uid AS c_uid FROM scored t JOIN scored c ON t.t_bulk = 1 AND c.t_bulk = 0 AND t.p_brand = c.p_brand AND t.p_type = c.p_type AND t.cx_total = c.cx_total)", SCORED))
def dist_coarsened(spark, folder):
    """Pairs at coarsened distance 0 (an equi-join on bucket codes). Both arms come from one written table."""
    keys = ("p_brand", "p_type", "cx_total")
    r = written_codes(spark, folder)
    t = r.where("t_bulk = 1").select(F.col("uid").alias("t_uid"), *(F.col(k).alias(f"t_{k}") for k in keys))
    c = r.where("t_bulk = 0").select(F.col("uid").alias("c_uid"), *(F.col(k).alias(f"c_{k}") for k in keys))
    same = [F.col(f"t_{k}").eqNullSafe(F.col(f"c_{k}")) for k in keys]
    return t.join(c, same[0] & same[1] & same[2]).where(distances.coarsened(keys) == 0).select("t_uid", "c_uid")


@query(units("SELECT round(covar_samp(a, a), 4) AS aa, round(covar_samp(a, b), 4) AS ab, round(covar_samp(b, b), 4) AS bb FROM (SELECT CAST(size AS DOUBLE) AS a, acct / 100000.0 AS b FROM units)"))
def cov_matrix(spark, folder):
    df = line_units(spark, folder).select(F.col("size").cast("double").alias("a"), (F.col("acct") / 100000.0).alias("b"))
    return df.agg(*(F.round(F.covar_samp(x, y), 4).alias(x + y) for x, y in ("aa", "ab", "bb")))


_MD = """WITH v AS (SELECT vec_id, label, CAST(embedding[1] AS DOUBLE) AS a, CAST(embedding[2] AS DOUBLE) AS b FROM embeddings), m AS (SELECT covar_samp(a, a) AS aa, covar_samp(a, b) AS ab, covar_samp(b, b) AS bb FROM v),
d AS (SELECT t.vec_id AS t_uid, c.vec_id AS c_uid, (bb * (t.a - c.a) * (t.a - c.a) - 2 * ab * (t.a - c.a) * (t.b - c.b) + aa * (t.b - c.b) * (t.b - c.b)) / (aa * bb - ab * ab) AS distance FROM v t JOIN v c ON t.label > 4 AND c.label <= 4{within}, m)
SELECT t_uid, c_uid, round(distance, 6) AS distance FROM d QUALIFY row_number() OVER (PARTITION BY t_uid ORDER BY distance, c_uid) = 1"""


@query(_MD.format(within=" AND abs(t.a + t.b - c.a - c.b) < 0.05"))
def md_pairs_within_caliper(spark, folder):
    """The same among controls within a caliper of a score (here the sum of both components)."""
    return nearest_mahalanobis(_vector_units(spark, folder).withColumn("s", F.col("a") + F.col("b")), SPEC_T, ("a", "b"), score="s", score_caliper=0.05).withColumn("distance", F.round("distance", 6))


def _vector_units(spark, folder):
    first, second = (F.get("embedding", F.lit(i)).cast("double") for i in (0, 1))
    return table(spark, folder, "embeddings").select(F.col("vec_id").alias("uid"), F.when(F.col("label") > 4, 1).otherwise(0).alias("t"), first.alias("a"), second.alias("b"))


@query(_MD.format(within=""))
def md_pairs(spark, folder):
    """Nearest control by Mahalanobis distance on two vector components: whitened, then cells of a
    grid around each treated unit widen until every one has its exact nearest."""
    return nearest_mahalanobis(_vector_units(spark, folder), SPEC_T, ("a", "b")).withColumn("distance", F.round("distance", 6))


@query("""WITH v AS (SELECT vec_id, label, unnest(embedding) AS x, unnest(range(64)) AS i FROM embeddings),
d AS (SELECT t.vec_id AS t_uid, c.vec_id AS c_uid, sqrt(sum((CAST(t.x AS DOUBLE) - CAST(c.x AS DOUBLE)) * (CAST(t.x AS DOUBLE) - CAST(c.x AS DOUBLE)) ORDER BY t.i)) AS distance FROM v t JOIN v c ON t.i = c.i AND t.label > 4 AND c.label <= 4 GROUP BY ALL)
SELECT t_uid, c_uid, round(distance, 6) AS distance FROM d QUALIFY row_number() OVER (PARTITION BY t_uid ORDER BY distance, c_uid) = 1""")
def embedding_nn(spark, folder):
    """Nearest control vector (label 4 or less) of each treated one by Euclidean distance."""
    e = table(spark, folder, "embeddings").select(F.col("vec_id").alias("uid"), F.col("embedding").alias("v"), "label")
    return nearest_vectors(e.where("label > 4"), e.where("label <= 4")).withColumn("distance", F.round("distance", 6))


@query(units("SELECT t_uid, c_uid, round(sqrt(distance), 6) AS d FROM edges", SCORED, _NARROW))
def udf_distance(spark, folder):
    """A user's distance as a vectorised function, called once for each different distance of candidate pairs."""
    d = distance_udf(lambda a, b: (a - b) ** 0.5)
    return measured_pairs(written_scores(spark, folder), SPEC, "ps", 200, lambda distance: F.round(d(distance, F.lit(0.0)), 6))
