"""Views of units over the given tables.

Money and shares are whole numbers (cents, per cent, 1e-4 for revenue), so that sums
are exact in any order.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.coarsening import week
from ..functions.treatments import conjunction, predicate_treatment, threshold_treatment
from ..plans.spec import TreatmentSet, UnitSpec
from .catalog import table
from .shared import materialized, passing

LINE_ORDER = ("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice", "l_quantity")
COARSE = ("p_brand", "p_type", "c_mktsegment", "o_orderstatus", "cx_total")
TREATMENTS = ("t_bulk", "t_combo", "t_disc", "t_heavy", "t_urgent")
SHARED = ("p_brand", "p_type", "c_mktsegment", "cx_week")


def whole(name: str, factor: int):
    """A value times ``factor`` as a whole number."""
    return F.round(F.col(name) * factor).cast("long")


def keyed_lines(spark: SparkSession, folder: str) -> DataFrame:
    """lineitem with ``seq`` and ``uid``; ids are computed inside an order, so they scale."""
    seq = F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*LINE_ORDER))
    return table(spark, folder, "lineitem").withColumn("seq", seq).withColumn("uid", F.col("l_orderkey") * 1000 + F.col("seq"))


def sold_orders(spark: SparkSession, folder: str) -> DataFrame:
    """orders with their customer, nation and region."""
    t = lambda n: table(spark, folder, n)
    return t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))


def bulk():
    """The treatment of large quantities against small ones."""
    return threshold_treatment("l_quantity", "> 40", "< 20").alias("t_bulk")


def coarse_total():
    """The bucket of an order's price."""
    return F.floor(F.col("o_totalprice") / 50000).cast("int").alias("cx_total")


def scored_covariates():
    """The covariates of the score."""
    return whole("o_totalprice", 100).alias("total"), F.col("p_size").alias("size"), whole("c_acctbal", 100).alias("acct")


def line_units(spark: SparkSession, folder: str) -> DataFrame:
    """One row for each line with its order, part, customer and region."""
    t, sold = (lambda n: table(spark, folder, n)), sold_orders(spark, folder)
    # Parts last: lines move for orders and for parts only, and the names of parts do not move again.
    rows = keyed_lines(spark, folder).join(sold, F.col("l_orderkey") == F.col("o_orderkey")).join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
    (total, size, acct), tax, discount = scored_covariates(), whole("l_tax", 100), whole("l_discount", 100)
    rows = rows.select(
        "uid", "seq", "l_orderkey", "p_partkey", F.col("l_shipdate").alias("ship_date"), "p_brand", "p_type", "c_mktsegment", "o_orderstatus", F.col("r_name").alias("site"),
        bulk(), threshold_treatment("l_discount", ">= 0.075", "<= 0.045").alias("t_disc"),
        predicate_treatment("o_orderpriority = '1-URGENT'").alias("t_urgent"), predicate_treatment("p_size > 35 and p_retailprice > 930").alias("t_heavy"),
        (whole("l_extendedprice", 100) * (100 - discount)).alias("y_rev"), predicate_treatment("l_returnflag = 'R'").alias("y_ret"),
        total, whole("p_retailprice", 100).alias("retail"), acct, tax.alias("tax"), size,
        coarse_total(), F.floor(tax / 3).cast("int").alias("cx_tax"), week(F.col("l_shipdate")).alias("cx_week"),
    )
    rows = rows.withColumn("t_combo", conjunction("t_bulk", "t_disc"))
    return rows.withColumn("t_rare", conjunction("t_combo", "t_urgent")).withColumn("h", ((F.col("l_orderkey") * 7919 + F.col("seq") * 104729) % 1000).cast("int"))


def line_spec(treatment: str = "t_bulk", covariates=COARSE, measured=("total", "acct")) -> UnitSpec:
    return UnitSpec("uid", treatment, tuple(covariates), ("y_rev", "y_ret"), tuple(measured))


def line_treatments(by_day: bool = False) -> TreatmentSet:
    """Five treatments, one of them a conjunction of two. ``by_day``: the day of shipping instead of its
    week, so that strata stay small on large tables."""
    own = {"t_bulk": ("o_orderstatus",), "t_disc": ("cx_tax",), "t_combo": ("o_orderstatus", "cx_tax"), "t_urgent": ("cx_total",), "t_heavy": ("cx_total",)}
    dated = (*SHARED[:3], "ship_date") if by_day else SHARED
    shared = {t: dated if t in ("t_bulk", "t_disc", "t_combo") else SHARED[:3] for t in own}
    return TreatmentSet("uid", {t: shared[t] + own[t] for t in sorted(own)}, ("y_rev", "y_ret"))


def hash_sample(df: DataFrame, keep_per_1000: int, column: str = "h") -> DataFrame:
    """Rows whose arithmetic hash of the key is below the limit: one sample on every engine."""
    return df.where(F.col(column) < keep_per_1000)


def planted_units(units: DataFrame, kind: str) -> DataFrame:
    """Units with a known effect of 5: assignment depends on tax (``discrete``) or on the
    order's price (``continuous``), and so does the outcome (here in units of 1/1000 or 1/100)."""
    if kind == "discrete":
        pr, base, step = F.when(F.col("tax") >= 5, 800).when(F.col("tax") >= 3, 500).otherwise(200), F.col("tax") * 10, 5
        y = (base + step * F.col("t_bulk")).cast("long")
    else:
        pr = 100 + 800 * F.col("total") / 50_000_000
        y = (F.col("total") + 500_000 * F.col("t_bulk")).cast("long")  # 1e-5: price / 1000 + 5
    kept = ((F.col("t_bulk") == 1) & (F.col("h") < pr)) | ((F.col("t_bulk") == 0) & (F.col("h") >= pr))
    return units.where("t_bulk is not null").where(kept).withColumn("y", y)


def scored_units(units: DataFrame, treatment: str = "t_bulk") -> DataFrame:
    """Units with a defined treatment and a fixed logistic score in whole micro-units ``ps``."""
    z = -3 + 5 * F.col("total") / 100 / 500000 + 1.0 * F.col("size") / 50 - F.col("acct") / 100 / 10000
    return units.where(F.col(treatment).isNotNull()).withColumn("ps", F.round(1e6 / (1 + F.exp(-z))).cast("long"))


def _bulk_lines(spark, folder):
    """Lines with a defined ``t_bulk``, numbered and with the keys of their parts and orders."""
    return keyed_lines(spark, folder).select("uid", "l_orderkey", "l_partkey", bulk()).where("t_bulk is not null")


def written_scores(spark: SparkSession, folder: str) -> DataFrame:
    """(uid, t_bulk, ps) of ``scored_units(line_units(...))`` as a written table. Lines are numbered and written
    before they meet parts and orders, so that the scratch disk holds one of both shuffles at a time."""
    with passing(_bulk_lines(spark, folder), "lines") as lines:
        rows = lines.join(table(spark, folder, "part"), F.col("l_partkey") == F.col("p_partkey"))
        rows = rows.join(sold_orders(spark, folder), F.col("l_orderkey") == F.col("o_orderkey"))
        return materialized(scored_units(rows.select("uid", "t_bulk", *scored_covariates())).select("uid", "t_bulk", "ps"), "scores", free=True)


def written_codes(spark: SparkSession, folder: str) -> DataFrame:
    """(uid, t_bulk, p_brand, p_type, cx_total) of the same units as a written table, in the same steps; parts last, so that
    their names do not move again."""
    with passing(_bulk_lines(spark, folder), "lines") as lines:
        priced = lines.join(sold_orders(spark, folder), F.col("l_orderkey") == F.col("o_orderkey")).select("uid", "t_bulk", "l_partkey", coarse_total())
        rows = priced.join(table(spark, folder, "part"), F.col("l_partkey") == F.col("p_partkey"))
        return materialized(rows.select("uid", "t_bulk", "p_brand", "p_type", "cx_total"), "coded", free=True)


def trips_and_readings(spark: SparkSession, folder: str):
    """(trips, readings, all events) with ``site`` and epoch seconds ``sec``."""
    events = table(spark, folder, "events")
    events = events.withColumn("site", (F.col("user_id") % 5).cast("int")).withColumn("sec", F.unix_timestamp(F.col("ts").cast("timestamp")))
    return events.where("event_type = 'purchase'"), events.where("event_type = 'error'"), events


def document_units(spark: SparkSession, folder: str) -> DataFrame:
    """Labelled documents: treatment toxic, outcome quality, covariates lang and length band."""
    labels = table(spark, folder, "labels")
    docs = table(spark, folder, "documents").select("doc_id", "lang", "source", "n_chars")
    return docs.join(labels, "doc_id").select(F.col("doc_id").alias("uid"), F.col("toxic").alias("t"), F.col("quality").alias("y"), "lang", "source", F.floor(F.log2(F.greatest(F.col("n_chars"), F.lit(1)))).cast("int").alias("band"))
