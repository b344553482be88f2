"""Queries over scored units: every unit with a defined treatment takes part."""

import re
import time
from collections import defaultdict

import numpy as np
import pytest

from stratamatch import workloads
from stratamatch.operators.neighbours import caliper_rule, candidate_pairs, match_sorted, nearest_without_replacement
from stratamatch.plans.spec import UnitSpec
from stratamatch.sources.units import line_units, scored_units, written_scores

from .oracle import connection

workloads.load()


@pytest.fixture(scope="module")
def scored(spark, small):
    """(uid, treated, ps) of all units, from the SQL."""
    sql = workloads.SQL["ps_trim"].replace("SELECT uid, ps FROM scored WHERE ps BETWEEN 100000 AND 900000", "SELECT uid, t_bulk, ps FROM scored")
    return connection(small).sql(sql).fetchall()


def _edges(scored, caliper=1000):
    return [(t, c, abs(p - q), p) for t, one, p in scored if one == 1 for c, other, q in scored if other == 0 and abs(p - q) < caliper]


def _greedy(edges, k, key):
    room, used, out = defaultdict(lambda: k), set(), set()
    for t, c, d, _ in sorted(edges, key=key):
        if room[t] and c not in used:
            room[t] -= 1
            used.add(c)
            out.add((t, c, float(d)))
    return out


def test_every_scored_unit_takes_part(spark, small, scored):
    assert scored_units(line_units(spark, small)).count() == len(scored) == 3493
    assert workloads.QUERIES["nn_candidates"](spark, small).count() == len(_edges(scored)) == 7272


def test_no_query_is_sampled():
    assert {n for n in workloads.SQL if "h < 50" in workloads.SQL[n]} == {"sample_units"}


@pytest.mark.parametrize("k", [1, 3])
def test_sorted_plans_equal_those_of_all_edges(spark, small, k):
    rows = scored_units(line_units(spark, small))
    spec = UnitSpec("uid", "t_bulk", ())
    edges = candidate_pairs(rows, spec, "ps", 1000)
    for mode in ("single_pass", "refill", "greedy"):
        want = {tuple(r) for r in nearest_without_replacement(edges, k, mode).select("t_uid", "c_uid", "distance", "rnk").collect()}
        assert {tuple(r) for r in match_sorted(rows, spec, "ps", k, 1000, mode).collect()} == want


def test_caliper_rule(spark):
    p = [0.1, 0.25, 0.5, 0.7, 0.9]
    want = 0.2 * np.std([np.log(x / (1 - x)) for x in p], ddof=1)
    assert caliper_rule(spark.createDataFrame([(x,) for x in [*p, 0.0, 1.0, None]], "ps double"), "ps") == pytest.approx(want)


def test_one_task_scan_as_a_mode(spark, small):
    edges = candidate_pairs(scored_units(line_units(spark, small)).where("h < 200"), UnitSpec("uid", "t_bulk", ()), "ps", 1000)
    rounds, scan = ({tuple(r) for r in nearest_without_replacement(edges, 2, mode).collect()} for mode in ("greedy", "greedy_local"))
    assert rounds == scan


def test_vectors_of_all_labels_take_part(spark, small):
    rows = [(r.vec_id, r.label, np.array(r.embedding, dtype=float)) for r in spark.read.parquet(f"{small}/embeddings.parquet").collect()]
    controls = [(i, v) for i, label, v in rows if label <= 4]
    want = {(i, *min((round(float(np.sqrt(((v - w) ** 2).sum())), 6), c) for c, w in controls)) for i, label, v in rows if label > 4}
    got = {(r.t_uid, r.distance, r.c_uid) for r in workloads.QUERIES["embedding_nn"](spark, small).collect()}
    assert len(got) == len(want) > 200 and {(t, c) for t, _, c in got} == {(t, c) for t, _, c in want}
    assert dict((t, d) for t, d, _ in got) == pytest.approx(dict((t, d) for t, d, _ in want), abs=2e-6)


def test_nearest_of_all_without_caliper(spark, small, scored):
    controls = [(u, p) for u, t, p in scored if t == 0]
    want = {(u, *min((abs(p - q), c) for c, q in controls)) for u, t, p in scored if t == 1}
    assert {(r.t_uid, int(r.distance), r.c_uid) for r in workloads.QUERIES["nnmwr_no_caliper"](spark, small).collect()} == want


@pytest.mark.parametrize("name, k, key", [("nnmnr_greedy", 3, lambda e: (e[2], e[0], e[1])), ("nnmnr_greedy_by_score", 1, lambda e: (-e[3], e[0], e[2], e[1]))])
def test_greedy_of_all_equals_the_scan(spark, small, scored, name, k, key):
    got = {(r.t_uid, r.c_uid, r.distance) for r in workloads.QUERIES[name](spark, small).collect()}
    assert got == _greedy(_edges(scored), k, key)


@pytest.mark.parametrize("order", [("distance", "t_uid", "c_uid"), ("priority", "t_uid", "distance", "c_uid")])
def test_greedy_with_one_score_held_by_many(spark, order):
    """250000 tied edges, more than the one-task scan once took: unit i takes the i-th control."""
    n = 500
    edges = spark.range(n * n).selectExpr(f"id div {n} as t_uid", f"10000 + id % {n} as c_uid", "0.0D as distance", "0 as priority")
    got = {(r.t_uid, r.c_uid, r.rnk) for r in nearest_without_replacement(edges, 1, "greedy", 1, order).collect()}
    assert got == {(i, 10000 + i, 1) for i in range(n)}
    few = nearest_without_replacement(edges, 3, "greedy", 1, order)
    assert {(r.t_uid, r.c_uid) for r in few.collect()} == {(i // 3, 10000 + i) for i in range(n)}


def test_arms_of_coarsened_pairs_come_from_one_read_of_the_lines(spark, small):
    """Both arms once ran the joins of units; the pairs read a written table only."""
    pairs = workloads.QUERIES["dist_coarsened"](spark, small)
    assert not any("lineitem" in f or "orders" in f for f in pairs.inputFiles())


def test_names_of_parts_move_for_parts_only(spark, small):
    """Parts are joined last: no exchange after theirs carries p_type."""
    keep = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = line_units(spark, small).select("uid", "p_type", "total", "acct")._jdf.queryExecution().optimizedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", keep)
    joins = [line for line in plan.splitlines() if "Join Inner" in line]
    assert "l_partkey" in joins[0] and "l_orderkey" in joins[1]


def test_candidates_come_from_written_lists(spark, small):
    """Both arms once ran the joins of units, and treated units moved three times, not the lists of their scores."""
    pairs = workloads.QUERIES["nn_candidates"](spark, small)
    assert pairs.inputFiles() and not any("lineitem" in f or "orders" in f for f in pairs.inputFiles())


def test_written_scores_leave_no_shuffle(spark, small, scored):
    """Rows of all scored units; the shuffles that made them are gone."""

    def shuffles():
        files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString(" ")
        return set(re.findall(r"shuffle_\d+_", files))

    before = shuffles()
    got = written_scores(spark, small)
    deadline = time.time() + 10
    while (left := shuffles() - before) and time.time() < deadline:
        time.sleep(0.1)
    assert not left
    assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled") == "false"
    assert sorted(tuple(r) for r in got.collect()) == sorted(scored)
