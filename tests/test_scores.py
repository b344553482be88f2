"""Matching by scores on tables where the edges within the caliper are too many to make."""

import random

import pytest
from pyspark.sql import functions as F

from stratamatch import workloads
from stratamatch.operators.neighbours import candidate_pairs, greedy_violations, greedy_violations_by_score, listed_pairs, match_sorted, measured_pairs, nearest_by_scores, theta_pairs
from stratamatch.plans.spec import UnitSpec

workloads.load()
SPEC = UnitSpec("uid", "t", ())


def drawn(seed, n=120, scores=40, null=True):
    r = random.Random(seed)
    rows = [(uid, int(r.random() < r.choice((0.3, 0.6))), r.randrange(-scores // 2, scores)) for uid in r.sample(range(10 * n), n)]
    return [*rows, (-1, 1, None), (-2, 0, None), (-3, None, 3)] if null else rows


def all_edges(rows, caliper):
    sides = [[(u, x) for u, t, x in rows if t == a and x is not None] for a in (1, 0)]
    return [(abs(x - y), t, c, x) for t, x in sides[0] for c, y in sides[1] if abs(x - y) < caliper]


def scan(edges, k, key):
    room, used, out = {}, set(), set()
    for e in sorted(edges, key=key):
        d, t, c = e[:3]
        if c not in used and room.get(t, 0) < k:
            room[t] = room.get(t, 0) + 1
            used.add(c)
            out.add((t, c, float(d)))
    return out


def found(df):
    return {(r.t_uid, r.c_uid, r.distance) for r in df.collect()}


def units(spark, rows):
    return spark.createDataFrame(rows, "uid long, t int, x long")


@pytest.mark.parametrize("seed, k, caliper", [(1, 1, 7), (2, 1, 100), (3, 2, 3), (4, 3, 15), (5, 1, 0.5), (6, 1, 2.5)])
def test_greedy_by_score_is_the_scan(spark, seed, k, caliper):
    rows = drawn(seed)
    want = scan(all_edges(rows, caliper), k, lambda e: (-e[3], e[1], e[0], e[2]))
    assert found(match_sorted(units(spark, rows), SPEC, "x", k, caliper, "greedy_by_score")) == want
    if seed == 2:  # fractions go the way of edges
        real = units(spark, rows).selectExpr("uid", "t", "x / 2.0 as x")
        assert {p[:2] for p in found(match_sorted(real, SPEC, "x", k, caliper / 2, "greedy_by_score"))} == {p[:2] for p in want}


def test_greedy_by_score_of_400_million_edges(spark):
    """20000 units of either arm at two scores: made as edges they fill the disk."""
    n = 20_000
    rows = spark.range(2 * n).selectExpr("id as uid", "cast(id % 2 as int) as t", "5 + id div 20000 as x")
    got = match_sorted(rows, SPEC, "x", 1, 10, "greedy_by_score").where("t_uid = c_uid + 1 and distance = 0").count()
    assert got == n


def test_no_units_no_pairs(spark):
    assert match_sorted(units(spark, [(1, 1, 5)]), SPEC, "x", 1, 10, "greedy_by_score").count() == 0
    assert match_sorted(units(spark, [(1, 0, None)]), SPEC, "x", 1, 10, "greedy_by_score").count() == 0


def first_ones(rows, k, caliper, ties="first"):
    by_t, out = {}, set()
    for d, t, c, _ in all_edges(rows, caliper):
        by_t.setdefault(t, []).append((d, c))
    for t, near in by_t.items():
        near.sort()
        last = near[min(k, len(near)) - 1][0]
        for i, (d, c) in enumerate(near):
            if ties == "first" and i < k or ties == "all" and d <= last:
                out.add((t, c, float(d), 1 + (i if ties == "first" else sum(x < d for x, _ in near))))
    return out


def ranked(df):
    got = [(r.t_uid, r.c_uid, r.distance, r.rnk) for r in df.collect()]
    assert len(got) == len(set(got))
    return set(got)


@pytest.mark.parametrize("plan, k", [("antijoin", 1), ("antijoin", 3), ("window", 2)])
def test_nearest_by_scores_is_the_first_edges(spark, plan, k):
    rows = drawn(7)
    for caliper in (2, 1000, None):
        assert ranked(nearest_by_scores(units(spark, rows), SPEC, "x", k, caliper, plan=plan)) == first_ones(rows, k, caliper or 10**9)


def test_antijoin_of_400_million_edges(spark):
    """The self-join of these edges has 4 * 10^12 rows."""
    rows = spark.range(40_000).selectExpr("id as uid", "cast(id % 2 as int) as t", "cast(5 as long) as x")
    got = nearest_by_scores(rows, SPEC, "x", 3, 10, plan="antijoin")
    assert got.groupBy("c_uid", "rnk").count().sort("rnk").collect() == [(0, 1, 20_000), (2, 2, 20_000), (4, 3, 20_000)]


def test_window_of_400_million_edges(spark):
    """Made as edges they are sorted by treated unit; here one treated unit ranks for its score."""
    rows = spark.range(40_000).selectExpr("id as uid", "cast(id % 2 as int) as t", "cast(5 as long) as x")
    got = nearest_by_scores(rows, SPEC, "x", 3, 10)
    assert got.groupBy("c_uid", "rnk").count().sort("rnk").collect() == [(0, 1, 20_000), (2, 2, 20_000), (4, 3, 20_000)]
    assert "band" not in workloads.QUERIES["nnmwr_k3"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().toString()


def test_nearest_within_blocks_by_scores(spark):
    rows = [(u, t, x, b) for i, b in enumerate((None, "a", "b", "c")) for u, t, x in ((u * 4 + i, t, x) for u, t, x in drawn(8 + i, 60, null=i == 1))]
    rows = [r for r in rows if r[3] != "c" or r[1] == 1]  # a block without controls
    df = spark.createDataFrame(rows, "uid long, t int, x long, block string")
    for k, caliper, ties in ((1, 5, "first"), (2, None, "first"), (2, 30, "all")):
        want = set().union(*(first_ones([r[:3] for r in rows if r[3] == b], k, caliper or 10**9, ties) for b in (None, "a", "b", "c")))
        assert ranked(nearest_by_scores(df, SPEC, "x", k, caliper, ("block",), ties=ties)) == want


@pytest.mark.parametrize("k", [1, 2, 5])
def test_all_ties_by_scores(spark, k):
    rows = drawn(9, 200)
    for caliper in (2, 1000):
        assert ranked(nearest_by_scores(units(spark, rows), SPEC, "x", k, caliper, ties="all")) == first_ones(rows, k, caliper, "all")


@pytest.mark.parametrize("n, scores", [(120, 40), (150, 400), (60, 6)])
def test_greedy_is_the_scan(spark, n, scores):
    """Chains of equal distances, capacities that end inside a score, calipers that cut."""
    import numpy as np

    from stratamatch.operators import scan as scans

    for seed in range(40):
        rows = drawn(seed, n, scores, null=False)
        arms = [[np.array(v, np.int64).reshape(-1) for v in zip(*((u, x) for u, t, x in rows if t == a))] for a in (1, 0)]
        for k, caliper in ((1, 1000), (2, 9), (3, 2.5)):
            got = [r for b in scans.by_distance(*(scans.Arm(*a) for a in arms), k, caliper) for r in b.to_pylist()]
            pairs = {(r["t_uid"], r["c_uid"], r["distance"]) for r in got}
            assert len(pairs) == len(got) and pairs == scan(all_edges(rows, caliper), k, lambda e: e[:3]), seed
    rows = drawn(1)
    assert found(match_sorted(units(spark, rows), SPEC, "x", 2, 9, "greedy")) == scan(all_edges(rows, 9), 2, lambda e: e[:3])


def test_greedy_of_400_million_edges(spark):
    """Tied distances once needed a round for each treated unit of a score, then all edges."""
    rows = spark.range(40_000).selectExpr("id as uid", "cast(id % 2 as int) as t", "5 + id % 2 as x")
    assert match_sorted(rows, SPEC, "x", 1, 10, "greedy").where("t_uid = c_uid + 1 and distance = 1").count() == 20_000


@pytest.mark.parametrize("seed, k", [(1, 1), (2, 2), (3, 1), (4, 3)])
def test_blocking_edges_by_score(spark, seed, k):
    """Greedy results, and results with pairs lost, exchanged and repeated."""
    rows, r = drawn(seed, 90), random.Random(seed)
    df, edges = units(spark, rows), all_edges(rows, 9)
    greedy = sorted(scan(edges, k, lambda e: e[:3]))
    broken = [greedy, [], r.sample(greedy, len(greedy) * 3 // 4), [(t, c, float(d)) for d, t, c, _ in r.sample(edges, 60)]]
    pairs = candidate_pairs(df, SPEC, "x", 9)
    for i, result in enumerate(broken):
        out = spark.createDataFrame(result, "t_uid long, c_uid long, distance double")
        got = greedy_violations_by_score(df, SPEC, "x", 9, out, k).first()
        assert got == greedy_violations(pairs, out, k).first()
        assert (i == 0) == (got.blocking_edges == 0)


def test_treatment_lattice_reads_its_units(spark, small):
    """Arms of every conjunction, counted from the table."""
    from stratamatch.sources.units import line_units

    got = {r.treatment: r for r in workloads.QUERIES["treatment_lattice"](spark, small).collect()}
    rows = line_units(spark, small).select("t_bulk", "t_disc", "t_urgent").collect()
    assert len(got) == 7
    for name, r in got.items():
        parts = name.split(",")
        assert r["size"] == len(parts)
        assert r.treated == sum(all(u[p] == 1 for p in parts) for u in rows) > 0
        assert r.controls == sum(any(u[p] == 0 for p in parts) for u in rows) > 0


@pytest.mark.parametrize("block", [1, 7, 1000])
def test_nested_loop_by_blocks(spark, block):
    rows = drawn(11)
    for caliper in (0.5, 4, 1000):
        got = [(r.t_uid, r.c_uid, r.distance) for r in theta_pairs(units(spark, rows), SPEC, "x", caliper, block).collect()]
        assert len(got) == len(set(got)) and set(got) == {(t, c, float(d)) for d, t, c, _ in all_edges(rows, caliper)}
    plan = theta_pairs(units(spark, rows), SPEC, "x", 4, min(block, 7))._jdf.queryExecution().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan


@pytest.mark.parametrize("kind", ["long", "double"])
def test_a_users_distance_is_called_for_distances_not_pairs(spark, kind):
    """All pairs get their value, though the function sees each different distance once."""
    from stratamatch.sqlapi import distance_udf

    rows, seen = drawn(11, n=300), spark.sparkContext.accumulator(0)

    def root(a, b):
        seen.add(len(a))
        return (a - b) ** 0.5

    d = distance_udf(root)
    df = units(spark, rows).withColumn("x", F.col("x").cast(kind))
    got = measured_pairs(df, SPEC, "x", 7, lambda distance: d(distance, F.lit(0.0))).collect()
    edges = all_edges(rows, 7)
    assert len(got) == len(edges) > 1000 and {(r.t_uid, r.c_uid, r.d) for r in got} == {(t, c, x**0.5) for x, t, c, _ in edges}
    assert seen.value == len({x for x, *_ in edges}) == 7


@pytest.mark.parametrize("kind, size", [("long", 1), ("long", 3), ("double", 128)])
def test_pairs_of_lists_are_all_edges(spark, monkeypatch, kind, size):
    """Lists of a score are joined and unfolded: full, split and single ones, without nulls."""
    monkeypatch.setattr("stratamatch.operators.neighbours.LIST", size)
    rows = drawn(11)
    df = units(spark, rows).withColumn("x", F.col("x").cast(kind))
    for caliper in (0, 0.5, 4, 1000):
        got = [(r.t_uid, r.c_uid, r.distance) for r in listed_pairs(df, SPEC, "x", caliper).collect()]
        assert len(got) == len(set(got)) and set(got) == {(t, c, float(d)) for d, t, c, _ in all_edges(rows, caliper)}
    assert listed_pairs(df, SPEC, "x", 4).schema == candidate_pairs(df, SPEC, "x", 4).schema


def test_lists_are_short_and_each_holds_one_score(spark):
    from stratamatch.operators.neighbours import LIST, _id_lists

    rows = spark.range(3000).selectExpr("id as uid", "cast(id % 2 as int) as t", "if(id < 2000, 7L, id) as x")
    lists = _id_lists(rows, SPEC, "x").collect()
    assert max(len(r.uid) for r in lists) == LIST and len([r for r in lists if r.x == 7]) < 40
    assert sorted((i, r.t, r.x) for r in lists for i in r.uid) == [(i, i % 2, 7 if i < 2000 else i) for i in range(3000)]
