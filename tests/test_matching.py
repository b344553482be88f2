"""Properties, worked cases and edge cases of the matching operators."""

import random

import pytest
from pyspark.sql import functions as F

from stratamatch.functions import coarsening, treatments
from stratamatch.functions.distances import covariance, mahalanobis, whitened
from stratamatch.operators import balance, effects
from stratamatch.operators.lattice import smallest_ancestor
from stratamatch.operators.multi import partition_treatments, phi_matrix
from stratamatch.operators.neighbours import greedy_local, nearest_sorted, nearest_with_replacement, nearest_without_replacement
from stratamatch.operators.pushdown import cem_auto, cem_pushed
from stratamatch.operators.ranking import with_rank
from stratamatch.operators.strata import cem, overlap_report, overlapping, summarize
from stratamatch.operators.subclass import subclassify
from stratamatch.plans.dag import check_pretreatment, d_separated, minimal_adjustment_set
from stratamatch.plans.spec import TreatmentSet, UnitSpec, checked_treatment

SCHEMA = "uid long, t int, x int, y long"
SPEC = UnitSpec("uid", "t", ("x",), ("y",))


def frame(spark, rows, schema=SCHEMA):
    return spark.createDataFrame(rows, schema)


@pytest.mark.parametrize(
    "rows",
    [[], [(1, 1, 0, 5)], [(1, 1, 0, 5), (2, 1, 0, 6)], [(1, 0, 0, 5)], [(1, None, 0, 5), (2, None, 1, 1)], [(1, 1, 0, 5), (2, 0, 1, 6)]],
)
def test_without_overlap_there_is_no_effect(spark, rows):
    df = frame(spark, rows)
    for plan in ("groupby", "window"):
        assert cem(df, SPEC, plan).count() == 0
    row = effects.stratified_effect(overlapping(summarize(df, SPEC)), ("y",)).first()
    assert (row["n"], row["ate_y"]) == (0, None)


def test_null_covariates_form_a_stratum(spark):
    df = frame(spark, [(1, 1, None, 5), (2, 0, None, 3), (3, 1, 2, 9)])
    assert {(r.uid, r.subclass) for r in cem(df, SPEC).collect()} == {(1, 2), (2, 2)}
    assert effects.stratified_effect(overlapping(summarize(df, SPEC)), ("y",)).first()["ate_y"] == 2


def test_one_stratum_equals_the_naive_difference(spark):
    df = frame(spark, [(i, i % 2, 1, i * i) for i in range(9)])
    naive = effects.naive_effect(df, SPEC).first()["ate_y"]
    assert effects.stratified_effect(overlapping(summarize(df, SPEC)), ("y",)).first()["ate_y"] == pytest.approx(naive)


def test_other_treatment_values_raise(spark):
    with pytest.raises(Exception, match="must be 0, 1 or null"):
        checked_treatment(frame(spark, [(1, 2, 0, 0)]), SPEC).collect()
    with pytest.raises(ValueError):
        UnitSpec("uid", "t", ("t",))


def test_planted_effect_is_found(spark, small):
    from stratamatch.sources.units import line_units, planted_units

    rows = planted_units(line_units(spark, small), "discrete")
    spec = UnitSpec("uid", "t_bulk", ("tax",), ("y",))
    assert effects.stratified_effect(overlapping(summarize(rows, spec)), ("y",)).first()["ate_y"] == pytest.approx(5.0)
    assert effects.naive_effect(rows, spec).first()["ate_y"] == pytest.approx(27.602, abs=0.001)


def test_exact_matching_leaves_no_imbalance(spark, small):
    from stratamatch.sources.units import line_units

    spec = UnitSpec("uid", "t_bulk", ("tax", "o_orderstatus"), (), ("tax",))
    assert balance.awmd(overlapping(summarize(line_units(spark, small), spec)), ("tax",)).first()[0] == 0


def test_results_do_not_depend_on_partitions(spark, small):
    from stratamatch.sources.units import line_spec, line_units

    u = line_units(spark, small)
    want = sorted(map(tuple, cem(u, line_spec()).select("uid", "subclass").collect()))
    for n in (1, 7):
        assert sorted(map(tuple, cem(u.repartition(n), line_spec()).select("uid", "subclass").collect())) == want


def _edges(rng, n_t, n_c, p):
    return [(t, 1000 + c, float(rng.randrange(6))) for t in range(n_t) for c in range(n_c) if rng.random() < p]


def _scan(edges, k):
    room, used, out = {}, set(), set()
    for t, c, d in sorted(edges, key=lambda e: (e[2], e[0], e[1])):
        if room.get(t, k) and c not in used:
            room[t] = room.get(t, k) - 1
            used.add(c)
            out.add((t, c))
    return out


@pytest.mark.parametrize("k", [1, 2])
def test_greedy_rounds_equal_the_scan(spark, k):
    rng = random.Random(k)
    edges = _edges(rng, 12, 15, 0.4)
    df = frame(spark, edges, "t_uid long, c_uid long, distance double")
    got = {(r.t_uid, r.c_uid) for r in nearest_without_replacement(df, k, "greedy").collect()}
    assert got == _scan(edges, k)
    assert {(r.t_uid, r.c_uid) for r in greedy_local(df.withColumn("left", F.lit(k))).collect()} == got
    assert {(r.t_uid, r.c_uid) for r in nearest_without_replacement(df, k, "greedy", max_rounds=1).collect()} == got


def test_greedy_in_order_of_priority(spark):
    rng = random.Random(9)
    edges = [(t, c, d, -(t % 3)) for t, c, d in _edges(rng, 9, 9, 0.5)]
    df = frame(spark, edges, "t_uid long, c_uid long, distance double, priority int")
    order = ("priority", "t_uid", "distance", "c_uid")
    want, used, full = set(), set(), set()
    for t, c, _, _ in sorted(edges, key=lambda e: (e[3], e[0], e[2], e[1])):
        if t not in full and c not in used:
            want.add((t, c))
            full.add(t)
            used.add(c)
    for rounds in (1, 40):
        assert {(r.t_uid, r.c_uid) for r in nearest_without_replacement(df, 1, "greedy", rounds, order).collect()} == want


def test_factorized_fit_equals_the_joined_fit(spark):
    from stratamatch.operators.propensity import fit_propensity, fit_propensity_factorized

    rng = random.Random(4)
    dim = spark.createDataFrame([(k, rng.random(), rng.random()) for k in range(40)], "k long, a double, b double")
    fact = spark.createDataFrame([(i, i % 40, int(rng.random() < 0.3 + 0.4 * (i % 40) / 40)) for i in range(800)], "uid long, k long, t int")
    _, w, b = fit_propensity_factorized(dim, fact, "k", "t", ("a", "b"))
    _, v, c = fit_propensity(fact.join(dim, "k"), UnitSpec("uid", "t", ()), numeric=("a", "b"))
    assert [*w.values(), b] == pytest.approx([*v.values(), c], abs=1e-4)


def _best_size(edges):
    """Maximum number of disjoint pairs (augmenting paths)."""
    near, mate = {}, {}
    for t, c, _ in edges:
        near.setdefault(t, []).append(c)

    def grow(t, seen):
        for c in near[t]:
            if c not in seen:
                seen.add(c)
                if c not in mate or grow(mate[c], seen):
                    mate[c] = t
                    return True
        return False

    return sum(grow(t, set()) for t in near)


def test_greedy_size_is_at_least_half_of_the_best():
    for seed in range(50):
        edges = _edges(random.Random(seed), 10, 8, 0.25)
        assert 2 * len(_scan(edges, 1)) >= _best_size(edges)


def test_modes_differ_where_a_best_edge_belongs_to_a_full_unit(spark):
    edges = [(1, 11, 1.0), (1, 12, 2.0), (2, 12, 3.0), (1, 13, 4.0), (2, 13, 5.0), (3, 13, 9.0)]
    df = frame(spark, edges, "t_uid long, c_uid long, distance double")
    got = {m: {(r.t_uid, r.c_uid) for r in nearest_without_replacement(df, 1, m).collect()} for m in ("single_pass", "refill", "greedy")}
    assert got["greedy"] == _scan(edges, 1) == {(1, 11), (2, 12), (3, 13)}
    assert got["single_pass"] == got["refill"] == {(1, 11)}


@pytest.mark.parametrize("rows", [[(1, 1, 0, 5), (2, 0, 0, 5), (3, 0, 0, 5), (4, 0, 9, 5)], [(i, i % 2, 7, 0) for i in range(8)], [(1, 1, 5, 0)], [(1, 0, 5, 0)]])
@pytest.mark.parametrize("k", [1, 3])
def test_sorted_plan_equals_all_pairs(spark, rows, k):
    df = frame(spark, rows)
    want = set()
    for u, t, x, _ in rows:
        if t == 1:
            near = sorted((abs(x - b), c) for c, s, b, _ in rows if s == 0)[:k]
            want |= {(u, c) for _, c in near}
    assert {(r.t_uid, r.c_uid) for r in nearest_sorted(df, UnitSpec("uid", "t", ()), "x", k).collect()} == want


def test_k_above_the_controls_and_caliper_zero(spark):
    from stratamatch.operators.neighbours import candidate_pairs

    df = frame(spark, [(1, 1, 0, 0), (2, 0, 0, 0)])
    assert candidate_pairs(df, UnitSpec("uid", "t", ()), "x", 0).count() == 0
    edges = candidate_pairs(df, UnitSpec("uid", "t", ()), "x", 5)
    assert nearest_with_replacement(edges, 9).count() == 1
    with pytest.raises(ValueError):
        nearest_with_replacement(edges, 0)


@pytest.mark.parametrize("n", [1, 3, 5, 10])
def test_ranked_quantiles_equal_ntile(spark, n):
    df = frame(spark, [(i, (i * 7) % 3 % 2, (i * 5) % 11, 0) for i in range(37)])
    a, b = (sorted((r.uid, r["quantile"], r.subclass) for r in subclassify(df, UnitSpec("uid", "t", ()), "x", n, p).collect()) for p in ("ranked", "ntile"))
    assert a == b


def test_approximate_quantiles_are_near(spark):
    df = frame(spark, [(i, i % 2, i % 400, 0) for i in range(2000)])
    sizes = [r["count"] for r in subclassify(df, UnitSpec("uid", "t", ()), "x", 5, "approx").groupBy("quantile").count().collect()]
    assert len(sizes) == 5 and max(sizes) - min(sizes) <= 20


def test_precision_grows_with_the_sample(spark, small):
    from stratamatch.sources.units import hash_sample, line_units

    spec = UnitSpec("uid", "t_bulk", ("o_orderstatus",), ("y_rev",))
    u = line_units(spark, small)
    errors = [effects.standard_error(hash_sample(u, n), spec, "y_rev").first()["se_y_rev"] for n in (50, 200, 1000)]
    assert errors[0] > errors[1] > errors[2] > 0


def test_rank_with_one_hot_score(spark):
    df = frame(spark, [(i, 0, 5, 0) for i in range(50)])
    assert sorted((r["rank"], r.uid) for r in with_rank(df, ["x", "uid"]).collect()) == [(i + 1, i) for i in range(50)]


def test_cut_points_are_half_open():
    with pytest.raises(ValueError):
        coarsening.cut(F.lit(1), [2, 2])


def test_value_equal_to_a_cut_goes_up(spark):
    df = spark.createDataFrame([(None,), (0,), (5,), (9,), (10,)], "v int")
    assert [r[0] for r in df.select(coarsening.cut(F.col("v"), [5, 10])).collect()] == [0, 1, 2, 2, 3]
    assert len(coarsening.histogram_cuts(df, "v", "sturges")) > 0


def test_conjunction_has_three_values(spark):
    df = spark.createDataFrame([(a, b) for a in (0, 1, None) for b in (0, 1, None)], "a int, b int")
    got = [r[0] for r in df.select(treatments.conjunction("a", "b")).collect()]
    assert got == [0, 0, 0, 0, 1, None, 0, None, None]
    assert len(treatments.enumerate_treatments("abc")) == 7


def test_phi_without_a_margin_is_null(spark):
    df = spark.createDataFrame([(1, 0), (1, 1)], "a int, b int")
    assert phi_matrix(df, ("a", "b")).first()["phi"] is None


def test_partition_prefers_correlated_groups():
    ts = TreatmentSet("uid", {t: ("x",) for t in "abcde"})
    phi = {("a", "b"): 0.9, ("a", "c"): 0.8, ("b", "c"): 0.1, ("d", "e"): 0.3}
    assert [g for g, _ in partition_treatments(phi, ts)] == [("a", "b", "c"), ("d", "e")]
    odd = TreatmentSet("uid", {"a": ("x",), "b": ("x",), "c": ("z",)})
    assert sorted(g for g, _ in partition_treatments({("a", "b"): 0.5}, odd)) == [("a", "b"), ("c",)]


def test_smallest_ancestor():
    sizes = {frozenset("abc"): 90, frozenset("ab"): 20, frozenset("bc"): 30}
    assert smallest_ancestor("b", sizes) == frozenset("ab")


DAG = {"season": ["weather", "traffic"], "weather": ["delay", "cancel"], "traffic": ["delay"], "carrier": ["traffic", "delay"], "delay": ["late"]}


def test_adjustment_sets():
    assert minimal_adjustment_set(DAG, "weather", "delay", ["season", "traffic", "carrier"]) == {"season"}
    assert minimal_adjustment_set(DAG, "weather", "delay", ["carrier"]) is None
    assert d_separated(DAG, ["season"], ["carrier"], set()) and not d_separated(DAG, ["season"], ["carrier"], {"traffic"})
    with pytest.raises(ValueError):
        check_pretreatment(DAG, "weather", ["cancel"])


def test_whitening_gives_mahalanobis(spark):
    df = spark.createDataFrame([(1.0, 2.0), (2.0, 1.0), (4.0, 3.0), (0.0, 1.0)], "a double, b double")
    import numpy as np

    cov = covariance(df, ["a", "b"])
    pair = df.limit(1).select(F.lit(1.0).alias("t_a"), F.lit(2.0).alias("t_b"), F.lit(4.0).alias("c_a"), F.lit(3.0).alias("c_b"))
    direct = pair.select(mahalanobis(["a", "b"], np.linalg.inv(cov))).first()[0]
    w = {(r.a, r.b): (r.w_0, r.w_1) for r in whitened(df, ["a", "b"], cov).collect()}
    assert direct == pytest.approx(sum((p - q) ** 2 for p, q in zip(w[1.0, 2.0], w[4.0, 3.0])))


@pytest.mark.parametrize("n", [0, 1, 2, 501])
def test_exact_quantiles_from_ranks(spark, n):
    import numpy as np

    from stratamatch.operators.ranking import exact_quantiles

    values = [int(x) for x in np.random.default_rng(n).integers(0, 40, size=n)]  # many ties
    got = exact_quantiles(spark.createDataFrame([(v,) for v in [*values, None]], "v int"), "v", (0, 0.1, 0.5, 0.77, 1))
    assert got == [None] * 5 if not n else got == pytest.approx(np.quantile(values, (0, 0.1, 0.5, 0.77, 1)).tolist())


def test_pruning_estimate_from_some_strata(spark, small):
    from stratamatch.operators.pushdown import estimated_pruning
    from stratamatch.sources.units import line_spec, line_units

    u, spec = line_units(spark, small), line_spec(covariates=("p_brand", "p_type", "cx_total"))
    assert abs(estimated_pruning(u, spec, 4) - estimated_pruning(u, spec, 1)) < 0.1
    one = line_spec(covariates=("p_type",))
    assert estimated_pruning(u, one, 1000) == estimated_pruning(u, one, 1) == 0.0


def test_mahalanobis_within_a_score_caliper_ends(spark):
    from stratamatch.operators.neighbours import nearest_mahalanobis

    rows = [(i, int(i < 5), float(i % 7), float(i * i % 11), float(100 * (i < 3))) for i in range(40)]
    df = spark.createDataFrame(rows, "uid long, t int, a double, b double, s double")
    got = {r.t_uid for r in nearest_mahalanobis(df, SPEC, ("a", "b"), score="s", score_caliper=1.0).collect()}
    assert got == {3, 4}  # units 0 to 2 have no control of a near score


def test_refresh_completes_dropped_supergroups(spark, tmp_path):
    """Both arms of a supergroup arrive in different parts; a row predicate and a covariate's are answered as from all rows."""
    import random

    from stratamatch.operators.prepare import answer, answer_online, load_manifest, prepare, refresh

    r = random.Random(4)
    rows = [(i, r.choice((0, 1, None)), r.choice((0, 1)), r.randrange(4), r.randrange(5), r.randrange(3), r.randrange(100)) for i in range(300)]
    df = spark.createDataFrame(rows, "uid long, t int, u int, x int, z int, w int, y long")
    ts = TreatmentSet("uid", {"t": ("x", "z"), "u": ("x", "z")}, ("y",))
    first = df.where("(t = 1 or t is null) and u = 1 or uid % 7 = 0")
    path = f"file://{tmp_path}/prepared"
    prepare(first, ts, path)
    refresh(spark, path, df.exceptAll(first).where("uid < 200"))
    refresh(spark, path, df.exceptAll(first).where("uid >= 200"))
    assert load_manifest(spark, path)["version"] == 3
    for treatment in ("t", "u"):
        for where in (None, "x > 1", "w = 1", "x > 0 and w < 2"):
            want, got = (d.first() for d in (answer_online(df, ts, treatment, where), answer(spark, path, treatment, where)))
            assert (got["strata"], got["n"], got["n1"]) == (want["strata"], want["n"], want["n1"]) and got["ate_y"] == pytest.approx(want["ate_y"])


def test_pushdown_choice(spark, small):
    from stratamatch.workloads.matching import CHAIN_SPEC, chain

    how, out = cem_auto(chain(spark, small), CHAIN_SPEC, "p_partkey")
    assert how in ("pushed", "integrated")
    assert out.count() == cem_pushed(chain(spark, small), CHAIN_SPEC, "p_partkey").count()


def test_plans_have_no_nested_loops(spark, small):
    from stratamatch.sources.units import line_spec, line_units
    from stratamatch.workloads.neighbours import edges

    def plan(df):
        return df._jdf.queryExecution().executedPlan().toString()

    u = line_units(spark, small)
    assert "Window [max" not in plan(cem(u, line_spec()))
    assert "NestedLoop" not in plan(edges(spark, small)) and "Cartesian" not in plan(edges(spark, small))
    assert "WindowGroupLimit" in plan(nearest_with_replacement(edges(spark, small), 1))
    one = summarize(u.select("uid", "t_bulk", "y_rev", "p_brand"), UnitSpec("uid", "t_bulk", ("p_brand",), ("y_rev",)))
    assert "partial_sum" in plan(one) and overlap_report(one).first()["strata"] > 0


def test_rounding_and_widths(spark):
    row = frame(spark, [(1, None, 17, 0)]).select(coarsening.rounded(F.lit(2.345), 1).alias("r"), coarsening.width_bucket(F.col("x"), 5).alias("w"), coarsening.width_bucket(-F.col("x"), 5).alias("m"), coarsening.width_bucket(F.lit(None).cast("int"), 5).alias("n")).first()
    assert (row.r, row.w, row.m, row.n) == (2.3, 3, -4, None)
