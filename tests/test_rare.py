"""Quality table of the rare treatment: six methods, every unit."""

from stratamatch import workloads
from stratamatch.sources.units import line_units
from stratamatch.workloads.matching import fitted_units

workloads.load()


def test_six_methods_for_the_rare_treatment(spark, small):
    rows = {r.method: r for r in workloads.QUERIES["method_comparison_rare"](spark, small).collect()}
    assert set(rows) == {"raw", "nn_with_replacement", "nn_without_replacement", "subclass", "exact", "coarsened"}
    defined = line_units(spark, small).where("t_rare is not null").groupBy("t_rare").count().collect()
    assert (rows["raw"].n1, rows["raw"].n0) == tuple(next(r["count"] for r in defined if r.t_rare == a) for a in (1, 0))
    assert 0 < rows["nn_without_replacement"].n1 == rows["nn_without_replacement"].n0 <= rows["nn_with_replacement"].n1


def test_fitted_scores_and_their_pairs(spark, small):
    """The fitted score has the treated share as its mean; sizes and imbalance against all pairs."""
    units = fitted_units(line_units(spark, small), "t_rare").select("uid", "t_rare", "ps", "total").collect()
    t, c = ([r for r in units if r.t_rare == a] for a in (1, 0))
    assert abs(sum(r.ps for r in units) / len(units) / 1e6 - len(t) / len(units)) < 1e-4
    pairs = [(a, min((abs(a.ps - b.ps), b.uid, b.total) for b in c)) for a in t]
    pairs = [(a, b) for a, b in pairs if b[0] < 1000]
    row = next(r for r in workloads.QUERIES["method_comparison_fitted"](spark, small).collect() if r.method == "nn_with_replacement")
    assert (row.n1, row.n0) == (len(pairs), len({b[1] for _, b in pairs}))
    assert abs(row.awmd_total - abs(sum(a.total - b[2] for a, b in pairs) / len(pairs) / 100)) < 1e-3
