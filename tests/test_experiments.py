"""The experiments at tiny sizes: their rows, not their seconds."""

from pathlib import Path

import pytest

from tilealg.plans import experiments as X

SF = "/root/testdata/sf0.001"


def test_sweeps_over_products(spark):
    *points, fit = X.size_sweep(spark, (32, 64), 0.125)
    assert [p["m"] for p in points] == [32, 64] and {"slope", "last_slope"} == set(fit)
    *points, fit = X.density_sweep(spark, 32, (0.05, 0.2))
    assert points[0]["nnz"] < points[1]["nnz"] and points[0]["flops"] < points[1]["flops"] and 0 <= fit["linearity"] <= 1


def test_placements_differ_in_copies_and_locality(spark):
    row, coarse, fine, tile = X.placement_sweep(spark, 48, 0.125)
    assert row["partials"] == coarse["partials"] and fine["copied"] == 2 * coarse["copied"]
    assert row["stays"] == tile["stays"] == 1.0 and coarse["stays"] < 1


def test_factor_parts(spark):
    rows = list(X.nmf_components(spark, 32, (0.125,), (2, 3)))
    assert [r["k"] for r in rows] == [2, 3] and all(r[p] >= 0 for r in rows for p in ("x", "y", "ratio"))


@pytest.mark.skipif(not Path(SF).exists(), reason="no tables here")
def test_experiments_on_tables(spark):
    (ranks,) = X.pagerank_hundred(spark, SF, 2)
    assert abs(ranks["mass"] - 1) < 1e-9 and ranks["pages"] == 200
    (grown,) = X.svm_scaling(spark, SF, (40,), iters=2)
    assert grown["n"] == 40 and grown["train"] == 32 and 0 < grown["kernel_density"] <= 1 and grown["test"] == 8
