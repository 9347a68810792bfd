import math

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from driftks.functions import significance as sig
from driftks.plans import params


@pytest.mark.parametrize(("d", "p"), [(0.0220, 0.01581), (0.0072, 0.9578)])
def test_published_p_values(d, p):
    assert sig.p_value_py(d, 10_000, 10_000) == pytest.approx(p, rel=0.02)


def test_published_tiny_p_values():
    assert sig.p_value_py(0.0976, 10_000, 10_000) == pytest.approx(7.4e-42, rel=0.3)
    assert sig.p_value_py(0.0837, 10_000, 10_000) == pytest.approx(7.0e-31, rel=0.3)


def test_critical_distances():
    assert sig.critical_distance(0.05, 10_000.0, 10_000.0) == pytest.approx(0.019206, abs=1e-6)
    assert sig.critical_distance(0.20, 84_000.0, 7_000.0) == pytest.approx(0.013345, abs=1e-6)


def test_precision_follows_the_definition():
    assert sig.precision_for(0.05, 0.025, 10_000, 10_000) == pytest.approx(0.001718, abs=1e-3)
    one_sided = sig.precision_for(0.05, 0.05, 10_000, 10_000)
    assert one_sided == pytest.approx(sig.critical_distance(0.05, 1e4, 1e4) - sig.critical_distance(0.10, 1e4, 1e4))


@pytest.mark.parametrize(("a", "eps", "delta"), [(11, 0.1, 0.20), (21, 0.1, 0.15), (51, 0.1, 0.12), (11, 0.01, 0.11), (21, 0.01, 0.06), (51, 0.01, 0.03), (101, 0.001, 0.011), (201, 0.001, 0.006), (501, 0.001, 0.003)])
def test_bounds_of_the_convergence_study(a, eps, delta):
    assert params.cdf_error_bound(a, eps) == pytest.approx(delta)


@pytest.mark.parametrize(("delta", "n", "a", "off"), [(0.025, 10_000, 634, 0), (0.005, 10_000, 1416, 0), (0.0005, 100_000, 14144, 0), (0.025, 84_000, 1835, 0), (0.001, 84_000, 9167, 0), (0.001, 1_107_796, 33_285, 0), (0.001, 984_000, 31_370, 0), (0.0001995, 10_000, 7083, 3), (0.000385, 84_000, 14_770, 3), (0.000385, 7_000, 4_265, 3)])
def test_published_points(delta, n, a, off):
    assert abs(params.points_for(delta, params.unit_slope_eps(delta, n)) - a) <= off


@pytest.mark.parametrize(("delta", "n", "eps", "off"), [(0.025, 10_000, 0.02341, 2e-5), (0.005, 10_000, 0.004293, 2e-6), (0.001, 84_000, 0.000892, 2e-6), (0.001, 1_107_796, 0.000970, 1e-6)])
def test_published_rank_errors(delta, n, eps, off):
    assert params.unit_slope_eps(delta, n) == pytest.approx(eps, abs=off)


def test_sketch_error_is_a_sixth():
    assert params.direct_sketch_eps(0.05) == pytest.approx(0.00833, abs=1e-5)


def test_tiny_budgets_clamp_to_exact():
    plan = params.plan_cdf(100, 0.005)
    assert (plan.eps, plan.a) == (0.0, 100)


def test_long_grids_become_balanced():
    plan = params.plan_cdf(10**12, 0.001)
    assert (plan.split, plan.a) == ("balanced", 2001)


def test_refused_parameters():
    with pytest.raises(ValueError):
        params.points_for(0.01, 0.01)
    with pytest.raises(ValueError):
        sig.ks_tail_inverse(1.5)


@given(st.floats(0.001, 0.3), st.integers(100, 10**9))
@settings(max_examples=60, deadline=None)
def test_every_split_keeps_the_budget(delta, n):
    for split in ("unit_slope", "balanced"):
        plan = params.plan_cdf(n, delta, split)
        assert plan.eps == 0 or params.cdf_error_bound(plan.a, plan.eps) <= delta * (1 + 1e-9)


@given(st.floats(0.05, 4), st.floats(0.05, 4))
@settings(max_examples=60, deadline=None)
def test_tail_falls(a, b):
    low, high = sorted((a, b))
    assert 0 <= sig.ks_tail_py(high) <= sig.ks_tail_py(low) <= 1


def test_columns_equal_python(spark):
    from pyspark.sql import functions as F

    rows = [(0.01, 500, 700), (0.05, 1000, 10), (0.2, 90, 80)]
    df = spark.createDataFrame(rows, "d double, n long, m long").select("*", sig.p_value("d", "n", "m").alias("p"), sig.certified_decision("d", F.lit(0.02), F.lit(0.1)).alias("c"))
    for r in df.collect():
        assert r.p == pytest.approx(sig.p_value_py(r.d, r.n, r.m), rel=1e-9)
    assert [r.c for r in df.collect()] == ["accept", "accept", "reject"]
    assert math.isclose(sig.log_p_value_py(0.9, 10**6, 10**6), math.log(2) - 2 * 0.81 * 5e5, rel_tol=1e-9)
