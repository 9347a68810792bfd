import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from driftks.functions.scalars import normal_cdf
from driftks.functions.sqlapi import DriftKS, cdf_at_arrow, register
from driftks.operators import cdf, drift, exact, kstest
from driftks.operators.quantiles import grouped_knots
from driftks.operators.samples import Sample, clean, is_supported
from driftks.plans import params
from driftks.sketch import direct, rankbound
from driftks.sources import generate, load, read_samples, sample_from_rows

from .conftest import SF


def brute(x, y):
    points = np.union1d(x, y)
    return np.abs(np.searchsorted(np.sort(x), points, "right") / len(x) - np.searchsorted(np.sort(y), points, "right") / len(y)).max()


def pair(spark, x, y):
    return sample_from_rows(spark, x), sample_from_rows(spark, y)


CASES = {
    "normal": lambda r: (r.normal(size=400), r.normal(0.3, 1, 350)),
    "ties": lambda r: (r.integers(0, 6, 500).astype(float), r.integers(0, 7, 90).astype(float)),
    "constant": lambda r: (np.ones(50), np.ones(40)),
    "apart": lambda r: (np.arange(30.0), np.arange(100.0, 120)),
    "single": lambda r: (np.array([2.0]), np.array([1.0, 2.0, 3.0])),
    "two values": lambda r: (np.repeat([0.0, 1.0], [10, 90]), np.repeat([0.0, 1.0], [60, 40])),
}


@pytest.mark.parametrize("case", CASES)
def test_exact_methods_agree_with_brute_force(spark, case):
    x, y = CASES[case](np.random.default_rng(5))
    a, b = pair(spark, x, y)
    for method in exact.METHODS:
        assert exact.exact_distance(a, b, method).first()["d"] == pytest.approx(brute(x, y), abs=1e-12), method


@pytest.mark.parametrize("case", CASES)
def test_approximation_stays_inside_its_bound(spark, case):
    x, y = CASES[case](np.random.default_rng(6))
    r = kstest.two_sample_test(*pair(spark, x, y), phi=0.1).first()
    assert abs(r["d_hat"] - brute(x, y)) <= r["d_bound"] + 1e-12
    assert r["p_lo"] <= r["p_value"] <= r["p_hi"]


def test_distance_is_a_distance(spark):
    r = np.random.default_rng(7)
    x, y = pair(spark, r.normal(size=200), r.normal(size=220))
    d = exact.exact_distance(x, y).first()["d"]
    assert d == exact.exact_distance(y, x).first()["d"] and 0 <= d <= 1
    assert exact.exact_distance(x, x).first()["d"] == 0
    up = [Sample(s.df, F.exp(s.column) * 3) for s in (x, y)]
    assert exact.exact_distance(*up).first()["d"] == pytest.approx(d)


def test_empty_and_missing(spark):
    full, none = sample_from_rows(spark, [1.0, None, float("nan"), 2.0]), sample_from_rows(spark, [])
    r = kstest.two_sample_test(full, none).first()
    assert (r["n"], r["m"], r["dropped_x"], r["d_hat"], r["decision"]) == (2, 0, 2, None, "no data")
    assert exact.exact_distance(none, none).first()["d"] is None
    kept, counts = clean(full.df, "value")
    assert kept.count() == 2 and tuple(counts.first()) == (2, 2)


def test_infinite_values(spark):
    x, y = pair(spark, [1.0, float("inf")], [float("-inf"), 0.0])
    assert exact.exact_distance(x, y).first()["d"] == 1.0
    with pytest.raises(ValueError):
        kstest.two_sample_test(x, y)


def test_strings_are_refused(spark):
    df = spark.createDataFrame([("a",)], "s string")
    with pytest.raises(TypeError):
        Sample(df, "s").values()
    assert not is_supported(df.schema["s"].dataType)
    times = spark.sql("select timestamp'2024-01-01 00:00:01' as t, date'1970-01-02' as d, cast(1.5 as decimal(5,2)) as c")
    assert [Sample(times, c).values().first()[0] for c in "tdc"] == [1704067201e6, 86400e6, 1.5]


def test_plain_interpolation_breaks_on_ties(spark):
    t = load(spark, SF, "lineitem")
    x, y = Sample(t, "l_discount"), Sample(t, "l_tax")
    d = exact.exact_distance(x, y, "window").first()["d"]
    plain, jump = (kstest.two_sample_test(x, y, phi=0.01, ties=k).first()["d_hat"] for k in ("interp", "jump"))
    assert d == pytest.approx(0.18665, abs=1e-5) and plain == pytest.approx(0.28773, abs=1e-4) and abs(jump - d) <= 0.0101


@pytest.mark.parametrize("interp", cdf.INTERPOLANTS)
def test_function_is_monotone(spark, interp):
    s = sample_from_rows(spark, np.random.default_rng(1).normal(size=300))
    f = cdf.build_cdf(s, params.plan_cdf(300, 0.05), interp=interp)
    v = f.eval_py(np.linspace(-5, 5, 500))
    assert (np.diff(v) >= -1e-12).all() and v.min() >= 0 and v.max() <= 1
    low, high = f.band_py(np.linspace(-5, 5, 500))
    assert (low <= v + 1e-9).all() and (v <= high + 1e-9).all()


def test_evaluations_agree(spark):
    r = np.random.default_rng(2)
    s = sample_from_rows(spark, r.integers(0, 20, 200))
    f = cdf.build_cdf(s, params.plan_cdf(200, 0.1))
    points = spark.createDataFrame([(float(v),) for v in [-3, 0, 0.5, 7, 7.25, 19, 25]], "v double")
    found = {m: [tuple(round(x, 9) for x in row) for row in cdf.eval_cdf(points, "v", f, "f", m).orderBy("v").collect()] for m in ("asof", "broadcast", "range_join", "nested", "array")}
    assert len({str(x) for x in found.values()}) == 1


def test_distributed_distance_equals_the_kernel(spark):
    r = np.random.default_rng(3)
    a, b = (cdf.build_cdf(sample_from_rows(spark, r.integers(0, k, 300)), params.plan_cdf(300, 0.05)) for k in (20, 25))
    assert cdf.approx_distance(a, b, spark).first()["d"] == pytest.approx(cdf.distance_py(a, b)[0])


@pytest.mark.parametrize("eps", [0.02, 0.005])
def test_rank_bounds_hold(spark, eps):
    values = np.random.default_rng(4).integers(0, 5000, 20_000).astype(float)
    s = Sample(spark.createDataFrame([(float(v),) for v in values], "value double").repartition(7), "value")
    sketch = rankbound.rank_sketch(s, eps, fanout=3, chunk=900).persist()
    ordered = np.sort(values)
    for r in rankbound.bounds(sketch).collect():
        least, most = np.searchsorted(ordered, r.v, "left") + 1, np.searchsorted(ordered, r.v, "right")
        assert r.low <= most and r.high >= least and r.high - r.low <= 2 * eps * len(values) + 2
    assert sketch.count() <= 4 / eps
    q = rankbound.sketch_quantile(sketch, 0.3).first()[0]
    assert abs(np.searchsorted(ordered, q, "right") / len(values) - 0.3) <= 2 * eps
    low, high = rankbound.sketch_rank_bounds(sketch, 1234.5).first()
    assert low <= np.searchsorted(ordered, 1234.5, "right") <= high


def test_direct_test_is_precise(spark):
    r = np.random.default_rng(8)
    x, y = r.normal(size=3000), r.normal(0.2, 1, 2500)
    found = direct.direct_sketch_test(*pair(spark, x, y), 0.05).first()
    assert abs(found["d_sketch"] - brute(x, y)) <= 0.05


def test_adaptive_gives_the_exact_decision(spark):
    r = np.random.default_rng(9)
    for shift in (0.0, 1.0):
        x, y = pair(spark, r.normal(size=500), r.normal(shift, 1, 500))
        assert (kstest.adaptive_test(x, y).first()["decision"] == "reject") == kstest.exact_test(x, y).first()["reject"]


def test_grouped_distances_at_any_number_of_ranges(spark):
    r = np.random.default_rng(10)
    rows = [(g, float(v), bool(s)) for g in "ab" for v, s in zip(r.integers(0, 40, 300), r.integers(0, 2, 300), strict=True)] + [("c", 1.0, True)]
    df = spark.createDataFrame(rows, "g string, v double, s boolean")
    for parts in (1, 5, 40):
        out = {x["g"]: x["d"] for x in drift.grouped_distance(drift.side_counts(df, ["g"], F.col("v"), F.col("s")), ["g"], parts).collect()}
        for g in "ab":
            x, y = (np.array([v for k, v, s in rows if k == g and s is side]) for side in (True, False))
            assert out[g] == pytest.approx(brute(x, y))
        assert out["c"] is None


def test_corrections(spark):
    p = [0.01, 0.04, 0.03, 0.005]
    t = spark.createDataFrame([(x,) for x in p], "p_value double")
    got = {m: [round(r["p_adjusted"], 6) for r in drift.adjusted(t, m).orderBy("p_value").collect()] for m in ("bonferroni", "holm", "bh")}
    assert got == {"bonferroni": [0.02, 0.04, 0.12, 0.16], "holm": [0.02, 0.03, 0.06, 0.06], "bh": [0.02, 0.02, 0.04, 0.04]}


def test_normal_model(spark):
    v = spark.createDataFrame([(x / 10,) for x in range(-50, 51)], "x double").select("x", normal_cdf(F.col("x")).alias("p"))
    assert max(abs(r.p - 0.5 * (1 + math.erf(r.x / math.sqrt(2)))) for r in v.collect()) < 2e-7


def test_generators(spark):
    for dist, mean in (("normal", 0.0), ("uniform", 0.5), ("exponential", 1.0), ("gamma_half", 0.5)):
        s = generate(spark, dist, 20_000, 3)
        assert s.values().agg(F.avg("value")).first()[0] == pytest.approx(mean, abs=0.05)
        assert s.values().agg(F.sum("value")).first()[0] == s.values().agg(F.sum("value")).first()[0]


def test_sql_surface(spark):
    register(spark)
    k = grouped_knots(load(spark, SF, "events"), ["event_type"], "value", 0.05)
    k.createOrReplaceTempView("knots_t")
    row = spark.sql("select max(abs(cdf_at(knots, 30D) - 0.45)) as off from knots_t").first()
    assert row["off"] < 0.1
    both = k.select(cdf_at_arrow("knots", F.lit(30.0)).alias("a"), F.expr("cdf_at(knots, 30D)").alias("b")).collect()
    assert all(abs(r.a - r.b) < 1e-12 for r in both)
    assert spark.sql("select count(*), max(p) from ks_grid(1000, 11)").first() == (11, 1.0)
    assert spark.sql("select sum(x) from cdf_knots('[[1, 0, 0.5], [2, 1, 1]]')").first()[0] == 3.0
    t = load(spark, SF, "lineitem")
    f = DriftKS(spark).features(t.where("l_returnflag <> 'A'"), ["l_tax", "l_quantity"], F.col("l_returnflag") == "R")
    assert not any(r["reject"] for r in f.collect())


def test_formats(spark, tmp_path):
    df = load(spark, SF, "supplier").select("s_suppkey", "s_acctbal")
    for fmt in ("csv", "json", "orc", "parquet"):
        path = str(tmp_path / fmt)
        df.write.format(fmt).option("header", True).save(path)
        back = read_samples(spark, path, fmt, df.schema, **({"header": True} if fmt == "csv" else {}))
        assert back.agg(F.sum("s_acctbal")).first() == df.agg(F.sum("s_acctbal")).first()


def test_no_window_sees_all_rows(spark):
    """Cumulative counts, distribution functions and as-of evaluation: no sorted single partition over rows."""
    t = load(spark, SF, "events")
    s = Sample(t, "value")
    f = cdf.build_cdf(s, params.plan_cdf(10_000, 0.02))
    made = [exact.exact_cdf(s), exact.gap_table(s, s), cdf.eval_cdf(s.values(), "value", f), exact.one_sample_distance(s, "expon", mean=50.0)]
    for df in made:
        plan = df._jdf.queryExecution().executedPlan().toString()
        windows = [i for i, line in enumerate(plan.split("\n")) if " Window [" in line]
        assert windows
        for i in windows:
            below = " ".join(plan.split("\n")[i : i + 4])
            # the one that may is over one row a range
            assert "SinglePartition" not in below or "__pid" in below and "__t_c" in below


def test_asof_evaluation_is_linear(spark):
    import time

    f = cdf.from_knots(params.probability_grid(0, 101), np.linspace(0, 1, 101), params.plan_cdf(10**6, 0.0, "fixed", 0.01, 101))
    points = spark.range(2_000_000).select(F.when(F.col("id") % 3 == 0, 0.5).otherwise(F.rand(1)).alias("v"))
    began = time.perf_counter()
    worst = cdf.eval_cdf(points, "v", f).agg(F.max(F.abs(F.col("f") - F.col("v")))).first()[0]
    assert worst < 1e-9 and time.perf_counter() - began < 60


def test_taking_segments_out_equals_brute_force(spark):
    r = np.random.default_rng(12)
    rows = [(None if k == 0 else f"s{k}", float(v), bool(x)) for k, v, x in zip(r.integers(0, 4, 400), r.integers(0, 30, 400), r.integers(0, 2, 400), strict=True)]
    df = spark.createDataFrame(rows, "k string, v double, x boolean")
    for out in drift.without_each(df, "k", F.col("v"), F.col("x")).collect():
        x, y = (np.array([v for k, v, s in rows if k != out["left_out"] and s is side]) for side in (True, False))
        assert out["d"] == pytest.approx(brute(x, y)) and (out["n"], out["m"]) == (len(x), len(y))
    with pytest.raises(ValueError):
        drift.without_each(df, "v", F.col("v"), F.col("x"), segments=3)


def test_p_value_interval_and_small_samples(spark):
    from driftks.functions import significance as sig

    row = spark.createDataFrame([(0.05, 0.01, 500, 400)], "d double, b double, n long, m long")
    lo, hi = sig.p_value_interval("d", "b", "n", "m")
    got = row.select(lo.alias("lo"), hi.alias("hi")).first()
    assert got["lo"] == pytest.approx(sig.p_value_py(0.06, 500, 400)) and got["hi"] == pytest.approx(sig.p_value_py(0.04, 500, 400))


def test_stratified_sample(spark):
    from driftks.operators.samples import stratified

    t = load(spark, SF, "orders")
    got = dict(stratified(t, "o_orderstatus", {"F": 1.0, "O": 0.1}).groupBy("o_orderstatus").count().collect())
    every = dict(t.groupBy("o_orderstatus").count().collect())
    assert set(got) == {"F", "O"} and got["F"] == every["F"] and abs(got["O"] / every["O"] - 0.1) < 0.03


def test_rows_are_not_sorted_or_gathered(spark):
    """The approximate test shuffles sketches only; the exact one at scale has no single partition below its totals."""
    t = load(spark, SF, "lineitem")
    s = Sample(t, "l_extendedprice", "l_returnflag = 'R'")
    plan = s.values().agg(F.percentile_approx("value", [0.1, 0.9], 100))._jdf.queryExecution().executedPlan().toString()
    assert "Sort" not in plan and "partial_percentile_approx" in plan and "l_extendedprice" in plan and "PushedFilters: [IsNotNull(l_returnflag), EqualTo(l_returnflag,R)" in plan
    hist = exact.histogram(s, Sample(t, "l_extendedprice", "l_returnflag = 'N'"))
    ranged = hist.repartitionByRange(8, "value")._jdf.queryExecution().executedPlan().toString()
    assert "SinglePartition" not in ranged and "partial_count" in ranged
