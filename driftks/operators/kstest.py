"""Two-sample tests end to end: approximate, certified, adaptive, and their simpler rivals."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.functions import significance as sig
from driftks.operators.cdf import ApproxCdf, build_cdf, distance_py, from_knots
from driftks.operators.exact import exact_distance, model_cdf
from driftks.operators.quantiles import both_knots, pair_knots
from driftks.operators.samples import Sample, profile_pair, subsample
from driftks.plans import config
from driftks.plans.params import CdfPlan, TestPlan, plan_cdf, plan_test, probability_grid

RESULT = (
    "n long, m long, dropped_x long, dropped_y long, eps_x double, eps_y double, a_x int, a_y int, delta_x double, delta_y double, "
    "d_hat double, at double, d_bound double, lambda double, p_value double, p_lo double, p_hi double, alpha double, reject boolean, decision string, engine string, split string, ties string"
)


def result_row(spark: SparkSession, d: float, at: float, n: int, m: int, plans: tuple[CdfPlan, CdfPlan], bound: float, alpha: float, engine: str, ties: str, dropped=(0, 0)) -> DataFrame:
    """The result of a test as one row; probabilities are columns of the plan."""
    x, y = plans
    if not n or not m:
        d = at = None
    crit = sig.critical_distance(alpha, n, m) if n and m else None
    base = spark.createDataFrame([(n, m, *dropped, x.eps, y.eps, x.a, y.a, x.delta, y.delta, d, at, bound, alpha, engine, x.split, ties)], "n long, m long, dropped_x long, dropped_y long, eps_x double, eps_y double, a_x int, a_y int, delta_x double, delta_y double, d_hat double, at double, d_bound double, alpha double, engine string, split string, ties string")
    lo, hi = sig.p_value_interval("d_hat", "d_bound", "n", "m")
    out = base.withColumn("lambda", sig.effective_scale("n", "m") * F.col("d_hat")).withColumn("p_value", sig.p_value("d_hat", "n", "m")).withColumn("p_lo", lo).withColumn("p_hi", hi)
    out = out.withColumn("reject", F.col("p_value") <= F.col("alpha"))
    decision = sig.certified_decision("d_hat", "d_bound", F.lit(crit).cast("double"))
    out = out.withColumn("decision", F.when(F.col("d_hat").isNull(), "no data").otherwise(decision))
    return out.select(*(c.split()[0] for c in RESULT.split(", ")))


def build_pair(ref: Sample, test: Sample, plan: TestPlan, ties: str = "jump", engine: str = "aggregate", interp: str = "linear", tail: str = "clamp") -> tuple[ApproxCdf, ApproxCdf]:
    """Both functions; with the ``aggregate`` engine from one pass over the pair."""
    if engine == "aggregate":
        knots = both_knots(ref, test, (plan.x, plan.y))
        return tuple(from_knots(g, q, p, ties, tail, interp) for (g, q), p in zip(knots, (plan.x, plan.y), strict=True))
    return tuple(build_cdf(s, p, ties, tail, interp, engine) for s, p in ((ref, plan.x), (test, plan.y)))


def two_sample_test(ref: Sample, test: Sample, alpha: float = config.ALPHA, beta: float | None = None, phi: float | None = None, delta: float | None = None, split: str = "unit_slope", engine: str = "aggregate", ties: str = "jump", interp: str = "linear", tail: str = "clamp", plan: TestPlan | None = None) -> DataFrame:
    """The approximate test: sizes, plan, one quantile pass over both samples, largest gap of the two functions, significance.

    No row is shuffled; sketches and knots are. Returns one row of ``RESULT``.
    """
    spark = ref.df.sparkSession
    seen = profile_pair(ref, test, distinct=False)
    if plan is None:
        plan = plan_test(max(seen.n, 1), max(seen.m, 1), phi, alpha if beta is not None else None, beta, delta, split)
    a, b = build_pair(ref, test, plan, ties, engine, interp, tail)
    d, at = distance_py(a, b)
    return result_row(spark, d, at, seen.n, seen.m, (plan.x, plan.y), plan.bound, alpha, engine, ties, (seen.dropped_x, seen.dropped_y))


def one_scan_test(df: DataFrame, value: Column, is_x: Column, alpha: float = config.ALPHA, phi: float = config.PHI) -> DataFrame:
    """Both sides of one table in a single pass: the balanced split does not need the sizes, so counts come with the sketches."""
    x = plan_cdf(0, phi / 2, "balanced")
    grid = probability_grid(0, x.a)
    qx, qy, n, m = pair_knots(df, value, is_x, (grid, grid), (x.eps, x.eps))
    plans = tuple(CdfPlan(k, x.delta, x.eps, x.a, x.split) for k in (n, m))
    a, b = (from_knots(grid if q else [], q, p) for q, p in zip((qx, qy), plans, strict=True))
    d, at = distance_py(a, b)
    return result_row(df.sparkSession, d, at, n, m, plans, plans[0].bound + plans[1].bound, alpha, "aggregate", "jump")


def exact_test(ref: Sample, test: Sample, alpha: float = config.ALPHA, method: str = "range") -> DataFrame:
    """The exact test: ``d``, ``at``, ``n``, ``m``, ``p_value`` and ``reject``."""
    found = exact_distance(ref, test, method)
    return found.withColumn("p_value", sig.p_value("d", "n", "m")).withColumn("alpha", F.lit(alpha)).withColumn("reject", F.col("p_value") <= alpha)


def adaptive_test(ref: Sample, test: Sample, alpha: float = config.ALPHA, phi: float = config.PHI, split: str = "balanced") -> DataFrame:
    """Approximate first; exact only where the certified decision is open. Adds ``escalated`` and ``d_exact`` (null if not needed).

    Samples with few distinct values go to the exact test at once: their histogram is small.
    """
    seen = profile_pair(ref, test)
    if min(seen.n, seen.m) > 0 and seen.distinct > config.EXACT_DISTINCT:
        out = two_sample_test(ref, test, alpha, phi=phi, split=split)
        if out.first()["decision"] != "undecided":
            return out.withColumn("escalated", F.lit(False)).withColumn("d_exact", F.lit(None).cast("double"))
    d, at, n, m = exact_distance(ref, test, "refine" if seen.distinct > config.EXACT_DISTINCT else "range").first()
    none = CdfPlan(n or 0, 0.0, 0.0, 0, "exact")
    out = result_row(ref.df.sparkSession, d, at, n or 0, m or 0, (none, none), 0.0, alpha, "exact", "jump", (seen.dropped_x, seen.dropped_y))
    return out.withColumn("escalated", F.lit(True)).withColumn("d_exact", F.col("d_hat"))


def against_cdf(ref: ApproxCdf, test: Sample, alpha: float = config.ALPHA, engine: str = "aggregate") -> DataFrame:
    """Test a sample against a stored distribution function; the reference is not scanned."""
    m = test.values().count()
    plan = plan_cdf(max(m, 1), ref.plan.delta, "balanced")
    cdf = build_cdf(test, plan, ref.ties, ref.tail, ref.interp, engine)
    d, at = distance_py(ref, cdf)
    return result_row(test.df.sparkSession, d, at, ref.plan.n, m, (ref.plan, plan), ref.bound + plan.bound, alpha, engine, ref.ties)


def approx_one_sample_test(sample: Sample, dist, phi: float = config.PHI, alpha: float = config.ALPHA, **params) -> DataFrame:
    """A sample's approximate function against a model: ``d_hat``, ``d_low``, ``d_high`` (certified), ``n``, ``p_value``.

    Between two knots the sample's function stays in a rectangle and the model between its values at the knots,
    so the corners of the rectangles bound the true distance from above.
    """
    spark = sample.df.sparkSession
    n = sample.values().count()
    cdf = build_cdf(sample, plan_cdf(max(n, 1), phi / 2, "balanced"))
    knots = cdf.to_df(spark)
    from pyspark.sql import Window

    w = Window.orderBy("x")
    model = model_cdf(F.col("x"), dist, **params)
    e = F.lit(cdf.plan.eps + (1.0 / n if n else 0.0))
    k = knots.withColumn("model", model).withColumn("next_lo", F.coalesce(F.lead("p_lo").over(w), F.lit(1.0))).withColumn("next_model", F.coalesce(F.lead("model").over(w), F.lit(1.0))).withColumn("first", F.row_number().over(w) == 1)
    gap = F.greatest(F.abs(F.col("p_hi") - F.col("model")), F.abs(F.col("p_lo") - F.col("model")))
    high = F.greatest(F.col("next_lo") + e - F.col("model"), F.col("next_model") - F.col("p_hi") + e, F.when(F.col("first"), F.col("model")).otherwise(0.0), gap + e)
    out = k.agg(F.max(gap).alias("d_hat"), F.max(F.abs(F.col("p_hi") - F.col("model")) - e).alias("low"), F.max(high).alias("d_high"))
    scale = F.lit(float(n) ** 0.5)
    return out.select("d_hat", F.greatest(F.lit(0.0), "low").alias("d_low"), F.least(F.lit(1.0), "d_high").alias("d_high"), F.lit(n).alias("n"), sig.ks_tail(scale * F.col("d_hat")).alias("p_value"), F.lit(alpha).alias("alpha"))


def one_sample_test(sample: Sample, dist, alpha: float = config.ALPHA, **params) -> DataFrame:
    """The exact one-sample test: ``d``, ``n``, ``p_value``, ``reject``."""
    from driftks.operators.exact import one_sample_distance

    out = one_sample_distance(sample, dist, **params)
    return out.withColumn("p_value", sig.ks_tail(F.sqrt("n") * F.col("d"))).withColumn("reject", F.col("p_value") <= alpha)


def spark_one_sample_test(sample: Sample, mean: float = 0.0, sd: float = 1.0) -> DataFrame:
    """Spark's own one-sample test against a normal model: ``p_value``, ``d``."""
    from pyspark.ml.stat import KolmogorovSmirnovTest

    found = KolmogorovSmirnovTest.test(sample.values(), "value", "norm", float(mean), float(sd))
    return found.select(F.col("statistic").alias("d"), F.col("pValue").alias("p_value"))


def sampled_test(ref: Sample, test: Sample, fraction: float = 0.1, seed: int = 1, alpha: float = config.ALPHA) -> DataFrame:
    """Ablation: the exact test on a Bernoulli sample of either side."""
    x, y = (Sample(subsample(s.values(), fraction, seed=seed), "value") for s in (ref, test))
    return exact_test(x, y, alpha)


def histogram_test(ref: Sample, test: Sample, bins: int = 100, alpha: float = config.ALPHA) -> DataFrame:
    """Ablation: gaps at the edges of an equi-width histogram only; never above the exact distance."""
    from driftks.operators.exact import _by_window, tagged

    both = tagged(ref, test)
    low, high = both.agg(F.min("value"), F.max("value")).first()
    if low is None or low == high:
        return exact_test(ref, test, alpha, "window")
    bucket = F.width_bucket("value", F.lit(low), F.lit(high), F.lit(bins))
    hist = both.groupBy(bucket.cast("double").alias("value")).agg(F.count_if(F.col("side") == "x").alias("cx"), F.count_if(F.col("side") == "y").alias("cy"))
    out = _by_window(hist)
    return out.withColumn("p_value", sig.p_value("d", "n", "m")).withColumn("alpha", F.lit(alpha)).withColumn("reject", F.col("p_value") <= alpha)
