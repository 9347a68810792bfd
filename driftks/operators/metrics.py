"""Accuracy and cost of approximate functions and tests."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.functions import significance as sig
from driftks.operators.cdf import ApproxCdf, build_cdf, distance_py, eval_cdf, from_knots
from driftks.operators.drift import grouped_distance, side_counts
from driftks.operators.exact import exact_cdf, exact_distance
from driftks.operators.kstest import build_pair
from driftks.operators.prefix import cumulative
from driftks.operators.quantiles import knots_column, quantile_knots
from driftks.operators.samples import Sample
from driftks.plans.params import CdfPlan, TestPlan, direct_sketch_eps, expected_points, expected_sketch_size, plan_cdf, plan_test, probability_grid
from driftks.plans.shipping import held, share
from driftks.sketch.rankbound import rank_sketch


def cdf_max_error(sample: Sample, cdf: ApproxCdf) -> DataFrame:
    """``max_error`` over all observations, next to the theoretical ``bound``, and whether it is ``inside``."""
    both = eval_cdf(exact_cdf(sample), "value", cdf, "f", "broadcast")
    row = both.agg(F.max(F.abs(F.col("f") - F.col("cdf"))).alias("max_error"))
    return row.withColumn("bound", F.lit(cdf.bound)).withColumn("inside", F.col("max_error") <= F.col("bound") + 1e-12)


def convergence(samples: DataFrame, settings: list[tuple[int, float]]) -> DataFrame:
    """For every (a, eps): the worst error over all samples (``sample``, ``value``) at all observations, the bound and the flag.

    One aggregate gives the knots of all samples and settings, one pass over the exact functions their errors.
    """
    spark = samples.sparkSession
    hist = samples.groupBy("sample", "value").agg(F.count("*").alias("c"))
    sizes = [r[0] for r in hist.groupBy("sample").agg(F.sum("c")).select("sum(c)").collect()]
    n = min(sizes)  # one grid for all: that of the smallest sample
    plans = [plan_cdf(n, 0.0, "fixed", eps, min(a, n)) for a, eps in settings]
    grids = [probability_grid(n, p.a) for p in plans]
    knots = samples.groupBy("sample").agg(*(knots_column(F.col("value"), g, p.eps).alias(f"q{i}") for i, (g, p) in enumerate(zip(grids, plans, strict=True))))
    cdfs = share(spark, {r["sample"]: [from_knots(g, r[f"q{i}"], p) for i, (g, p) in enumerate(zip(grids, plans, strict=True))] for r in knots.collect()})

    def errors(batches):
        for batch in batches:
            for sample, part in batch.groupby("sample"):
                yield pd.DataFrame([(sample, i, float(np.abs(f.eval_py(part["value"]) - part["cdf"]).max())) for i, f in enumerate(held(cdfs)[sample])], columns=["sample", "setting", "error"])

    exact = cumulative(hist, ["sample"], "value", ["c"]).select("sample", "value", (F.col("c_upto") / F.col("c_all")).alias("cdf"))
    worst = exact.mapInPandas(errors, "sample int, setting int, error double").groupBy("setting").agg(F.max("error").alias("max_error"), F.count_distinct("sample").alias("samples"))
    named = spark.createDataFrame([(i, a, e, p.bound) for i, ((a, e), p) in enumerate(zip(settings, plans, strict=True))], "setting int, a int, eps double, bound double")
    out = worst.join(F.broadcast(named), "setting").select("a", "eps", "samples", "max_error", "bound", (F.col("max_error") <= F.col("bound") + 1e-12).alias("inside"))
    return out.orderBy(F.desc("eps"), "a")


def cdf_compare(sample: Sample, plan: CdfPlan) -> DataFrame:
    """The exact curve and the approximate one: ``value``, ``cdf``, ``f``, and whether the value is a knot."""
    cdf = build_cdf(sample, plan)
    knots = cdf.to_df(sample.df.sparkSession).select(F.col("x").alias("value"), F.lit(True).alias("is_knot"))
    return eval_cdf(exact_cdf(sample), "value", cdf, "f", "broadcast").join(F.broadcast(knots), "value", "left").select("value", "cdf", "f", F.coalesce("is_knot", F.lit(False)).alias("is_knot"))


def quantile_rank_error(sample: Sample, plan: CdfPlan, engine: str = "summary") -> DataFrame:
    """Rank error of each returned quantile: how far the wanted probability is from the ranks its value has (ties count as a range)."""
    spark = sample.df.sparkSession
    grid, q = quantile_knots(sample, plan, engine)
    wanted = spark.createDataFrame(pd.DataFrame({"p": grid, "value": q}), "p double, value double")
    ranks = exact_cdf(sample).withColumn("low", F.col("cdf") - F.col("c") / F.col("n"))
    met = ranks.join(F.broadcast(wanted), "value")
    miss = F.greatest(F.lit(0.0), F.col("low") - F.col("p"), F.col("p") - F.col("cdf"))
    return met.select("p", "value", miss.alias("miss"))


def rank_guarantee(sample: Sample, plan: CdfPlan, engine: str = "summary") -> DataFrame:
    """One row: knots, the worst rank error and whether it is within eps and one rank."""
    n = max(1, plan.n)
    return quantile_rank_error(sample, plan, engine).agg(F.count("*").alias("knots"), F.max("miss").alias("worst"), F.bool_and(F.col("miss") <= plan.eps + 1.0 / n + 1e-12).alias("inside"))


def replicate(pairs: DataFrame, phi: float, alpha: float, split: str = "unit_slope") -> DataFrame:
    """One row a replication of ``pairs`` (``rep``, ``is_x``, ``value``): exact and approximate distance, p-values and decisions, and whether the error is inside its bound.

    All replications share two passes: one histogram for the exact distances, one grouped aggregate for the knots (on the grid
    of the smallest replication). Only knots reach the driver.
    """
    spark = pairs.sparkSession
    exact = {r["rep"]: r for r in grouped_distance(side_counts(pairs, ["rep"], F.col("value"), F.col("is_x")), ["rep"]).where("d is not null").collect()}
    kind = "replication int, n long, m long, a_x int, a_y int, d double, d_hat double, error double, bound double, p double, p_hat double, reject boolean, reject_hat boolean, inside boolean, agrees boolean"
    if not exact:
        return spark.createDataFrame([], kind)
    plan = plan_test(min(r["n"] for r in exact.values()), min(r["m"] for r in exact.values()), phi, split=split)
    grids = [probability_grid(p.n, p.a) for p in (plan.x, plan.y)]
    side = (F.when(F.col("is_x"), F.col("value")), F.when(~F.col("is_x"), F.col("value")))
    knots = pairs.groupBy("rep").agg(*(knots_column(v, g, p.eps).alias(name) for v, g, p, name in zip(side, grids, (plan.x, plan.y), "xy", strict=True)))
    rows = []
    for r in knots.collect():
        if r["rep"] not in exact:
            continue
        d, n, m = (exact[r["rep"]][c] for c in ("d", "n", "m"))
        d_hat, _ = distance_py(*(from_knots(g, r[s], p) for g, s, p in zip(grids, "xy", (plan.x, plan.y), strict=True)))
        p, p_hat = sig.p_value_py(d, n, m), sig.p_value_py(d_hat, n, m)
        open_ = abs(d - sig.critical_distance(alpha, float(n), float(m))) <= plan.bound
        rows.append((r["rep"], n, m, plan.x.a, plan.y.a, d, d_hat, abs(d_hat - d), plan.bound, p, p_hat, p <= alpha, p_hat <= alpha, abs(d_hat - d) <= plan.bound + 1e-12, open_ or (p <= alpha) == (p_hat <= alpha)))
    return spark.createDataFrame(sorted(rows), kind)


def replication_summary(rows: DataFrame) -> DataFrame:
    """Ranges of distances and p-values, worst error, rejections and disagreements over replications."""
    return rows.agg(
        F.count("*").alias("replications"), F.min("d").alias("d_min"), F.max("d").alias("d_max"), F.min("d_hat").alias("d_hat_min"), F.max("d_hat").alias("d_hat_max"), F.max("error").alias("worst_error"), F.max("bound").alias("bound"),
        F.min("p").alias("p_min"), F.max("p").alias("p_max"), F.min("p_hat").alias("p_hat_min"), F.max("p_hat").alias("p_hat_max"), F.count_if("reject").alias("rejected"), F.count_if("reject_hat").alias("rejected_hat"),
        F.count_if(F.col("reject") != F.col("reject_hat")).alias("disagreements"), F.bool_and("inside").alias("all_inside"), F.bool_and("agrees").alias("all_agree"),
    )


def compare_tests(ref: Sample, test: Sample, phi: float) -> DataFrame:
    """One row: exact distance, distance by approximate functions and by sketches, their stored points, and flags of the target precision."""
    from driftks.sketch.direct import direct_sketch_test

    d, _, n, m = exact_distance(ref, test, "range").first()
    plan = plan_test(n, m, phi)
    a, b = build_pair(ref, test, plan)
    d_hat, _ = distance_py(a, b)
    s = direct_sketch_test(ref, test, phi).first()
    row = (n, m, phi, plan.x.delta, plan.x.eps, direct_sketch_eps(phi), plan.x.a + plan.y.a, a.size + b.size, s["points_x"] + s["points_y"], d, d_hat, s["d_sketch"], abs(d_hat - d) <= phi + 1 / n + 1 / m, abs(s["d_sketch"] - d) <= phi)
    return ref.df.sparkSession.createDataFrame([row], "n long, m long, phi double, delta double, eps_cdf double, eps_sketch double, points_planned int, points_cdf int, points_sketch int, d double, d_cdf double, d_sketch double, cdf_inside boolean, sketch_inside boolean")


def storage_model(spark: SparkSession, sizes: list[int], deltas: list[float]) -> DataFrame:
    """Expected knots and sketch tuples over sample sizes and bounds; knots grow with the root of n, sketches with its logarithm."""
    rows = [(n, d, plan_cdf(n, d, max_points=None).a, expected_points(d, n), expected_sketch_size(2 * d / 6, n)) for n in sizes for d in deltas]
    return spark.createDataFrame(rows, "n long, delta double, a int, knots double, tuples double")


def storage_study(sample_of, sizes: list[int], deltas: list[float]) -> DataFrame:
    """``n``, ``delta``, ``a``, ``knots`` and ``tuples``: the quantiles that the approximate function asks for, the distinct ones
    among them, and what the direct sketch of the same precision stores, built for samples of growing size (``sample_of``: a sample of n values)."""
    rows, spark = [], None
    for n in sizes:
        s = sample_of(n)
        spark = s.df.sparkSession
        for delta in deltas:
            cdf = build_cdf(s, plan_cdf(n, delta, max_points=None))
            rows.append((n, delta, len(cdf.raw[0]), cdf.size, rank_sketch(s, direct_sketch_eps(2 * delta)).count()))
    return spark.createDataFrame(rows, "n long, delta double, a long, knots long, tuples long")


def scaling_exponent(table: DataFrame, size: str = "n", points: str = "knots", by: str = "delta") -> DataFrame:
    """Slope of log points over log n for each ``by``."""
    return table.groupBy(by).agg(F.regr_slope(F.log(points), F.log(size)).alias("exponent"))


def missing_removed(samples: dict[str, Sample]) -> DataFrame:
    """``sample``, ``kept`` and ``dropped`` rows."""
    out = None
    for label, s in samples.items():
        fine = F.col("value").isNotNull() & ~F.isnan("value")
        row = s.raw().agg(F.count_if(fine).alias("kept"), F.count_if(~F.coalesce(fine, F.lit(False))).alias("dropped")).select(F.lit(label).alias("sample"), "kept", "dropped")
        out = row if out is None else out.unionByName(row)
    return out


def true_distance_error(d: float, plan: TestPlan) -> float:
    """The certified share of the budget that an error uses."""
    return d / plan.bound if math.isfinite(plan.bound) and plan.bound else float("nan")


def normal_table(n: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).normal(size=n)
