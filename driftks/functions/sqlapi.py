"""The SQL surface: functions registered with a session, table functions and a fluent facade."""

from __future__ import annotations

import json

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import udtf

from driftks.operators import drift, kstest
from driftks.operators.samples import Sample
from driftks.plans.config import ALPHA, SERIES_TERMS, TAIL_IS_ONE
from driftks.plans.params import probability_grid

FUNCTIONS = {
    "ks_tail(lam DOUBLE) RETURNS DOUBLE": f"CASE WHEN lam IS NULL THEN NULL WHEN lam < {TAIL_IS_ONE} THEN 1.0D ELSE greatest(0.0D, least(1.0D, 2.0D * aggregate(sequence(1, {SERIES_TERMS}), 0.0D, (s, k) -> s + (CASE WHEN k % 2 = 1 THEN 1.0D ELSE -1.0D END) * exp(-2.0D * k * k * lam * lam)))) END",
    "ks_p_value(d DOUBLE, n DOUBLE, m DOUBLE) RETURNS DOUBLE": "ks_tail(sqrt(n * m / (n + m)) * d)",
    "unit_slope_eps(delta DOUBLE, n DOUBLE) RETURNS DOUBLE": "greatest(0.0D, delta - sqrt(delta / n))",
    "points_for(delta DOUBLE, eps DOUBLE) RETURNS BIGINT": "ceil(1.0D / (delta - eps) + 1.0D - 1e-9D)",
    "cdf_at(knots ARRAY<STRUCT<x: DOUBLE, p_lo: DOUBLE, p_hi: DOUBLE>>, v DOUBLE) RETURNS DOUBLE": (
        "CASE WHEN size(knots) = 0 THEN NULL WHEN v < knots[0].x THEN knots[0].p_lo"
        " WHEN v >= element_at(knots, -1).x THEN element_at(knots, -1).p_hi"
        " ELSE aggregate(sequence(0, size(knots) - 2), CAST(NULL AS DOUBLE), (s, i) -> CASE WHEN knots[i].x <= v AND v < knots[i + 1].x THEN knots[i].p_hi + (v - knots[i].x) / (knots[i + 1].x - knots[i].x) * (knots[i + 1].p_lo - knots[i].p_hi) ELSE s END) END"
    ),
}


def register(spark: SparkSession) -> None:
    """Create the SQL functions as temporary ones; their bodies are inlined into plans."""
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("ks_grid", ks_grid)
    spark.udtf.register("cdf_knots", cdf_knots)


@udtf(returnType=T.StructType().add("knot_id", T.IntegerType()).add("p", T.DoubleType()))
class ks_grid:  # noqa: N801
    """``ks_grid(n, a)``: the probability grid as rows."""

    def eval(self, n: int, a: int):
        yield from enumerate(probability_grid(n, a))


@udtf(returnType=T.StructType().add("x", T.DoubleType()).add("p_lo", T.DoubleType()).add("p_hi", T.DoubleType()))
class cdf_knots:  # noqa: N801
    """``cdf_knots(json)``: knots from a JSON array of [x, p_lo, p_hi]."""

    def eval(self, text: str):
        for x, lo, hi in json.loads(text or "[]"):
            yield float(x), float(lo), float(hi)


@F.pandas_udf(T.DoubleType())
def cdf_at_arrow(knots: pd.Series, v: pd.Series) -> pd.Series:
    """``cdf_at`` for long knot arrays: binary search in Arrow batches."""
    out = []
    for ks, x in zip(knots, v, strict=True):
        if ks is None or not len(ks) or x is None or np.isnan(x):
            out.append(None)
            continue
        xs = [k["x"] for k in ks]
        i = int(np.searchsorted(xs, x, side="right")) - 1
        if i < 0:
            out.append(ks[0]["p_lo"])
        elif i + 1 == len(xs):
            out.append(ks[i]["p_hi"])
        else:
            a, b = ks[i], ks[i + 1]
            out.append(a["p_hi"] + (x - a["x"]) / (b["x"] - a["x"]) * (b["p_lo"] - a["p_hi"]))
    return pd.Series(out, dtype="float64")


@F.pandas_udf(T.DoubleType())
def exact_distance_agg(value: pd.Series, is_x: pd.Series) -> float:
    """Exact distance as a grouped aggregate, for groups that fit one task."""
    fine = value.notna() & is_x.notna()
    v, side = value[fine].to_numpy(float), is_x[fine].to_numpy(bool)
    if not side.any() or side.all():
        return float("nan")
    points = np.unique(v)
    x, y = np.sort(v[side]), np.sort(v[~side])
    return float(np.abs(np.searchsorted(x, points, "right") / len(x) - np.searchsorted(y, points, "right") / len(y)).max())


def rank_sketch_agg(eps: float):
    """A grouped aggregate that gives the rank-bound summary of a group that fits one task, as v, g, delta triples in one array."""
    from driftks.sketch.rankbound import summarise

    @F.pandas_udf(T.ArrayType(T.DoubleType()))
    def sketch(value: pd.Series) -> list:
        return summarise(value.dropna().to_numpy(float), eps)[["v", "g", "delta"]].to_numpy(float).ravel().tolist()

    return sketch


def exact_by_group(df: DataFrame, keys: list[str], value: str, is_x: Column) -> DataFrame:
    """``keys`` and ``d`` for many small groups."""
    return df.groupBy(*keys).agg(exact_distance_agg(F.col(value).cast("double"), is_x).alias("d"))


def two_sample_cogroup(ref: DataFrame, test: DataFrame, keys: list[str], value: str) -> DataFrame:
    """``keys``, ``n``, ``m``, ``d`` of many small groups whose sides are in two tables."""

    def both(key, x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        a, b = (np.sort(p[value].dropna().to_numpy(float)) for p in (x, y))
        points = np.union1d(a, b)
        d = float(np.abs(np.searchsorted(a, points, "right") / len(a) - np.searchsorted(b, points, "right") / len(b)).max()) if len(a) and len(b) else None
        return pd.DataFrame([(*key, len(a), len(b), d)], columns=[*keys, "n", "m", "d"])

    kinds = ", ".join(f"`{k}` {ref.schema[k].dataType.simpleString()}" for k in keys)
    return ref.select(*keys, value).groupBy(*keys).cogroup(test.select(*keys, value).groupBy(*keys)).applyInPandas(both, f"{kinds}, n long, m long, d double")


class DriftKS:
    """Fluent use: ``DriftKS(spark).compare(ref, test, column)``."""

    def __init__(self, spark: SparkSession, alpha: float = ALPHA):
        self.spark, self.alpha = spark, alpha

    def compare(self, ref: DataFrame, test: DataFrame, column: str, method: str = "approximate", **options) -> DataFrame:
        x, y = Sample(ref, column), Sample(test, column)
        if method == "approximate":
            return kstest.two_sample_test(x, y, self.alpha, **options)
        if method == "adaptive":
            return kstest.adaptive_test(x, y, self.alpha, **options)
        if method == "exact":
            return kstest.exact_test(x, y, self.alpha, **options)
        raise ValueError(f"unknown method {method!r}")

    def features(self, df: DataFrame, features: list[str], is_x: Column, correction: str = "holm") -> DataFrame:
        return drift.multi_feature_test(df, features, is_x, correction).withColumn("reject", F.col("p_adjusted") <= self.alpha)
