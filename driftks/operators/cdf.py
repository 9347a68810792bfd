"""Approximate distribution functions: construction from quantiles, evaluation and comparison."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from driftks.functions.scalars import cdf_at
from driftks.operators.quantiles import quantile_knots
from driftks.operators.samples import Sample
from driftks.plans.params import CdfPlan
from driftks.plans.shipping import held, share

INTERPOLANTS = ("linear", "step_low", "step_high", "mid")


@dataclass(frozen=True)
class ApproxCdf:
    """Sorted knots ``x`` with the probabilities to the left (``p_lo``) and at (``p_hi``) each.

    With ``ties="jump"`` equal quantiles are one knot at which the function jumps, and the bound of the error holds
    for samples with repeated values too. With ``"interp"`` all quantiles are kept and the line runs
    through them; the bound then holds for samples without ties only.
    """

    x: np.ndarray
    p_lo: np.ndarray
    p_hi: np.ndarray
    plan: CdfPlan
    ties: str = "jump"
    tail: str = "clamp"
    interp: str = "linear"
    raw: tuple[np.ndarray, np.ndarray] = field(default=(np.zeros(0), np.zeros(0)), repr=False)

    @property
    def size(self) -> int:
        """Stored points."""
        return len(self.x)

    @property
    def bound(self) -> float:
        return self.plan.bound

    def eval_py(self, points, left: bool = False) -> np.ndarray:
        """Values at ``points``, or the limits from the left there."""
        v = np.asarray(points, float)
        if not len(self.x):
            return np.full(len(v), np.nan)
        low = self.p_lo[0] if self.tail == "clamp" else 0.0
        if self.ties == "interp":
            out = np.interp(v, *self.raw)
            return np.where(v < self.x[0], low, out)
        i = np.searchsorted(self.x, v, side="left" if left else "right") - 1
        at = np.clip(i, 0, None)
        nxt = np.clip(i + 1, None, len(self.x) - 1)
        a, b = self.p_hi[at], np.where(i + 1 < len(self.x), self.p_lo[nxt], self.p_hi[at])
        width = self.x[nxt] - self.x[at]
        with np.errstate(invalid="ignore", divide="ignore"):
            part = np.where(width > 0, np.clip((v - self.x[at]) / width, 0, 1), 0.0)
        part = np.nan_to_num(part, nan=0.0)
        exact = (i >= 0) & (self.x[at] == v)
        part = {"linear": part, "step_low": np.zeros_like(part), "step_high": np.where(exact, 0.0, 1.0), "mid": np.where(exact, 0.0, 0.5)}[self.interp]
        out = a + part * (b - a)
        return np.where(i < 0, low, out)

    def band_py(self, points) -> tuple[np.ndarray, np.ndarray]:
        """Least and greatest value that the true function can have at ``points``."""
        v = np.asarray(points, float)
        i = np.searchsorted(self.x, v, side="right") - 1
        e = self.plan.eps + (1.0 / self.plan.n if self.plan.n else 0.0)
        step = 1.0 / max(1, self.plan.a - 1)
        low = np.where(i < 0, 0.0, self.p_hi[np.clip(i, 0, None)] - e)
        nxt = np.clip(i + 1, None, len(self.x) - 1)
        high = np.where(i + 1 < len(self.x), np.maximum(self.p_lo[nxt], self.p_hi[np.clip(i, 0, None)] + step), 1.0) + e
        return np.clip(low, 0, 1), np.clip(high, 0, 1)

    def to_df(self, spark: SparkSession) -> DataFrame:
        """Knots as rows: ``knot_id``, ``x``, ``p_lo``, ``p_hi``."""
        frame = pd.DataFrame({"knot_id": np.arange(self.size, dtype=np.int32), "x": self.x, "p_lo": self.p_lo, "p_hi": self.p_hi})
        return spark.createDataFrame(frame, "knot_id int, x double, p_lo double, p_hi double")


def from_knots(grid, quantiles, plan: CdfPlan, ties: str = "jump", tail: str = "clamp", interp: str = "linear") -> ApproxCdf:
    """The function through quantiles at ``grid``."""
    q, p = np.asarray(quantiles, float), np.asarray(grid, float)
    if interp not in INTERPOLANTS:
        raise ValueError(f"unknown interpolant {interp!r}")
    if len(q) and not np.isfinite(q).all():
        raise ValueError("infinite values have no slope to interpolate: use the exact test")
    q = np.maximum.accumulate(q) if len(q) else q
    x, first = np.unique(q, return_index=True)
    last = np.append(first[1:], len(q)) - 1 if len(q) else first
    return ApproxCdf(x, p[first], p[last], plan, ties, tail, interp, (q, p))


def build_cdf(sample: Sample, plan: CdfPlan, ties: str = "jump", tail: str = "clamp", interp: str = "linear", engine: str = "aggregate") -> ApproxCdf:
    """One scan of the sample; only its knots reach the driver."""
    grid, q = quantile_knots(sample, plan, engine)
    return from_knots(grid, q, plan, ties, tail, interp)


def distance_py(a: ApproxCdf, b: ApproxCdf) -> tuple[float, float]:
    """Largest gap between two functions, and where it is.

    The difference is linear between the knots of both, so its largest size is at a knot or just left of one.
    """
    if not a.size or not b.size:
        return float("nan"), float("nan")
    if a.ties == b.ties == "interp":  # each function has its requested probabilities at its own knots
        (xa, pa), (xb, pb) = a.raw, b.raw
        gaps = np.append(np.abs(pa - b.eval_py(xa)), np.abs(pb - a.eval_py(xb)))
        k = int(gaps.argmax())
        return float(gaps[k]), float(np.append(xa, xb)[k])
    points = np.union1d(a.x, b.x)
    gap = np.abs(a.eval_py(points) - b.eval_py(points))
    if a.ties == "jump" or b.ties == "jump":
        gap = np.maximum(gap, np.abs(a.eval_py(points, True) - b.eval_py(points, True)))
    k = int(gap.argmax())
    return float(gap[k]), float(points[k])


def approx_distance(a: ApproxCdf, b: ApproxCdf, spark: SparkSession) -> DataFrame:
    """``distance_py`` as a plan: the union of knots, two as-of evaluations, one maximum. Returns ``d`` and ``at``."""
    points = a.to_df(spark).select("x").unionByName(b.to_df(spark).select("x")).distinct()
    both = eval_cdf(eval_cdf(points, "x", a, "fa"), "x", b, "fb")
    gap = F.greatest(F.abs(F.col("fa") - F.col("fb")), F.abs(F.col("fa_left") - F.col("fb_left")))
    return both.select("x", gap.alias("gap")).agg(F.max("gap").alias("d"), F.min_by("x", F.struct(-F.col("gap"), "x")).alias("at"))


def eval_cdf(points: DataFrame, column: str, cdf: ApproxCdf, name: str = "f", method: str = "asof") -> DataFrame:
    """``points`` with the function's values ``name`` and left limits ``name_left`` at ``column``.

    ``asof``: knots and points in sorted streams, each point takes the last knot before and the next one; ``broadcast``: binary search in every task, no
    shuffle of the points; ``range_join``: equality join on a bucket of the value plus the segment's condition;
    ``nested``: nested loop over the segments, for small grids; ``array``: the knots as one literal.
    """
    spark = points.sparkSession
    if method == "broadcast":
        shared = share(spark, cdf)

        @F.pandas_udf("struct<f: double, g: double>")
        def both(v: pd.Series) -> pd.DataFrame:
            return pd.DataFrame({"f": held(shared).eval_py(v), "g": held(shared).eval_py(v, True)})

        return points.withColumn("__v", both(F.col(column).cast("double"))).withColumn(name, F.col("__v.f")).withColumn(f"{name}_left", F.col("__v.g")).drop("__v")
    if method == "array":
        knots = F.array(*(F.struct(F.lit(float(x)).alias("x"), F.lit(float(a)).alias("p_lo"), F.lit(float(b)).alias("p_hi")) for x, a, b in zip(cdf.x, cdf.p_lo, cdf.p_hi, strict=True)))
        return points.withColumn(name, cdf_at(knots, F.col(column))).withColumn(f"{name}_left", cdf_at(knots, F.col(column), left=True))
    if method == "asof":
        return _asof(points, column, cdf, name)
    knots = cdf.to_df(spark).select(F.col("x").alias("__x"), F.col("p_lo").alias("__lo"), F.col("p_hi").alias("__hi"))
    w = Window.orderBy("__x")
    segments = knots.withColumn("__nx", F.lead("__x").over(w)).withColumn("__nlo", F.lead("__lo").over(w)).withColumn("__px", F.lag("__x").over(w))
    first, last = float(cdf.x[0]), float(cdf.x[-1])
    before = spark.createDataFrame([(None, float(cdf.p_lo[0]), float(cdf.p_lo[0]), first, float(cdf.p_lo[0]), None)], "__x double, __lo double, __hi double, __nx double, __nlo double, __px double")
    segments = segments.drop("__px").unionByName(before.drop("__px"))
    v = F.col(column)
    inside = (F.col("__x").isNull() | (v >= F.col("__x"))) & (F.col("__nx").isNull() | (v < F.col("__nx")))
    if method == "nested":
        joined = points.join(F.broadcast(segments), inside, "left")
    elif method == "range_join":
        width = max((last - first) / max(1, cdf.size), 1e-300)
        # values outside the knots share the first and the last bucket
        bucket = lambda c: F.when(c.isNotNull(), F.greatest(F.lit(-1), F.least(F.lit(cdf.size + 1), F.floor((c - first) / width))))
        edges = F.sequence(F.coalesce(bucket(F.col("__x")), F.lit(-1)), F.coalesce(bucket(F.col("__nx")), F.lit(cdf.size + 1)))
        spread = segments.withColumn("__b", F.explode(edges))
        joined = points.withColumn("__b", bucket(v)).join(spread, "__b", "left").where(inside | F.col("__lo").isNull()).drop("__b")
    else:
        raise ValueError(f"unknown method {method!r}")
    return _valued(joined, v, name).drop("__x", "__lo", "__hi", "__nx", "__nlo")


def _valued(df: DataFrame, v: Column, name: str) -> DataFrame:
    x, lo, hi, nx, nlo = (F.col(c) for c in ("__x", "__lo", "__hi", "__nx", "__nlo"))
    value = F.when(x.isNull(), nlo).when(nx.isNull() | (v == x), hi).otherwise(hi + (v - x) / (nx - x) * (nlo - hi))
    return df.withColumn(name, value).withColumn(f"{name}_left", F.when(v == x, lo).otherwise(value))


def _asof(points: DataFrame, column: str, cdf: ApproxCdf, name: str) -> DataFrame:
    """The as-of join: in a sorted stream, every point sees the last knot at or before it, which brings the next one along.

    Points are dealt evenly whatever their values, and every share gets all knots (as many as the function stores), so neither a
    frequent value nor a long table fills a task, and a point costs one step of a running last.
    """
    spark = points.sparkSession
    shares = int(spark.conf.get("spark.sql.shuffle.partitions"))
    frame = pd.DataFrame({"__v": cdf.x, "__x": cdf.x, "__lo": cdf.p_lo, "__hi": cdf.p_hi, "__nx": np.append(cdf.x[1:], np.nan), "__nlo": np.append(cdf.p_lo[1:], np.nan)})
    fields = ("__x", "__lo", "__hi", "__nx", "__nlo")
    knots = spark.createDataFrame(frame, ", ".join(f"{c} double" for c in frame.columns))
    knots = knots.select("__v", F.struct("__x", "__lo", "__hi", F.nanvl("__nx", F.lit(None).cast("double")).alias("__nx"), F.nanvl("__nlo", F.lit(None).cast("double")).alias("__nlo")).alias("__knot"))
    rest = [F.lit(None).cast(t).alias(c) for c, t in points.dtypes]
    stream = points.select("*", F.col(column).cast("double").alias("__v"), F.lit(1).alias("__point"), F.pmod(F.monotonically_increasing_id(), F.lit(shares)).alias("__share"), F.lit(None).cast(knots.schema["__knot"].dataType).alias("__knot"))
    every = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(shares - 1).cast("long")))
    stream = stream.unionAll(knots.select(*rest, "__v", F.lit(0).alias("__point"), every.alias("__share"), "__knot"))
    past = Window.partitionBy("__share").orderBy("__v", "__point").rowsBetween(Window.unboundedPreceding, 0)
    found = stream.withColumn("__a", F.last("__knot", ignorenulls=True).over(past)).where("__point = 1")
    for c in fields:
        found = found.withColumn(c, F.col(f"__a.{c}"))
    first = float(cdf.p_lo[0]) if cdf.tail == "clamp" else 0.0
    found = found.withColumn("__nlo", F.when(F.col("__x").isNull(), F.lit(first)).otherwise(F.col("__nlo")))
    return _valued(found, F.col("__v"), name).select(*points.columns, name, f"{name}_left")


def cdf_band(points: DataFrame, column: str, cdf: ApproxCdf) -> DataFrame:
    """``points`` with the least and the greatest possible value of the true function."""
    shared = share(points.sparkSession, cdf)

    @F.pandas_udf("struct<low: double, high: double>")
    def band(v: pd.Series) -> pd.DataFrame:
        low, high = held(shared).band_py(v)
        return pd.DataFrame({"low": low, "high": high})

    return points.withColumn("__v", band(F.col(column).cast("double"))).select("*", F.col("__v.low").alias("low"), F.col("__v.high").alias("high")).drop("__v")
