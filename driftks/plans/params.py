"""Parameters of approximate distribution functions: error bound, trade-off and split of a budget."""

from __future__ import annotations

import math
import warnings
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.functions.significance import precision_for
from driftks.plans.config import DRIVER_KNOTS, PHI


def cdf_error_bound(a, eps):
    """Bound on the error of a piecewise linear distribution function through ``a`` quantiles of rank error ``eps``."""
    return 1.0 / (a - 1) + eps


def points_for(delta: float, eps: float) -> int:
    """The least number of equi-spaced quantiles that keeps the bound ``delta`` at rank error ``eps``."""
    if eps >= delta:
        raise ValueError("the rank error must be smaller than the bound")
    exact = 1.0 / (delta - eps) + 1.0
    near = round(exact)
    return max(3, near if abs(exact - near) < 1e-9 * near else math.ceil(exact))


def unit_slope_eps(delta: float, n: float) -> float:
    """The rank error at which the trade-off curve, scaled by ``delta`` and ``n``, has slope one (0 where that is negative)."""
    return max(0.0, delta - math.sqrt(delta / n)) if n > 0 else 0.0


def direct_sketch_eps(phi: float) -> float:
    """Rank error of a sketch that is compared directly, for a distance precise to ``phi``."""
    return phi / 6.0


def expected_points(delta: float, n: float) -> float:
    """Knots at the unit-slope split: they grow with the root of n / delta."""
    return math.sqrt(n / delta) + 1.0


def expected_sketch_size(eps: float, n: float) -> float:
    """Scale of a quantile summary's size: log(eps n) / eps."""
    return max(1.0, math.log(max(math.e, eps * n))) / eps


@dataclass(frozen=True)
class CdfPlan:
    """How one sample's distribution function is built."""

    n: int
    delta: float
    eps: float
    a: int
    split: str

    @property
    def bound(self) -> float:
        """The certified error: the bound of the grid and the sketch, and one row for rounding of ranks."""
        if self.n < 3 and self.n > 0:
            return 1.0
        return max(self.delta, cdf_error_bound(self.a, self.eps)) + (1.0 / self.n if self.n else 0.0)


@dataclass(frozen=True)
class TestPlan:
    """How a pair of samples is compared."""

    phi: float
    x: CdfPlan
    y: CdfPlan

    @property
    def bound(self) -> float:
        return self.x.bound + self.y.bound


def plan_cdf(n: int, delta: float, split: str = "unit_slope", eps: float | None = None, a: int | None = None, max_points: int | None = DRIVER_KNOTS) -> CdfPlan:
    """Split the budget ``delta`` into rank error and grid.

    ``unit_slope``: the closed form that depends on n; ``balanced``: half the budget each, independent of
    n; ``fixed``: the given ``eps`` and ``a``. A unit-slope grid beyond ``max_points`` becomes balanced.
    """
    if split == "fixed":
        if eps is None or a is None:
            raise ValueError("a fixed split needs eps and a")
        return CdfPlan(n, cdf_error_bound(a, eps), eps, max(3, min(a, n)) if n >= 3 else max(n, 1), split)
    if split == "unit_slope":
        e = unit_slope_eps(delta, n)
        points = points_for(delta, e)
        if max_points is None or points <= max_points:
            return CdfPlan(n, delta, e if points <= n else 0.0, min(points, n) if n >= 3 else max(n, 1), split)
        warnings.warn(f"a unit-slope grid of {points} points is beyond {max_points}: the balanced split is taken", stacklevel=2)
    elif split != "balanced":
        raise ValueError(f"unknown split {split!r}")
    return CdfPlan(n, delta, delta / 2.0, points_for(delta, delta / 2.0), "balanced")


def plan_test(n: int, m: int, phi: float | None = None, alpha: float | None = None, beta: float | None = None, delta: float | None = None, split: str = "unit_slope", max_points: int | None = DRIVER_KNOTS) -> TestPlan:
    """Half of the wanted precision for each sample; the precision comes from ``phi``, ``delta``, or ``alpha`` and ``beta``."""
    if phi is None:
        phi = 2 * delta if delta is not None else precision_for(alpha, beta, n, m) if alpha is not None and beta is not None else PHI
    return TestPlan(phi, plan_cdf(n, phi / 2, split, max_points=max_points), plan_cdf(m, phi / 2, split, max_points=max_points))


def probability_grid(n: int, a: int) -> list[float]:
    """``a`` equi-spaced probabilities from 1/n (0 for unknown n) to 1."""
    low = 1.0 / n if n else 0.0
    return [low + (1.0 - low) * i / (a - 1) for i in range(a - 1)] + [1.0] if a > 1 else [1.0]


def probability_grid_df(spark: SparkSession, n: int, a: int) -> DataFrame:
    low = 1.0 / n if n else 0.0
    return spark.range(a).select(F.col("id").cast("int").alias("knot_id"), (F.lit(low) + F.lit(1.0 - low) * F.col("id") / F.lit(max(1, a - 1))).alias("p"))


def tradeoff_curve(spark: SparkSession, delta: float, n: int, steps: int = 50) -> DataFrame:
    """Points of the trade-off hyperbola: rank error, number of quantiles, slope in scaled axes; the unit-slope point is marked."""
    mark = unit_slope_eps(delta, n)
    eps = F.col("eps")
    rows = spark.range(steps).select((F.lit(delta) * F.col("id") / steps).alias("eps"), F.lit(False).alias("marked"))
    rows = rows.union(spark.range(1).select(F.lit(mark).alias("eps"), F.lit(True).alias("marked")))
    return rows.select("eps", (1.0 / (delta - eps) + 1.0).alias("a"), (F.lit(delta / n) / F.pow(delta - eps, F.lit(2))).alias("slope"), "marked")


def plan_table(spark: SparkSession, plan: TestPlan) -> DataFrame:
    """A plan as one row, for SQL."""
    row = {"phi": plan.phi, **{f"{k}_x": v for k, v in asdict(plan.x).items()}, **{f"{k}_y": v for k, v in asdict(plan.y).items()}}
    return spark.createDataFrame([row])
