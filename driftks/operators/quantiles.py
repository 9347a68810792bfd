"""Quantiles of samples from Spark's summaries."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from driftks.operators.samples import Sample, tagged
from driftks.plans.config import DRIVER_KNOTS
from driftks.plans.params import CdfPlan, probability_grid

ENGINES = ("summary", "aggregate", "exact")


def accuracy(eps: float) -> int:
    """The integer accuracy of ``percentile_approx`` whose rank error is ``eps`` at most."""
    return min(2**31 - 1, max(1, math.ceil(1.0 / eps))) if eps > 0 else 2**31 - 1


def grid_literal(grid: list[float]) -> Column:
    """A grid as a constant of the plan, sent as one text: element by element, long grids cost more than the scan."""
    return F.split(F.lit(",".join(map(repr, grid))), ",").cast("array<double>")


def knots_column(value: Column, grid: list[float], eps: float) -> Column:
    """An aggregate that gives the quantiles of ``value`` at ``grid`` as one array."""
    if len(grid) > DRIVER_KNOTS:
        raise ValueError(f"{len(grid)} probabilities are too many for a literal; use the balanced split")
    return F.percentile_approx(value, grid_literal([float(p) for p in grid]), F.lit(accuracy(eps)))


def quantile_knots(sample: Sample, plan: CdfPlan, engine: str = "aggregate") -> tuple[list[float], list[float]]:
    """The grid of ``plan`` and the sample's quantiles there.

    ``aggregate``: the quantile summary as an aggregate inside a plan; ``summary``: the same, eagerly, by ``approxQuantile``
    (which passes probabilities and quantiles one by one); ``exact``: rank error 0. Only the knots come to the driver.
    """
    grid = probability_grid(plan.n, plan.a)
    if engine == "aggregate":
        found = sample.values().agg(knots_column(F.col("value"), grid, plan.eps)).first()[0]
    elif engine in ENGINES:
        found = sample.values().approxQuantile("value", grid, 0.0 if engine == "exact" else plan.eps)
    else:
        raise ValueError(f"unknown engine {engine!r}")
    return (grid, list(found)) if found else ([], [])


def both_knots(ref: Sample, test: Sample, plans: tuple[CdfPlan, CdfPlan]) -> list[tuple[list[float], list[float]]]:
    """Grid and quantiles of two samples, from one aggregate over their tagged union: one job, no row shuffled."""
    grids = [probability_grid(p.n, p.a) for p in plans]
    value = lambda side: F.when(F.col("side") == side, F.col("value"))
    row = tagged(ref, test).agg(*(knots_column(value(s), g, p.eps) for s, g, p in zip("xy", grids, plans, strict=True))).first()
    return [(g, list(q)) if q else ([], []) for g, q in zip(grids, row, strict=True)]


def pair_knots(df: DataFrame, value: Column, is_x: Column, grids: tuple[list[float], list[float]], eps: tuple[float, float]) -> tuple[list[float], list[float], int, int]:
    """Knots and sizes of two sides of one table in one scan: two conditional sketches and two counts in one aggregate."""
    value = value.cast("double")
    fine = F.when(value.isNotNull() & ~F.isnan(value), value)
    x, y = F.when(is_x, fine), F.when(~is_x, fine)
    row = df.agg(knots_column(x, grids[0], eps[0]), knots_column(y, grids[1], eps[1]), F.count(x), F.count(y)).first()
    return list(row[0] or []), list(row[1] or []), row[2], row[3]


def grouped_knots(df: DataFrame, keys: list[str], value: str, delta: float, grid_points: int | None = None) -> DataFrame:
    """``keys``, ``n`` and ``knots`` (array<struct<x, p_lo, p_hi>>) of every group; only sketches are shuffled.

    All groups share one grid, which must be a literal, so the balanced split is used.
    """
    a = grid_points or math.ceil(2 / delta) + 1
    grid = probability_grid(0, a)
    fine = F.col(value).isNotNull() & ~F.isnan(value)
    q = df.where(fine).groupBy(*keys).agg(F.count("*").alias("n"), knots_column(F.col(value).cast("double"), grid, delta / 2).alias("q"))
    return q.select(*keys, "n", collapsed_column(F.col("q"), grid).alias("knots"))


def collapsed_column(q: Column, grid: list[float]) -> Column:
    """Knots from an array of quantiles at ``grid``: equal quantiles become one knot with its first and last probability."""
    p = grid_literal([float(x) for x in grid])
    pairs = F.arrays_zip(q.alias("x"), p.alias("p"))
    kind = "array<struct<x:double,p_lo:double,p_hi:double>>"

    def add(out: Column, k: Column) -> Column:
        last = F.element_at(out, -1)
        x, prob = k["x"].cast("double"), k["p"]
        fresh = F.array(F.struct(x.alias("x"), prob.alias("p_lo"), prob.alias("p_hi")))
        widened = F.array(F.struct(last["x"].alias("x"), last["p_lo"].alias("p_lo"), prob.alias("p_hi")))
        return F.when((F.size(out) > 0) & (F.get(out, F.size(out) - 1)["x"] == x), F.concat(F.slice(out, 1, F.size(out) - 1), widened)).otherwise(F.concat(out, fresh)).cast(kind)

    return F.aggregate(pairs, F.array().cast(kind), add)
