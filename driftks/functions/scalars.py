"""Column functions the methods need beside the built-in ones."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


def as_double(df_type: T.DataType, column: Column) -> Column:
    """A value as DOUBLE: numbers and decimals by cast, dates and timestamps as epoch microseconds, day-time intervals as seconds."""
    if isinstance(df_type, (T.NumericType,)):
        return column.cast("double")
    if isinstance(df_type, T.TimestampNTZType):
        return F.unix_micros(column.cast("timestamp")).cast("double")
    if isinstance(df_type, (T.TimestampType, T.DateType)):
        return F.unix_micros(column.cast("timestamp")).cast("double")
    if isinstance(df_type, T.DayTimeIntervalType):
        return (column.cast("interval day to second").cast("decimal(38,6)")).cast("double")
    raise TypeError(f"{df_type.simpleString()} is not numeric: derive a number from it first, such as its length")


def normal_cdf(x: Column, mean: float = 0.0, sd: float = 1.0) -> Column:
    """The normal distribution function, by a rational approximation with an error below 1e-7."""
    z = (x - mean) / (sd * 2.0**0.5)
    a = F.abs(z)
    t = 1.0 / (1.0 + 0.3275911 * a)
    # Published coefficients of the approximation of the error function.
    c = (0.254829592, -0.284496736, 1.421413741, -1.453152027, 1.061405429)
    poly = F.lit(0.0)
    for k in reversed(c):
        poly = (poly + k) * t
    erf = F.signum(z) * (1.0 - poly * F.exp(-a * a))
    return 0.5 * (1.0 + erf)


def uniform_cdf(x: Column, low: float = 0.0, high: float = 1.0) -> Column:
    return F.greatest(F.lit(0.0), F.least(F.lit(1.0), (x - low) / (high - low)))


def exponential_cdf(x: Column, mean: float = 1.0) -> Column:
    return F.when(x <= 0, 0.0).otherwise(1.0 - F.exp(-x / mean))


MODELS = {"norm": normal_cdf, "uniform": uniform_cdf, "expon": exponential_cdf}


def cdf_at(knots: Column, x: Column, left: bool = False) -> Column:
    """Value at ``x`` of a distribution kept as sorted array<struct<x, p_lo, p_hi>>; ``left``: the limit from below.

    Between two knots the function runs from ``p_hi`` of the one to ``p_lo`` of the other; outside the knots
    it keeps the nearest knot's probability.
    """
    below = F.filter(knots, lambda k: k["x"] <= x)
    last, first = F.element_at(below, -1), F.get(knots, F.size(below))
    slope = (x - last["x"]) / (first["x"] - last["x"]) * (first["p_lo"] - last["p_hi"])
    at_knot = last["p_lo"] if left else last["p_hi"]
    return (
        F.when(F.size(knots) == 0, F.lit(None).cast("double"))
        .when(F.size(below) == 0, F.get(knots, F.lit(0))["p_lo"])
        .when(last["x"] == x, at_knot)
        .when(first.isNull(), last["p_hi"])
        .otherwise(last["p_hi"] + slope)
    )
