"""Significance of a KS distance: tail probability, p-value, critical distance and precision.

Every function has a Column form, which stays inside Catalyst, and a plain Python form for planning.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from driftks.plans.config import SERIES_TERMS, TAIL_IS_ONE


def _col(x) -> Column:
    return x if isinstance(x, Column) else F.col(x) if isinstance(x, str) else F.lit(float(x))


def ks_tail(lam) -> Column:
    """Probability that the scaled distance exceeds ``lam`` under the null hypothesis."""
    lam = _col(lam).cast("double")
    term = lambda k: F.when(k % 2 == 1, 1.0).otherwise(-1.0) * F.exp(F.lit(-2.0) * k * k * lam * lam)
    total = F.aggregate(F.sequence(F.lit(1), F.lit(SERIES_TERMS)), F.lit(0.0), lambda s, k: s + term(k))
    return F.when(lam.isNull(), F.lit(None).cast("double")).when(lam < TAIL_IS_ONE, F.lit(1.0)).otherwise(F.greatest(F.lit(0.0), F.least(F.lit(1.0), 2.0 * total)))


def ks_tail_py(lam: float) -> float:
    if lam < TAIL_IS_ONE:
        return 1.0
    total = math.fsum((-1) ** (k - 1) * math.exp(-2.0 * k * k * lam * lam) for k in range(1, SERIES_TERMS + 1))
    return min(1.0, max(0.0, 2.0 * total))


def effective_scale(n, m, small_sample: bool = False) -> Column:
    """sqrt(nm / (n+m)); with ``small_sample``, the published correction for small samples on top."""
    n, m = _col(n).cast("double"), _col(m).cast("double")
    root = F.sqrt(F.try_divide(n * m, n + m))
    return root + 0.12 + 0.11 / root if small_sample else root


def effective_scale_py(n: float, m: float, small_sample: bool = False) -> float:
    root = math.sqrt(n * m / (n + m)) if n and m else 0.0
    return root + 0.12 + 0.11 / root if small_sample and root else root


def p_value(d, n, m, small_sample: bool = False) -> Column:
    """Significance of distance ``d`` between samples of ``n`` and ``m`` rows."""
    return ks_tail(effective_scale(n, m, small_sample) * _col(d))


def p_value_py(d: float, n: float, m: float, small_sample: bool = False) -> float:
    return ks_tail_py(effective_scale_py(n, m, small_sample) * d)


def log_p_value_py(d: float, n: float, m: float) -> float:
    """Natural logarithm of the p-value; right far out in the tail, where the series underflows."""
    lam = effective_scale_py(n, m) * d
    return math.log(ks_tail_py(lam)) if lam < 5 else math.log(2.0) - 2.0 * lam * lam


def ks_tail_inverse(alpha: float) -> float:
    """The scaled distance whose tail probability is ``alpha``."""
    if not 0 < alpha < 1:
        raise ValueError("alpha must lie between 0 and 1")
    low, high = TAIL_IS_ONE, 40.0
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if ks_tail_py(mid) > alpha else (low, mid)
    return (low + high) / 2


def critical_distance(alpha: float, n, m):
    """The distance whose p-value is ``alpha``: a float for numbers, a Column for columns."""
    lam = ks_tail_inverse(alpha)
    if isinstance(n, (int, float)) and isinstance(m, (int, float)):
        return lam / effective_scale_py(n, m)
    return F.lit(lam) / effective_scale(n, m)


def precision_for(alpha: float, beta: float, n: float, m: float) -> float:
    """The smaller shift of the critical distance when ``alpha`` moves by ``beta`` either way (upwards only where ``beta`` >= ``alpha``)."""
    at = critical_distance(alpha, n, m)
    shifts = [abs(critical_distance(a, n, m) - at) for a in (alpha - beta, alpha + beta) if 0 < a < 1]
    if not shifts:
        raise ValueError("neither alpha + beta nor alpha - beta is a probability")
    return min(shifts)


def decide(p, alpha: float) -> Column:
    """Whether the null hypothesis is rejected at level ``alpha``."""
    return F.when(_col(p) <= alpha, True).otherwise(False)


def certified_decision(d_hat, bound, d_crit) -> Column:
    """``reject``, ``accept`` or ``undecided`` from an approximate distance and the bound of its error."""
    d_hat, bound, d_crit = _col(d_hat), _col(bound), _col(d_crit)
    return F.when(d_hat - bound >= d_crit, "reject").when(d_hat + bound < d_crit, "accept").otherwise("undecided")


def p_value_interval(d_hat, bound, n, m) -> tuple[Column, Column]:
    """Least and greatest p-value of the distances within ``bound`` of ``d_hat``."""
    d_hat, bound = _col(d_hat), _col(bound)
    return p_value(F.least(F.lit(1.0), d_hat + bound), n, m), p_value(F.greatest(F.lit(0.0), d_hat - bound), n, m)
