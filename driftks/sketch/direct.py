"""The direct-sketch test: two quantile summaries are compared themselves."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftks.functions import significance as sig
from driftks.operators.samples import Sample
from driftks.plans.config import ALPHA
from driftks.plans.params import direct_sketch_eps
from driftks.sketch.rankbound import rank_sketch


def _function(rows) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """Stored values with the least and the greatest number of rows at or below each."""
    rows = sorted(rows, key=lambda r: r[0])
    v = np.array([r[0] for r in rows])
    low = np.cumsum([r[1] for r in rows])
    high = low + np.array([r[2] for r in rows])
    last = np.append(v[1:] != v[:-1], True)
    return v[last], low[last], high[last], int(low[-1]) if len(low) else 0


def _at(f, points: np.ndarray) -> np.ndarray:
    """Middle of the rank bounds at ``points``, as a share of the sample."""
    v, low, high, n = f
    i = np.searchsorted(v, points, side="right") - 1
    least = np.where(i >= 0, low[np.clip(i, 0, None)], 0)
    most = np.where(i + 1 < len(v), high[np.clip(i + 1, None, len(v) - 1)] - 1, n)
    most = np.where((i >= 0) & (v[np.clip(i, 0, None)] == points), np.maximum(least, np.minimum(most, high[np.clip(i, 0, None)])), most)
    return (least + np.maximum(least, most)) / 2 / n


def direct_sketch_test(ref: Sample, test: Sample, phi: float, alpha: float = ALPHA) -> DataFrame:
    """One row: ``d_sketch``, sizes of samples and summaries, ``eps``, ``p_value``, ``reject``. Only stored tuples reach the driver."""
    spark, eps = ref.df.sparkSession, direct_sketch_eps(phi)
    fx, fy = (_function([tuple(r) for r in rank_sketch(s, eps).collect()]) for s in (ref, test))
    if not len(fx[0]) or not len(fy[0]):
        return spark.createDataFrame([], "d_sketch double, n long, m long, points_x int, points_y int, eps double, p_value double, reject boolean")
    points = np.union1d(fx[0], fy[0])
    d = float(np.abs(_at(fx, points) - _at(fy, points)).max())
    row = spark.createDataFrame([(d, fx[3], fy[3], len(fx[0]), len(fy[0]), eps)], "d_sketch double, n long, m long, points_x int, points_y int, eps double")
    return row.withColumn("p_value", sig.p_value("d_sketch", "n", "m")).withColumn("reject", F.col("p_value") <= alpha)
