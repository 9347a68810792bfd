"""KLL sketches of Spark: native, mergeable, with a probabilistic rank error."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from driftks.functions import significance as sig
from driftks.operators.samples import Sample, tagged
from driftks.plans.config import ALPHA
from driftks.plans.lineage import settled

K = 800


def sketches(df: DataFrame, keys: list[str], value: str | Column = "value", k: int = K) -> DataFrame:
    """``keys``, ``n`` and ``sketch`` (binary) of every group; sketches are merged before and after the shuffle."""
    v = F.col(value) if isinstance(value, str) else value
    return df.groupBy(*keys).agg(F.count(v).alias("n"), F.kll_sketch_agg_double(v.cast("double"), k).alias("sketch"))


def merged(df: DataFrame, keys: list[str]) -> DataFrame:
    """Sketches rolled up to coarser ``keys``; the rows they came from are not read again."""
    out = df.groupBy(*keys) if keys else df.groupBy()
    return out.agg(F.sum("n").alias("n"), F.kll_merge_agg_double("sketch").alias("sketch"))


def probes_of(pair: DataFrame, columns: tuple[str, ...] = ("sx", "sy"), probes: int = 200) -> list[float]:
    """Quantiles of the sketches in a one-row table, as probe values (they must be literals in a plan)."""
    grid = F.array(*(F.lit((i + 0.5) / probes) for i in range(probes)))
    row = pair.select(*(F.kll_sketch_get_quantile_double(c, grid) for c in columns)).first()
    return sorted({float(v) for r in row for v in r or []})


def distance(pairs: DataFrame, probes: list[float], x: str = "sx", y: str = "sy") -> DataFrame:
    """Add ``d``: the widest gap of the two sketches' ranks at the probe values."""
    points = F.array(*map(F.lit, probes))
    ranks = F.zip_with(F.kll_sketch_get_rank_double(x, points), F.kll_sketch_get_rank_double(y, points), lambda a, b: F.abs(a - b))
    return pairs.withColumn("d", F.array_max(ranks))


def direct_kll_test(ref: Sample, test: Sample, k: int = K, alpha: float = ALPHA) -> DataFrame:
    """The direct-sketch test on KLL sketches of both sides, in one aggregate over the tagged union."""
    x, y = F.col("side") == "x", F.col("side") == "y"
    row = tagged(ref, test).agg(
        F.count_if(x).alias("n"), F.count_if(y).alias("m"),
        F.kll_sketch_agg_double(F.when(x, F.col("value")), k).alias("sx"), F.kll_sketch_agg_double(F.when(y, F.col("value")), k).alias("sy"),
    )
    row = settled(row)
    out = distance(row, probes_of(row)).select("d", "n", "m")
    return out.withColumn("p_value", sig.p_value("d", "n", "m")).withColumn("reject", F.col("p_value") <= alpha)
