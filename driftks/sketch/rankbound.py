"""A mergeable quantile summary that keeps rank bounds, as a DataFrame.

A summary is a sorted list of (v, g, delta): ``v`` is a value of the sample, the least rank it can have is the sum
of ``g`` up to it, and the greatest is ``delta`` more. Tasks summarise what they read; summaries
are merged in a tree by key, so no task holds more than ``fanout`` of them.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from driftks.operators.samples import Sample

SCHEMA = "v double, g long, delta long"


def summarise(values: np.ndarray, eps: float) -> pd.DataFrame:
    """A summary of one chunk: every step-th rank of the sorted values, exact ranks, first and last included."""
    v = np.sort(values)
    n = len(v)
    if not n:
        return pd.DataFrame({"v": np.zeros(0), "g": np.zeros(0, np.int64), "delta": np.zeros(0, np.int64)})
    step = max(1, int(math.floor(2 * eps * n)))
    at = np.unique(np.append(np.arange(0, n, step), n - 1))
    return pd.DataFrame({"v": v[at], "g": np.diff(np.concatenate([[-1], at])), "delta": np.zeros(len(at), np.int64)})


def merge(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
    """The summary of both samples: rank bounds in the one come from the neighbours in the other."""
    if not len(a) or not len(b):
        return a if len(a) else b
    out = []
    for mine, other, side in ((a, b, "left"), (b, a, "right")):
        low_mine = np.cumsum(mine["g"].to_numpy())
        high_mine = low_mine + mine["delta"].to_numpy()
        low_other = np.cumsum(other["g"].to_numpy())
        high_other = low_other + other["delta"].to_numpy()
        k = np.searchsorted(other["v"].to_numpy(), mine["v"].to_numpy(), side=side)
        low = low_mine + np.where(k > 0, low_other[np.clip(k - 1, 0, None)], 0)
        high = high_mine + np.where(k < len(other), high_other[np.clip(k, None, len(other) - 1)] - 1, low_other[-1])
        out.append(pd.DataFrame({"v": mine["v"].to_numpy(), "low": low, "high": np.maximum(low, high)}))
    both = pd.concat(out).sort_values(["v", "low", "high"], kind="stable")
    low = np.maximum.accumulate(both["low"].to_numpy())
    high = np.minimum.accumulate(both["high"].to_numpy()[::-1])[::-1]
    high = np.maximum(high, low)
    return pd.DataFrame({"v": both["v"].to_numpy(), "g": np.diff(np.concatenate([[0], low])), "delta": high - low})


def compress(s: pd.DataFrame, eps: float) -> pd.DataFrame:
    """Drop entries as long as the gap of rank bounds between neighbours stays within 2 eps n."""
    if len(s) < 3:
        return s
    low = np.cumsum(s["g"].to_numpy())
    high = low + s["delta"].to_numpy()
    room = 2 * eps * low[-1]
    keep, last = [0], 0
    for i in range(1, len(s) - 1):
        if high[i + 1] - low[last] > room:
            keep.append(i)
            last = i
    keep.append(len(s) - 1)
    low, high = low[keep], high[keep]
    return pd.DataFrame({"v": s["v"].to_numpy()[keep], "g": np.diff(np.concatenate([[0], low])), "delta": high - low})


def _joined(allowed: float):
    """Merge the summaries of one parent, two by two, and compress the result to the error ``allowed`` so far."""

    def join(pdf: pd.DataFrame) -> pd.DataFrame:
        parts = [p[["v", "g", "delta"]].reset_index(drop=True) for _, p in pdf.sort_values(["bucket", "seq"], kind="stable").groupby("bucket", sort=True)]
        while len(parts) > 1:
            parts = [merge(parts[i], parts[i + 1]) if i + 1 < len(parts) else parts[i] for i in range(0, len(parts), 2)]
        done = compress(parts[0], allowed)
        return done.assign(seq=np.arange(len(done)), bucket=int(pdf["parent"].iloc[0]))

    return join


def tree_levels(partitions: int, fanout: int) -> int:
    return max(1, math.ceil(math.log(max(2, partitions), fanout)))


def rank_sketch(sample: Sample, eps: float, fanout: int = 16, chunk: int = 200_000) -> DataFrame:
    """The summary of a sample with rank error ``eps``, as rows ``v``, ``g``, ``delta``.

    Half of the budget goes to the chunks, the rest in equal parts to the levels of the merge tree.
    """
    values = sample.values()
    partitions = max(1, values.rdd.getNumPartitions())
    levels = tree_levels(partitions, fanout)
    leaf, step = eps / 2, eps / 2 / (levels + 1)

    def leaves(batches):
        import pyspark

        pid = pyspark.TaskContext.get().partitionId()
        held, size, whole = [], 0, None
        for batch in batches:
            held.append(batch["value"].to_numpy())
            size += len(batch)
            if size >= chunk:
                part = summarise(np.concatenate(held), leaf)
                whole = part if whole is None else compress_within(whole, part, leaf, step)
                held, size = [], 0
        if size:
            part = summarise(np.concatenate(held), leaf)
            whole = part if whole is None else compress_within(whole, part, leaf, step)
        if whole is not None:
            yield whole.assign(seq=np.arange(len(whole)), bucket=pid)

    def compress_within(a, b, leaf, step):
        return compress(merge(a, b), leaf + step)

    out = values.mapInPandas(leaves, SCHEMA + ", seq long, bucket int")
    for level in range(levels):
        allowed = leaf + step * (level + 2)
        out = out.withColumn("parent", F.floor(F.col("bucket") / fanout).cast("int")).groupBy("parent").applyInPandas(_joined(allowed), SCHEMA + ", seq long, bucket int")
    return out.select("v", "g", "delta")


def bounds(sketch: DataFrame) -> DataFrame:
    """``v`` with its least and greatest rank, and the size ``n`` of the sample. Over stored tuples only."""
    w = Window.orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    low = sketch.groupBy("v").agg(F.sum("g").alias("g"), F.max_by("delta", "delta").alias("delta")).withColumn("low", F.sum("g").over(w))
    return low.select("v", "low", (F.col("low") + F.col("delta")).alias("high"), F.sum("g").over(Window.partitionBy()).alias("n"))


def sketch_quantile(sketch: DataFrame, p: float) -> DataFrame:
    """The stored value whose rank bounds are nearest to rank p n."""
    b = bounds(sketch)
    wanted = F.ceil(F.lit(p) * F.col("n"))
    miss = F.greatest(wanted - F.col("low"), F.col("high") - wanted)
    return b.agg(F.min_by("v", F.struct(miss, "v")).alias("quantile"))


def sketch_rank_bounds(sketch: DataFrame, value: float) -> DataFrame:
    """Least and greatest number of rows at or below ``value``."""
    b = bounds(sketch)
    return b.agg(F.coalesce(F.max(F.when(F.col("v") <= value, F.col("low"))), F.lit(0)).alias("low"), F.coalesce(F.min(F.when(F.col("v") > value, F.col("high") - 1)), F.max("n")).alias("high"))
