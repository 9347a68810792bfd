"""Drift reports: many features, groups, hierarchies, corrections and explanations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from driftks.functions import significance as sig
from driftks.functions.scalars import cdf_at
from driftks.operators.prefix import cumulative
from driftks.operators.quantiles import grouped_knots
from driftks.operators.samples import long_features
from driftks.plans.lineage import settled
from driftks.sketch import kll


def side_counts(df: DataFrame, keys: list[str], value: Column, is_x: Column) -> DataFrame:
    """``keys``, ``value``, ``cx``, ``cy``: the value histogram of either side in every group, pre-aggregated before the shuffle."""
    rows = df.select(*keys, value.cast("double").alias("value"), is_x.alias("__x")).where(F.col("value").isNotNull() & ~F.isnan("value") & F.col("__x").isNotNull())
    return rows.groupBy(*keys, "value").agg(F.count_if("__x").alias("cx"), F.count_if(~F.col("__x")).alias("cy"))


def grouped_distance(hist: DataFrame, keys: list[str], partitions: int | None = None) -> DataFrame:
    """Exact distance in every group of a histogram: ``keys``, ``d``, ``n``, ``m``, ``p_value``.

    The histogram is dealt by ranges of (keys, value), so one group may span many tasks; counts of earlier ranges of a
    group are added as offsets. Groups with one empty side have no distance.
    """
    sums = cumulative(hist, keys, "value", ["cx", "cy"], partitions)
    gap = F.abs(F.try_divide("cx_upto", "cx_all") - F.try_divide("cy_upto", "cy_all"))
    out = sums.select(*keys, F.col("cx_all").alias("n"), F.col("cy_all").alias("m"), gap.alias("gap")).groupBy(*keys).agg(F.max("gap").alias("d"), F.max("n").alias("n"), F.max("m").alias("m"))
    return out.withColumn("p_value", sig.p_value("d", "n", "m"))


def drift_by_group(df: DataFrame, keys: list[str], value: Column, is_x: Column) -> DataFrame:
    """One exact test for each group."""
    return grouped_distance(side_counts(df, keys, value, is_x), keys)


def drift_by_feature(df: DataFrame, features: list[str], is_x: Column, keys: list[str] | None = None) -> DataFrame:
    """One exact test for each feature (and group), all from one scan."""
    keys = keys or []
    rows = long_features(df.withColumn("__is_x", is_x), features, [*keys, "__is_x"])
    return grouped_distance(side_counts(rows, [*keys, "feature"], F.col("value"), F.col("__is_x")), [*keys, "feature"])


def adjusted(tests: DataFrame, method: str = "holm", p: str = "p_value") -> DataFrame:
    """Add ``p_adjusted``: ``bonferroni``, ``holm`` or ``bh`` over all rows of a table of tests (a row a test)."""
    everything, rising = Window.partitionBy(), Window.orderBy(F.col(p))
    count = F.count(p).over(everything)
    rank = F.row_number().over(rising)
    one = F.lit(1.0)
    if method == "bonferroni":
        return tests.withColumn("p_adjusted", F.least(one, F.col(p) * count))
    if method == "holm":
        raw = tests.withColumn("__raw", F.col(p) * (count - rank + 1))
        return raw.withColumn("p_adjusted", F.least(one, F.max("__raw").over(rising.rowsBetween(Window.unboundedPreceding, 0)))).drop("__raw")
    if method == "bh":
        raw = tests.withColumn("__raw", F.col(p) * count / rank)
        return raw.withColumn("p_adjusted", F.least(one, F.min("__raw").over(rising.rowsBetween(0, Window.unboundedFollowing)))).drop("__raw")
    raise ValueError(f"unknown correction {method!r}")


def multi_feature_test(df: DataFrame, features: list[str], is_x: Column, correction: str = "holm") -> DataFrame:
    return adjusted(drift_by_feature(df, features, is_x), correction)


def levels(keys: list[str], cube: bool) -> list[list[str]]:
    """Key sets of a rollup (prefixes) or a cube (all subsets), the finest first."""
    if not cube:
        return [keys[:i] for i in range(len(keys), -1, -1)]
    return [[k for i, k in enumerate(keys) if mask >> i & 1] for mask in range(2 ** len(keys) - 1, -1, -1)]


def drift_rollup(df: DataFrame, keys: list[str], value: Column, is_x: Column, cube: bool = False) -> DataFrame:
    """Exact distance at every level of a hierarchy (or cube); a key that a level leaves out is null.

    Rows are counted once, at the finest level; coarser histograms are sums of finer ones.
    """
    finest = settled(side_counts(df, keys, value, is_x))
    kinds = {k: finest.schema[k].dataType for k in keys}
    every = None
    for i, level in enumerate(levels(keys, cube)):
        part = finest.groupBy(*level, "value").agg(F.sum("cx").alias("cx"), F.sum("cy").alias("cy"))
        part = part.select(F.lit(i).alias("level"), *(F.col(k) if k in level else F.lit(None).cast(kinds[k]).alias(k) for k in keys), "value", "cx", "cy")
        every = part if every is None else every.unionByName(part)
    return grouped_distance(every, ["level", *keys])


def sketch_rollup(df: DataFrame, keys: list[str], value: Column, is_x: Column, k: int = kll.K) -> DataFrame:
    """The same by KLL sketches: one scan at the finest level, then sketches alone are merged upwards. ``level``, keys, ``n``, ``m``, ``d``."""
    rows = df.select(*keys, value.cast("double").alias("value"), is_x.alias("__x")).where(F.col("value").isNotNull() & ~F.isnan("value"))
    x, v = F.col("__x"), F.col("value")
    fine = settled(rows.groupBy(*keys).agg(F.count_if(x).alias("n"), F.count_if(~x).alias("m"), F.kll_sketch_agg_double(F.when(x, v), k).alias("sx"), F.kll_sketch_agg_double(F.when(~x, v), k).alias("sy")))
    kinds = {c: fine.schema[c].dataType for c in keys}
    every = None
    for i, level in enumerate(levels(keys, False)):
        part = (fine.groupBy(*level) if level else fine.groupBy()).agg(F.sum("n").alias("n"), F.sum("m").alias("m"), F.kll_merge_agg_double("sx").alias("sx"), F.kll_merge_agg_double("sy").alias("sy"))
        part = part.select(F.lit(i).alias("level"), *(F.col(c) if c in level else F.lit(None).cast(kinds[c]).alias(c) for c in keys), "n", "m", "sx", "sy")
        every = part if every is None else every.unionByName(part)
    every = settled(every)
    top = every.where(F.col("level") == len(keys))
    return kll.distance(every.where("n > 0 and m > 0"), kll.probes_of(top)).drop("sx", "sy")


def pairwise_groups(df: DataFrame, key: str, value: str, delta: float = 0.01) -> DataFrame:
    """Approximate distance between all pairs of groups, over their knots: ``a``, ``b``, ``d_hat``. Rows are read once; pairs are of knot arrays."""
    knots = settled(grouped_knots(df, [key], value, delta))
    a = knots.select(F.col(key).alias("a"), F.col("knots").alias("ka"))
    b = knots.select(F.col(key).alias("b"), F.col("knots").alias("kb"))
    pairs = a.join(b, F.col("a") < F.col("b"))
    points = F.concat(F.transform("ka", lambda k: k["x"]), F.transform("kb", lambda k: k["x"]))
    rows = pairs.select("a", "b", "ka", "kb", F.explode(F.array_distinct(points)).alias("x"))
    gap = lambda left: F.abs(cdf_at(F.col("ka"), F.col("x"), left) - cdf_at(F.col("kb"), F.col("x"), left))
    return rows.groupBy("a", "b").agg(F.max(F.greatest(gap(False), gap(True))).alias("d_hat"))


def explain_gap(df: DataFrame, value: Column, is_x: Column, by: list[str], at: float) -> DataFrame:
    """Which segments the gap at value ``at`` comes from: shares of either side at or below it, in each segment; they add up to the signed gap."""
    v = value.cast("double")
    rows = df.where(v.isNotNull() & ~F.isnan(v))
    total = rows.agg(F.count_if(is_x).alias("n"), F.count_if(~is_x).alias("m"))
    per = rows.groupBy(*by).agg(F.count_if(is_x & (v <= at)).alias("x_below"), F.count_if(~is_x & (v <= at)).alias("y_below"))
    share = F.try_divide(F.col("x_below"), F.col("n")) - F.try_divide(F.col("y_below"), F.col("m"))
    return per.crossJoin(F.broadcast(total)).select(*by, "x_below", "y_below", share.alias("contribution"))


def without_each(df: DataFrame, segment: str, value: Column, is_x: Column, segments: int = 200) -> DataFrame:
    """Distance that is left when one segment is taken out: ``left_out``, ``d``, ``n``, ``m``.

    One histogram is kept, with each segment's counts beside it. Where a segment has no row of a value, its own running
    counts stand still and the others' gap is widest at a value of the others, so the gap is asked for at every value of the
    total: the segments (``segments`` of them at most, checked) are columns of one pass over it.
    """
    hist = settled(side_counts(df, [segment], value, is_x))
    names = [r[0] for r in hist.select(segment).distinct().limit(segments + 1).collect()]
    if len(names) > segments:
        raise ValueError(f"more than {segments} segments: take drift_by_group or explain_gap, or raise the bound")
    own = [c for i, k in enumerate(names) for c in (F.sum(F.when(F.col(segment).eqNullSafe(F.lit(k)), F.col("cx")).otherwise(0)).alias(f"x{i}"), F.sum(F.when(F.col(segment).eqNullSafe(F.lit(k)), F.col("cy")).otherwise(0)).alias(f"y{i}"))]
    wide = hist.groupBy("value").agg(F.sum("cx").alias("cx"), F.sum("cy").alias("cy"), *own)
    sums = cumulative(wide, [], "value", [c for c in wide.columns if c != "value"])
    rest = lambda side, i, end: F.col(f"c{side}_{end}") - F.col(f"{side}{i}_{end}")
    gap = lambda i: F.abs(F.try_divide(rest("x", i, "upto"), rest("x", i, "all")) - F.try_divide(rest("y", i, "upto"), rest("y", i, "all")))
    kind = hist.schema[segment].dataType
    row = [F.struct(F.lit(k).cast(kind).alias("left_out"), F.max(gap(i)).alias("d"), F.max(rest("x", i, "all")).alias("n"), F.max(rest("y", i, "all")).alias("m")) for i, k in enumerate(names)]
    if not row:
        return hist.sparkSession.createDataFrame([], f"left_out {kind.simpleString()}, d double, n long, m long")
    return sums.agg(F.array(*row).alias("rows")).select(F.inline("rows"))


def worst(tests: DataFrame, k: int, by: str = "d") -> DataFrame:
    """The ``k`` rows with the largest distance."""
    return tests.orderBy(F.desc(by)).limit(k)
