"""The exact two-sample distance, four ways, and the exact one-sample distance.

All start from the value histogram (distinct values with their counts on either side), which Spark
pre-aggregates before the shuffle: ties vanish and repeated values cost one row a task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from driftks.functions.scalars import MODELS
from driftks.operators.prefix import cumulative
from driftks.operators.samples import Sample, tagged

METHODS = ("window", "range", "refine", "histogram_join")


def histogram(ref: Sample, test: Sample) -> DataFrame:
    """``value``, ``cx`` and ``cy``: how often each distinct value occurs in either sample."""
    return tagged(ref, test).groupBy("value").agg(F.count_if(F.col("side") == "x").alias("cx"), F.count_if(F.col("side") == "y").alias("cy"))


def _gaps(hist: DataFrame, window, n: Column, m: Column, before_x: Column | int = 0, before_y: Column | int = 0) -> DataFrame:
    fx = F.try_divide(F.sum("cx").over(window) + before_x, n)
    fy = F.try_divide(F.sum("cy").over(window) + before_y, m)
    return hist.select("*", fx.alias("fx"), fy.alias("fy"), F.abs(fx - fy).alias("gap"))


def _widest(gaps: DataFrame) -> DataFrame:
    """``d``, the widest gap, and ``at``, the least value where it occurs."""
    return gaps.agg(F.max("gap").alias("d"), F.min_by("value", F.struct(-F.col("gap"), "value")).alias("at"))


def _sized(gaps: DataFrame) -> DataFrame:
    return gaps.agg(F.max("gap").alias("d"), F.min_by("value", F.struct(-F.col("gap"), "value")).alias("at"), F.max("n").alias("n"), F.max("m").alias("m"))


def gaps_of(hist: DataFrame, partitions: int | None = None) -> DataFrame:
    """Both exact functions and their gap at each value of a histogram, by value ranges; no task sees all rows."""
    sums = cumulative(hist, [], "value", ["cx", "cy"], partitions)
    fx, fy = F.try_divide("cx_upto", "cx_all"), F.try_divide("cy_upto", "cy_all")
    return sums.select("value", "cx", "cy", fx.alias("fx"), fy.alias("fy"), F.abs(fx - fy).alias("gap"), F.col("cx_all").alias("n"), F.col("cy_all").alias("m"))


def gap_table(ref: Sample, test: Sample) -> DataFrame:
    """Both exact functions and their gap at each distinct value."""
    return gaps_of(histogram(ref, test))


def _by_window(hist: DataFrame) -> DataFrame:
    """The textbook form, one sorted partition: for a histogram of few values (bins, categories)."""
    totals = hist.agg(F.sum("cx").alias("n"), F.sum("cy").alias("m"))
    ordered = Window.orderBy("value").rowsBetween(Window.unboundedPreceding, 0)
    return _sized(_gaps(hist.crossJoin(F.broadcast(totals)), ordered, F.col("n"), F.col("m")))


def _by_range(hist: DataFrame, partitions: int | None = None) -> DataFrame:
    """Cumulative counts within value ranges, on top of the sums of the ranges before."""
    return _sized(gaps_of(hist, partitions))


def _by_join(ref: Sample, test: Sample, partitions: int | None = None) -> DataFrame:
    x = ref.values().groupBy("value").agg(F.count("*").alias("cx"))
    y = test.values().groupBy("value").agg(F.count("*").alias("cy"))
    return _by_range(x.join(y, "value", "full_outer").select("value", F.coalesce("cx", F.lit(0)).alias("cx"), F.coalesce("cy", F.lit(0)).alias("cy")), partitions)


def bucket_of(value: Column, edges: list[float]) -> Column:
    """How many of the sorted ``edges`` are below ``value``, by bisection inside the plan."""
    e = F.array(*map(F.lit, edges))
    steps = max(1, len(edges).bit_length())
    start = F.struct(F.lit(0).alias("low"), F.lit(len(edges)).alias("high"))

    def halve(s: Column, _: Column) -> Column:
        mid = F.floor((s["low"] + s["high"]) / 2).cast("int")
        over = F.get(e, mid) < value
        open_ = s["low"] < s["high"]
        return F.struct(F.when(open_ & over, mid + 1).otherwise(s["low"]).alias("low"), F.when(open_ & ~over, mid).otherwise(s["high"]).alias("high"))

    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, halve)["low"]


def _by_refining(ref: Sample, test: Sample, knots: int) -> DataFrame:
    """Exact counts in buckets bound the gap inside each; only buckets that can hold the widest gap are sorted."""
    spark = ref.df.sparkSession
    both = tagged(ref, test)
    edges = sorted(set(both.approxQuantile("value", [i / knots for i in range(knots + 1)], 0.5 / knots)))
    if not edges:
        return _by_window(histogram(ref, test))
    placed = both.withColumn("bucket", bucket_of(F.col("value"), edges))
    # one row a bucket: at most ``knots`` + 2
    counts = {r["bucket"]: (r["cx"], r["cy"]) for r in placed.groupBy("bucket").agg(F.count_if(F.col("side") == "x").alias("cx"), F.count_if(F.col("side") == "y").alias("cy")).collect()}
    n, m = (sum(c[k] for c in counts.values()) for k in (0, 1))
    if not n or not m:
        return _by_window(histogram(ref, test))
    rows, x, y, best = [], 0, 0, 0.0
    for b in range(len(edges) + 1):
        cx, cy = counts.get(b, (0, 0))
        most = max((x + cx) / n - y / m, (y + cy) / m - x / n)
        rows.append((b, x, y, most))
        x, y = x + cx, y + cy
        best = max(best, abs(x / n - y / m))
    alive = [r[:3] for r in rows if r[3] >= best - 1e-12]
    starts = F.broadcast(spark.createDataFrame(alive, "bucket int, bx long, by long"))
    hist = placed.join(starts, "bucket").groupBy("bucket", "bx", "by", "value").agg(F.count_if(F.col("side") == "x").alias("cx"), F.count_if(F.col("side") == "y").alias("cy"))
    inside = Window.partitionBy("bucket").orderBy("value").rowsBetween(Window.unboundedPreceding, 0)
    gaps = _gaps(hist, inside, F.lit(n), F.lit(m), F.col("bx"), F.col("by"))
    return _widest(gaps).select("d", "at", F.lit(n).cast("long").alias("n"), F.lit(m).cast("long").alias("m"))


def exact_distance(ref: Sample, test: Sample, method: str = "range", partitions: int | None = None, knots: int = 256) -> DataFrame:
    """One row: ``d``, ``at`` (the least value with the widest gap), ``n`` and ``m``.

    ``window`` sorts the histogram in one partition and is for few distinct values; ``range``, ``refine`` and
    ``histogram_join`` (of the two histograms) hold at any size. All give the same numbers.
    """
    if method == "window":
        return _by_window(histogram(ref, test))
    if method == "range":
        return _by_range(histogram(ref, test), partitions)
    if method == "refine":
        return _by_refining(ref, test, knots)
    if method == "histogram_join":
        return _by_join(ref, test, partitions)
    raise ValueError(f"unknown method {method!r}")


def exact_cdf(sample: Sample) -> DataFrame:
    """``value``, its count ``c``, the sample's size ``n`` and the exact distribution function ``cdf``, right-continuous at ties."""
    hist = sample.values().groupBy("value").agg(F.count("*").alias("c"))
    sums = cumulative(hist, [], "value", ["c"])
    return sums.select("value", "c", F.col("c_all").alias("n"), (F.col("c_upto") / F.col("c_all")).alias("cdf"))


def model_cdf(value: Column, dist, **params) -> Column:
    """The distribution function of a named model or of a function from Column to Column."""
    return MODELS[dist](value, **params) if isinstance(dist, str) else dist(value, **params)


def one_sample_distance(sample: Sample, dist, **params) -> DataFrame:
    """One row ``d``, ``n``: the exact distance between a sample and a model, either side of every step."""
    cdf = exact_cdf(sample).withColumn("left", F.col("cdf") - F.col("c") / F.col("n"))
    model = model_cdf(F.col("value"), dist, **params)
    gap = F.greatest(F.abs(F.col("cdf") - model), F.abs(F.col("left") - model))
    return cdf.select(gap.alias("gap"), "c").agg(F.max("gap").alias("d"), F.sum("c").alias("n"))


def signed_distance(state: DataFrame) -> DataFrame:
    """Distance from a multiset table ``side``, ``value``, ``sign`` (+1 inserted, -1 removed)."""
    net = state.groupBy("value").agg(F.sum(F.when(F.col("side") == "x", F.col("sign")).otherwise(0)).alias("cx"), F.sum(F.when(F.col("side") == "y", F.col("sign")).otherwise(0)).alias("cy"))
    return _by_range(net.where("cx <> 0 or cy <> 0"))


def incremental_test(ref: Sample, test: Sample, inserts: DataFrame, deletes: DataFrame) -> DataFrame:
    """Distance after insertions and removals (tables ``side``, ``value``); histograms are updated, nothing is sorted anew but them."""
    now = tagged(ref, test).withColumn("sign", F.lit(1))
    more = inserts.select("side", F.col("value").cast("double").alias("value"), F.lit(1).alias("sign"))
    less = deletes.select("side", F.col("value").cast("double").alias("value"), F.lit(-1).alias("sign"))
    return signed_distance(now.unionByName(more).unionByName(less))
