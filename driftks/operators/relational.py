"""Relational operators around the tests: profiles, joins, set operations, windows, time and text features."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from driftks.operators.cdf import eval_cdf, from_knots
from driftks.operators.workloads import gauss
from driftks.plans.params import CdfPlan
from driftks.sources import load

#: Knots that stand for a stored reference in the evaluation queries.
REFERENCE = [(0.0, 0.0, 0.0), (10.0, 0.2, 0.2), (30.0, 0.45, 0.5), (60.0, 0.75, 0.75), (150.0, 0.95, 0.95), (400.0, 1.0, 1.0)]


def dirty_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with missing readings put in: null where the id is divisible by 43, NaN where it is divisible by 10."""
    value = F.when(F.col("event_id") % 43 == 0, F.lit(None)).when(F.col("event_id") % 10 == 0, F.lit(float("nan"))).otherwise(F.col("value"))
    return load(spark, sf_dir, "events").select("event_id", "event_type", value.alias("value"))


def clean_counts(spark, sf_dir):
    fine = F.col("value").isNotNull() & ~F.isnan("value")
    return dirty_events(spark, sf_dir).groupBy("event_type").agg(F.count_if(fine).alias("kept"), F.count_if(~F.coalesce(fine, F.lit(False))).alias("dropped"))


def slices_profile(spark, sf_dir):
    """Twenty replications in one scan: size, range and mean of each."""
    g = gauss(spark, sf_dir).withColumn("slice", F.pmod(F.floor(F.col("vec_id") / 2), F.lit(20)).cast("int"))
    return g.groupBy("slice").agg(F.count("*").alias("n"), F.round(F.min("z"), 6).alias("low"), F.round(F.max("z"), 6).alias("high"), F.round(F.avg("z"), 6).alias("mean"))


def join_labels(spark, sf_dir):
    """Sort-merge join of documents and labels, then a profile by quality and language."""
    d = load(spark, sf_dir, "documents").select("doc_id", "lang", "n_chars")
    j = d.hint("merge").join(load(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id")
    return j.groupBy("quality", "lang").agg(F.count("*").alias("n"), F.round(F.avg("n_chars"), 6).alias("mean_chars"))


def histogram_outer(spark, sf_dir):
    """Full outer join of two value histograms."""
    t = load(spark, sf_dir, "lineitem")
    a = t.groupBy(F.col("l_discount").alias("value")).agg(F.count("*").alias("c"))
    b = t.groupBy(F.col("l_tax").alias("value")).agg(F.count("*").alias("c2"))
    return a.join(b, "value", "full_outer").select("value", F.coalesce("c", F.lit(0)).alias("cx"), F.coalesce("c2", F.lit(0)).alias("cy"))


def parameter_grid(spark, sf_dir):
    """Every setting of the convergence study with every slice (a tiny cross join)."""
    from driftks.operators.workloads import CONVERGENCE

    s = spark.createDataFrame(CONVERGENCE, "a int, eps double")
    return s.crossJoin(spark.range(20).select(F.col("id").alias("slice"))).select("a", "eps", "slice", F.round(1.0 / (F.col("a") - 1) + F.col("eps"), 9).alias("bound"))


def interval_events(spark, sf_dir):
    """Interval join of events with weekly monitor windows: equality on the day, then the interval's condition."""
    days = spark.range(5).select(F.expr("timestamp_ntz'2024-01-01' + make_dt_interval(cast(id as int) * 7)").alias("start"), F.col("id").alias("week"))
    windows = days.withColumn("end", F.expr("start + make_dt_interval(7)")).withColumn("day", F.explode(F.expr("sequence(cast(start as date), cast(end as date) - 1)")))
    e = load(spark, sf_dir, "events").select("ts", "value", F.col("ts").cast("date").alias("day"))
    j = e.join(F.broadcast(windows), "day").where((F.col("ts") >= F.col("start")) & (F.col("ts") < F.col("end")))
    return j.groupBy("week").agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("mean"))


def describe_sample(spark, sf_dir):
    """Moments, exact quantiles and mode of order prices by status."""
    o = load(spark, sf_dir, "orders")
    v = "o_totalprice"
    return o.groupBy("o_orderstatus").agg(
        F.count(v).alias("n"), F.round(F.avg(v), 4).alias("mean"), F.round(F.stddev_samp(v), 4).alias("sd"), F.round(F.percentile(v, F.lit(0.25)), 4).alias("q1"), F.round(F.median(v), 4).alias("median"), F.round(F.percentile(v, F.lit(0.75)), 4).alias("q3"), F.min(v).alias("low"), F.max(v).alias("high"),
    )


def pivot_report(spark, sf_dir):
    """Mean price by year, flags as columns."""
    t = load(spark, sf_dir, "lineitem").withColumn("year", F.year("l_shipdate"))
    return t.groupBy("year").pivot("l_returnflag", ["A", "N", "R"]).agg(F.round(F.avg("l_extendedprice"), 4)).select("year", F.col("A").alias("flag_a"), F.col("N").alias("flag_n"), F.col("R").alias("flag_r"))


def ranked_values(spark, sf_dir):
    """All ranking windows over supplier balances within a nation."""
    w = Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")
    s = load(spark, sf_dir, "supplier")
    return s.select("s_suppkey", F.row_number().over(w).alias("row_no"), F.rank().over(w).alias("rank_no"), F.dense_rank().over(w).alias("dense_no"), F.round(F.percent_rank().over(w), 9).alias("percent"), F.round(F.cume_dist().over(w), 9).alias("cume"), F.ntile(4).over(w).alias("quarter"), F.lag("s_suppkey").over(w).alias("before"), F.first("s_suppkey").over(w).alias("first_key"), F.nth_value("s_suppkey", 2).over(w).alias("second_key"))


def rolling_mean_range(spark, sf_dir):
    """Count and sum of the values within 5 below each distinct value (a RANGE frame), by event type."""
    e = load(spark, sf_dir, "events").groupBy("event_type", "value").agg(F.count("*").alias("c"))
    w = Window.partitionBy("event_type").orderBy("value").rangeBetween(-5, 0)
    return e.select("event_type", "value", F.sum("c").over(w).alias("within"), F.round(F.sum(F.col("value") * F.col("c")).over(w), 4).alias("total"))


def text_features(spark, sf_dir):
    """Derived numeric features of three text tables."""
    def one(table, text, name):
        t = load(spark, sf_dir, table).select(F.char_length(text).alias("chars"), F.size(F.split(F.trim(F.regexp_replace(text, r"[\x20\t\n]+", " ")), " ")).alias("words"))
        return t.agg(F.lit(name).alias("source"), F.count("*").alias("n"), F.sum("chars").alias("chars"), F.sum("words").alias("words"))

    return one("documents", "text", "documents").unionByName(one("pages", "html", "pages")).unionByName(one("conversations", "text", "conversations"))


def exploded_gauss(spark, sf_dir):
    """Size, mean and deviation of each embedding dimension."""
    return gauss(spark, sf_dir).groupBy("dim").agg(F.count("*").alias("n"), F.round(F.avg("z"), 6).alias("mean"), F.round(F.stddev_samp("z"), 6).alias("sd"))


def union_points(spark, sf_dir):
    """Distinct values of both sides: the points at which two functions are compared."""
    t = load(spark, sf_dir, "lineitem")
    return t.select(F.col("l_discount").alias("x")).unionByName(t.select(F.col("l_tax").alias("x"))).distinct()


def new_values_except(spark, sf_dir):
    t = load(spark, sf_dir, "lineitem")
    return t.select(F.col("l_discount").alias("x")).exceptAll(t.select(F.col("l_tax").alias("x"))).groupBy("x").agg(F.count("*").alias("surplus"))


def common_values_intersect(spark, sf_dir):
    t = load(spark, sf_dir, "lineitem")
    return t.select(F.col("l_discount").alias("x")).intersectAll(t.select(F.col("l_tax").alias("x"))).groupBy("x").agg(F.count("*").alias("shared"))


def labelled_semi(spark, sf_dir):
    d = load(spark, sf_dir, "documents").select("doc_id", "lang", "n_chars")
    return d.join(load(spark, sf_dir, "labels"), "doc_id", "left_semi").groupBy("lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


def unlabelled_anti(spark, sf_dir):
    d = load(spark, sf_dir, "documents").select("doc_id", "lang", "n_chars")
    return d.join(load(spark, sf_dir, "labels"), "doc_id", "left_anti").groupBy("lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


def reference_cdf():
    import numpy as np

    from driftks.operators.cdf import ApproxCdf

    x, lo, hi = (np.array(c) for c in zip(*REFERENCE, strict=True))
    return ApproxCdf(x, lo, hi, CdfPlan(1000, 0.1, 0.05, 21, "fixed"))


def _evaluated(spark, sf_dir, method):
    points = load(spark, sf_dir, "events").select("value").distinct()
    return eval_cdf(points, "value", reference_cdf(), "f", method).select("value", F.round("f", 9).alias("f"), F.round("f_left", 9).alias("f_left"))


def asof_eval(spark, sf_dir):
    return _evaluated(spark, sf_dir, "asof")


def range_join_eval(spark, sf_dir):
    return _evaluated(spark, sf_dir, "range_join")


def nested_eval(spark, sf_dir):
    return _evaluated(spark, sf_dir, "nested")


def broadcast_eval(spark, sf_dir):
    return _evaluated(spark, sf_dir, "broadcast")


def array_eval(spark, sf_dir):
    return _evaluated(spark, sf_dir, "array")


def attach_reference(spark, sf_dir):
    """Broadcast join of events with the stored reference of their feature."""
    refs = spark.createDataFrame([("click", 50.0), ("purchase", 60.0), ("view", 40.0)], "event_type string, reference double")
    e = load(spark, sf_dir, "events").join(F.broadcast(refs), "event_type")
    return e.groupBy("event_type").agg(F.count("*").alias("n"), F.count_if(F.col("value") > F.col("reference")).alias("over"))


def json_feature(spark, sf_dir):
    k = F.get_json_object("props", "$.k").cast("int")
    return load(spark, sf_dir, "events").groupBy("event_type").agg(F.count(k).alias("n"), F.sum(k).alias("total"), F.min(k).alias("low"), F.max(k).alias("high"))


def unpivot_profile(spark, sf_dir):
    from driftks.operators.samples import long_features

    rows = long_features(load(spark, sf_dir, "lineitem"), ["l_quantity", "l_extendedprice", "l_discount", "l_tax"], ["l_returnflag"])
    return rows.groupBy("l_returnflag", "feature").agg(F.count("*").alias("n"), F.min("value").alias("low"), F.max("value").alias("high"), F.round(F.avg("value"), 6).alias("mean"))


def session_features(spark, sf_dir):
    """Sessions of a user end after a day without an event: number of sessions and longest."""
    e = load(spark, sf_dir, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    s = e.groupBy("user_id", F.session_window("ts", "1 day")).agg(F.count("*").alias("c"))
    return s.groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("c").alias("longest"))


def tie_rate(spark, sf_dir):
    """How many rows share their value with another row, per column; decides between interpolation and the value histogram."""
    t = load(spark, sf_dir, "lineitem")
    out = None
    for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax"):
        part = t.agg(F.lit(c).alias("feature"), F.count(c).alias("n"), F.count_distinct(c).alias("distinct_values"))
        out = part if out is None else out.unionByName(part)
    return out


def hash_sample(spark, sf_dir):
    """A deterministic tenth of the orders, by plain modulo of the key."""
    return load(spark, sf_dir, "orders").where(F.col("o_orderkey") % 10 == 3).agg(F.count("*").alias("n"), F.round(F.avg("o_totalprice"), 6).alias("mean"))


def sorted_sample(spark, sf_dir):
    """A total order with nulls last, and its first rows."""
    c = load(spark, sf_dir, "customer").select("c_custkey", F.when(F.col("c_custkey") % 7 != 0, F.col("c_acctbal")).alias("balance"))
    return c.orderBy(F.col("balance").asc_nulls_last(), "c_custkey").limit(20)


def value_histogram(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").groupBy(F.col("l_quantity").alias("value")).agg(F.count_if(F.col("l_returnflag") == "R").alias("cx"), F.count_if(F.col("l_returnflag") == "N").alias("cy"))


def local_knots(values: list[float], grid: list[float], plan: CdfPlan):
    """A function from knots that are already on the driver."""
    return from_knots(grid, values, plan)
