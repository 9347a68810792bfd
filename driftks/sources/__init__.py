"""Where samples come from and where results go."""

from __future__ import annotations

import json
from pathlib import PurePosixPath

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from driftks.operators.cdf import ApproxCdf
from driftks.operators.samples import Sample
from driftks.plans.params import CdfPlan


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The Parquet table ``name`` below ``sf_dir``."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_samples(spark: SparkSession, path: str, fmt: str, schema: str | T.StructType | None = None, **options) -> DataFrame:
    """A scan of CSV, JSON, ORC, Parquet, text or another installed format. Without a schema, text formats take a second pass to infer one."""
    reader = spark.read.format(fmt).options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    elif fmt == "csv":
        reader = reader.option("inferSchema", True)
    return reader.load(path)


def sample_from_sql(spark: SparkSession, sql: str, column: str) -> Sample:
    return Sample(spark.sql(sql), column)


def sample_from_table(spark: SparkSession, name: str, column: str) -> Sample:
    """A catalog table or temporary view."""
    return Sample(spark.table(name), column)


def sample_from_jdbc(spark: SparkSession, url: str, table: str, column: str, partition_column: str, low, high, partitions: int, **options) -> Sample:
    """A JDBC table, read in ``partitions`` ranges of ``partition_column``."""
    reader = spark.read.format("jdbc").options(url=url, dbtable=table, partitionColumn=partition_column, lowerBound=low, upperBound=high, numPartitions=partitions, **options)
    return Sample(reader.load(), column)


def sample_from_rows(spark: SparkSession, rows) -> Sample:
    """An in-memory sample: numbers, a pandas Series or an Arrow array."""
    values = rows.to_pylist() if hasattr(rows, "to_pylist") else list(rows)
    return Sample(spark.createDataFrame([(None if v is None else float(v),) for v in values], "value double"), "value")


def generate(spark: SparkSession, dist: str, n: int, seed: int, partitions: int = 4, **params) -> Sample:
    """``n`` draws: ``normal`` (mean, sd), ``uniform`` (low, high), ``exponential`` (mean), ``gamma_half`` (shape 1/2, scale).

    Reproducible for a seed and a number of partitions.
    """
    rows = spark.range(0, n, 1, partitions)
    if dist == "normal":
        value = F.lit(params.get("mean", 0.0)) + F.lit(params.get("sd", 1.0)) * F.randn(seed)
    elif dist == "uniform":
        low, high = params.get("low", 0.0), params.get("high", 1.0)
        value = F.lit(low) + F.lit(high - low) * F.rand(seed)
    elif dist == "exponential":
        value = -F.lit(params.get("mean", 1.0)) * F.log1p(-F.rand(seed))
    elif dist == "gamma_half":  # half the square of a standard normal has shape one half
        value = F.lit(params.get("scale", 1.0) / 2) * F.pow(F.randn(seed), F.lit(2))
    else:
        raise ValueError(f"unknown distribution {dist!r}")
    return Sample(rows.select(value.alias("value")), "value", label=dist)


def time_slice(df: DataFrame, ts: str, start: str, end: str) -> DataFrame:
    """Rows with ``start`` <= ts < ``end``; prunes partitions and row groups where the layout allows."""
    return df.where((F.col(ts) >= F.lit(start).cast(df.schema[ts].dataType)) & (F.col(ts) < F.lit(end).cast(df.schema[ts].dataType)))


def event_stream(spark: SparkSession, folder: str, schema: T.StructType | str, max_files: int | None = None, ts: str = "ts") -> DataFrame:
    """A Parquet folder as a stream; ``ts`` as TIMESTAMP, so that it can carry a watermark."""
    reader = spark.readStream.schema(schema)
    if max_files:
        reader = reader.option("maxFilesPerTrigger", max_files)
    return reader.parquet(folder).withColumn(ts, F.col(ts).cast("timestamp"))


def rate_stream(spark: SparkSession, rows_per_second: int = 100) -> DataFrame:
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()


def save_cdf(cdf: ApproxCdf, spark: SparkSession, path: str, feature: str, run: str) -> None:
    """Store a distribution function: a few KB of knots and its plan, partitioned by feature and run."""
    rows = cdf.to_df(spark).withColumn("meta", F.lit(json.dumps({"n": cdf.plan.n, "delta": cdf.plan.delta, "eps": cdf.plan.eps, "a": cdf.plan.a, "split": cdf.plan.split, "tail": cdf.tail, "interp": cdf.interp})))
    rows = rows.withColumn("feature", F.lit(feature)).withColumn("run", F.lit(run))
    rows.coalesce(1).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("feature", "run").parquet(path)


def load_cdf(spark: SparkSession, path: str, feature: str, run: str) -> ApproxCdf:
    rows = spark.read.parquet(path).where((F.col("feature") == feature) & (F.col("run") == run)).orderBy("x").collect()
    if not rows:
        raise LookupError(f"no stored function for {feature!r}, run {run!r} in {PurePosixPath(path).name}")
    meta = json.loads(rows[0]["meta"])
    plan = CdfPlan(meta["n"], meta["delta"], meta["eps"], meta["a"], meta["split"])
    x, lo, hi = (np.array([r[k] for r in rows]) for k in ("x", "p_lo", "p_hi"))
    return ApproxCdf(x, lo, hi, plan, "jump", meta["tail"], meta["interp"])


def append_results(df: DataFrame, path: str, run_id: str) -> None:
    """Write results under ``run_id``; a run written again replaces itself, so retries are harmless."""
    df.withColumn("run_id", F.lit(run_id)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("run_id").parquet(path)
