"""Samples: one numeric column of a DataFrame, cleaned of missing values."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from driftks.functions.scalars import as_double


def _column(df: DataFrame, column: str | Column) -> Column:
    expr = F.col(column) if isinstance(column, str) else column
    return as_double(df.select(expr.alias("c")).schema["c"].dataType, expr)


@dataclass(frozen=True)
class Sample:
    """A bag of numbers: a column (or expression) of ``df``, optionally filtered."""

    df: DataFrame
    column: str | Column
    where: str | Column | None = None
    label: str = ""

    def raw(self) -> DataFrame:
        """One DOUBLE column ``value``, missing values included; filter and projection reach the scan."""
        df = self.df if self.where is None else self.df.where(self.where)
        return df.select(_column(df, self.column).alias("value"))

    def values(self) -> DataFrame:
        """``value`` without null and NaN."""
        return self.raw().where(F.col("value").isNotNull() & ~F.isnan("value"))

    def persist(self) -> Sample:
        """A sample whose cleaned values are cached; for use when several passes follow."""
        return Sample(self.values().persist(), "value", None, self.label)


def clean(df: DataFrame, column: str) -> tuple[DataFrame, DataFrame]:
    """``df`` without rows whose ``column`` is null or NaN, and the one-row count of what was ``kept`` and ``dropped``."""
    value = _column(df, column)
    there = value.isNotNull() & ~F.isnan(value)
    counts = df.agg(F.count_if(there).alias("kept"), F.count_if(~there | value.isNull()).alias("dropped"))
    return df.where(there), counts


def tagged(ref: Sample, test: Sample) -> DataFrame:
    """Both samples in one table: ``side`` ('x' for the reference, 'y' for the test sample) and ``value``."""
    return ref.values().select(F.lit("x").alias("side"), "value").unionAll(test.values().select(F.lit("y").alias("side"), "value"))


@dataclass(frozen=True)
class Profile:
    """What one pass over a pair of samples tells."""

    n: int
    m: int
    dropped_x: int
    dropped_y: int
    distinct: int


def profile_pair(ref: Sample, test: Sample, distinct: bool = True) -> Profile:
    """Sizes, missing values and, on request, the approximate distinct count of a pair, in one job."""
    both = ref.raw().select(F.lit(True).alias("x"), "value").unionAll(test.raw().select(F.lit(False).alias("x"), "value"))
    fine = F.col("value").isNotNull() & ~F.isnan("value")
    row = both.agg(F.count_if(fine & F.col("x")), F.count_if(fine & ~F.col("x")), F.count_if(~F.coalesce(fine, F.lit(False)) & F.col("x")), F.count_if(~F.coalesce(fine, F.lit(False)) & ~F.col("x")), F.approx_count_distinct(F.when(fine, F.col("value"))) if distinct else F.lit(0)).first()
    return Profile(*row)


def profile(sample: Sample) -> DataFrame:
    """One row: ``n``, ``dropped``, ``low``, ``high`` and the approximate number of distinct values."""
    fine = F.col("value").isNotNull() & ~F.isnan("value")
    value = F.when(fine, F.col("value"))
    return sample.raw().agg(F.count(value).alias("n"), (F.count("*") - F.count(value)).alias("dropped"), F.min(value).alias("low"), F.max(value).alias("high"), F.approx_count_distinct(value).alias("distinct_about"))


def slices(df: DataFrame, key: Column, k: int) -> DataFrame:
    """Add ``slice``, 0 to k-1, by plain modulo of an integer key: ``k`` replications in one scan."""
    return df.withColumn("slice", F.pmod(key, F.lit(k)).cast("int"))


def long_features(df: DataFrame, features: list[str], keys: list[str]) -> DataFrame:
    """One row a value: ``keys``, ``feature`` and ``value`` (DOUBLE), without missing values."""
    cast = df.select(*keys, *(_column(df, c).alias(c) for c in features))
    return cast.unpivot(keys, features, "feature", "value").where(F.col("value").isNotNull() & ~F.isnan("value"))


def subsample(df: DataFrame, fraction: float, key: Column | None = None, seed: int = 1) -> DataFrame:
    """A Bernoulli sample; with a key, the same rows on every run and cluster."""
    if key is None:
        return df.sample(fraction, seed)
    return df.where(F.pmod(F.xxhash64(F.lit(seed), key), F.lit(1 << 30)) < int(fraction * (1 << 30)))


def stratified(df: DataFrame, stratum: str, fractions: dict, seed: int = 1) -> DataFrame:
    """A sample with its own fraction for each value of ``stratum`` (values without one are left out)."""
    return df.sampleBy(stratum, fractions, seed)


def is_supported(kind: T.DataType) -> bool:
    """Whether a column of this type can be a sample as it is."""
    try:
        as_double(kind, F.lit(None))
    except TypeError:
        return False
    return True
