"""Reading the given tables and a few column conventions that the operators share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.plans.lineage import remove, settled, shared_folder  # noqa: F401  (operators take them from here)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The Parquet table ``name`` below ``sf_dir`` (any path that Spark's readers open)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def whole_text(text: str | Column) -> Column:
    """The text, with null read as the empty text."""
    return F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))


def parts(batches, rows: int = 256):
    """Arrow batches in parts of so many rows, so that Python holds the objects of one part at a time."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def bound(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of ``value``, which is worked out once however often, and in however deep a lambda, ``body`` uses it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def joined_unique(left: DataFrame, right: DataFrame, on: list[str], least: int = 100_000, parts: int = 10_000) -> DataFrame:
    """Left join with ``right``, whose keys ``on`` are unique, where a key may hold any share of ``left`` (a settled table).

    Keys are counted first (pre-aggregated). Those that hold more than 1/``parts`` of the rows, and more than ``least``
    rows, are ``parts`` at most: what they meet is broadcast and their rows stay where they are. The rest is joined as usual.
    """
    counts = left.groupBy(*on).agg(F.count("*").alias("__c"))
    heavy = counts.where(F.col("__c") > max(least, left.count() // parts)).drop("__c")
    heavy = left.sparkSession.createDataFrame(heavy.collect(), heavy.schema)  # ``parts`` rows at most
    if heavy.isEmpty():
        return left.join(right, on, "left")
    hot, met = F.broadcast(heavy), F.broadcast(right.join(F.broadcast(heavy), on, "left_semi"))
    apart = left.join(hot, on, "left_anti").join(right, on, "left")
    return left.join(hot, on, "left_semi").join(met, on, "left").unionByName(apart)
