"""Running sums over a sorted table without a task that sees all of it."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from driftks.plans.lineage import settled


def cumulative(df: DataFrame, keys: list[str], order: str, sums: list[str], partitions: int | None = None) -> DataFrame:
    """Add, for each column c of ``sums``, ``c_upto`` (the sum in ``order`` up to the row, inclusive) and ``c_all`` (of all rows), by ``keys``.

    Rows are dealt by ranges of (keys, order), so one key may span many tasks; sums of the earlier ranges of a key are added
    as offsets. Ties of ``order`` within a key should be one row. The ranged table is written, so that its ranges stay as they are.
    """
    parts = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = settled(df.repartitionByRange(parts, *keys, order).withColumn("__pid", F.spark_partition_id()))
    totals = ranged.groupBy(*keys, "__pid").agg(*(F.sum(c).alias(f"__t_{c}") for c in sums))
    earlier = Window.partitionBy(*keys).orderBy("__pid").rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy(*keys)
    before = [F.coalesce(F.sum(f"__t_{c}").over(earlier), F.lit(0)).alias(f"__b_{c}") for c in sums]
    every = [F.sum(f"__t_{c}").over(whole).alias(f"{c}_all") for c in sums]
    # a row for each range of each key
    offsets = totals.select(*(F.col(k).alias(f"__k_{k}") for k in keys), F.col("__pid").alias("__p"), *before, *every)
    same = F.col("__pid") == F.col("__p")
    for k in keys:
        same = same & F.col(k).eqNullSafe(F.col(f"__k_{k}"))
    inside = Window.partitionBy(*keys, "__pid").orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    met = ranged.join(offsets if keys else F.broadcast(offsets), same)
    upto = [(F.sum(c).over(inside) + F.col(f"__b_{c}")).alias(f"{c}_upto") for c in sums]
    return met.select(*df.columns, *upto, *(f"{c}_all" for c in sums))
