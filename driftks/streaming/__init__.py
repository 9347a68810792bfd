"""Monitors over Structured Streaming: windowed sketches, late data, stored references and changing multisets."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import IntegerType, StructField, StructType

from driftks.functions import significance as sig
from driftks.functions.scalars import cdf_at
from driftks.operators.cdf import ApproxCdf
from driftks.operators.drift import grouped_distance
from driftks.operators.kstest import against_cdf
from driftks.operators.quantiles import accuracy, collapsed_column
from driftks.operators.samples import Sample
from driftks.sketch import kll
from driftks.sources import append_results

PROBES = [i / 20 for i in range(21)]


def with_lateness(stream: DataFrame, delay: str, ts: str = "ts") -> DataFrame:
    """Rows later than ``delay`` behind the newest one are dropped by stateful operators (and counted in their progress)."""
    return stream.withWatermark(ts, delay)


def _knots(value: Column, eps: float) -> Column:
    return F.percentile_approx(value.cast("double"), PROBES, accuracy(eps))


def windowed_knots(stream: DataFrame, window: Column, value: str = "value", keys: tuple[str, ...] = (), eps: float = 0.001) -> DataFrame:
    """Count and quantiles of every window (and key): ``start``, ``end``, keys, ``n``, ``knots``."""
    out = stream.groupBy(window.alias("w"), *keys).agg(F.count(value).alias("n"), _knots(F.col(value), eps).alias("knots"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n", "knots")


def weekly_knots(stream: DataFrame, value: str = "value", ts: str = "ts", keys: tuple[str, ...] = ()) -> DataFrame:
    """Tumbling windows of seven days that begin on Mondays."""
    return windowed_knots(stream, F.window(ts, "7 days", startTime="4 days"), value, keys)


def sliding_knots(stream: DataFrame, length: str, step: str, value: str = "value", ts: str = "ts", keys: tuple[str, ...] = ()) -> DataFrame:
    """Sliding windows. A row enters length/step of them; for long windows merge daily sketches instead."""
    return windowed_knots(stream, F.window(ts, length, step), value, keys)


def session_knots(stream: DataFrame, gap: str, key: str, value: str = "value", ts: str = "ts") -> DataFrame:
    """Session windows of each key that end after ``gap`` without a row."""
    return windowed_knots(stream, F.session_window(ts, gap), value, (key,))


def daily_sketches(stream: DataFrame, value: str = "value", ts: str = "ts", keys: tuple[str, ...] = (), k: int = kll.K) -> DataFrame:
    """A mergeable sketch a day (and key): ``day``, keys, ``n``, ``sketch``."""
    days = stream.groupBy(F.window(ts, "1 day").alias("w"), *keys).agg(F.count(value).alias("n"), F.kll_sketch_agg_double(F.col(value).cast("double"), k).alias("sketch"))
    return days.select(F.col("w.start").alias("day"), *keys, "n", "sketch")


def merge_days(days: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """Daily sketches (batch) merged into one per key."""
    return kll.merged(days, list(keys))


def deduplicated(stream: DataFrame, key: str, delay: str, ts: str = "ts") -> DataFrame:
    """Rows whose ``key`` came before within the watermark are dropped."""
    return with_lateness(stream, delay, ts).dropDuplicatesWithinWatermark([key])


def observed(stream: DataFrame, name: str = "profile", value: str = "value") -> DataFrame:
    """Row and missing counts as metrics of each batch; no pass of their own."""
    return stream.observe(name, F.count("*").alias("n_rows"), F.count_if(F.col(value).isNull()).alias("n_missing"))


def two_streams(x: DataFrame, y: DataFrame, length: str, value: str = "value", ts: str = "ts", k: int = kll.K) -> DataFrame:
    """Two live samples in one windowed aggregate of a tagged union: ``start``, ``n``, ``m``, ``sx``, ``sy``."""
    both = x.select(ts, F.col(value).alias("value"), F.lit(True).alias("is_x")).unionAll(y.select(ts, F.col(value).alias("value"), F.lit(False).alias("is_x")))
    v = F.col("value").cast("double")
    out = both.groupBy(F.window(ts, length).alias("w")).agg(F.count_if("is_x").alias("n"), F.count_if(~F.col("is_x")).alias("m"), F.kll_sketch_agg_double(F.when(F.col("is_x"), v), k).alias("sx"), F.kll_sketch_agg_double(F.when(~F.col("is_x"), v), k).alias("sy"))
    return out.select(F.col("w.start").alias("start"), "n", "m", "sx", "sy")


def attach_reference(stream: DataFrame, references: DataFrame, feature: str = "feature") -> DataFrame:
    """Stream-static join: every row with the knots of its feature (a few KB each)."""
    return stream.join(F.broadcast(references), feature)


def monitor(stream: DataFrame, reference: ApproxCdf, out_path: str, checkpoint: str, value: str = "value", alpha: float = 0.05):
    """Test every micro-batch against a stored function; results are written by batch number, so a replay replaces them."""

    def test(batch: DataFrame, number: int) -> None:
        if not batch.isEmpty():
            append_results(against_cdf(reference, Sample(batch, value), alpha), out_path, f"batch{number}")

    return stream.writeStream.foreachBatch(test).option("checkpointLocation", checkpoint).trigger(availableNow=True)


def run_to_folder(stream: DataFrame, folder: str, mode: str = "complete", trigger: dict | None = None) -> DataFrame:
    """Process what is there, wait, and return what was written: ``folder`` gets the checkpoint and a table of each batch.

    ``complete``: the rows of the last batch; ``append``: all rows; ``update``: all rows with their ``batch``, the latest of a key
    counts. A batch that is run again replaces itself, and a query that is started again on the folder goes on where it stopped.
    Nothing passes through the driver.
    """

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out/batch={number}")

    query = stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").trigger(**(trigger or {"availableNow": True})).start()
    query.awaitTermination()
    spark = stream.sparkSession
    done = spark.read.schema(StructType([*stream.schema.fields, StructField("batch", IntegerType())])).option("basePath", f"{folder}/out").parquet(f"{folder}/out")
    if mode == "update":
        return done
    if mode == "append":
        return done.drop("batch")
    last = done.agg(F.max("batch")).first()[0]
    return done.where(F.col("batch") == F.lit(last)).drop("batch")


def console_sink(stream: DataFrame, mode: str = "complete", rows: int = 20):
    """A writer that prints each batch; for trying things out."""
    return stream.writeStream.format("console").outputMode(mode).option("numRows", rows)


def parquet_sink(stream: DataFrame, path: str, checkpoint: str, partition: list[str] | None = None):
    """A writer of appended Parquet files with exactly-once commits; needs a stream of final rows (append mode)."""
    out = stream.writeStream.format("parquet").outputMode("append").option("path", path).option("checkpointLocation", checkpoint)
    return out.partitionBy(*partition) if partition else out


def live_distance(pairs: DataFrame, k: int = kll.K) -> DataFrame:
    """Distance of the two live samples of every window (batch table ``start``, ``n``, ``m``, ``sx``, ``sy``): from sketches, no row is read again."""
    whole = pairs.agg(F.kll_merge_agg_double("sx").alias("sx"), F.kll_merge_agg_double("sy").alias("sy"))
    out = kll.distance(pairs.where("n > 0 and m > 0"), kll.probes_of(whole))
    return out.select("start", "n", "m", "d").withColumn("p_value", sig.p_value("d", "n", "m"))


def window_drift(windows: DataFrame) -> DataFrame:
    """Each window of ``windowed_knots`` (a batch table) against the one before, over their knots: ``start``, ``n``, ``n_before``, ``d_hat``."""
    jumped = windows.select("start", "n", collapsed_column(F.col("knots"), PROBES).alias("ks"))
    before = Window.orderBy("start")  # a row a window
    both = jumped.withColumn("kb", F.lag("ks").over(before)).withColumn("n_before", F.lag("n").over(before)).where("kb is not null")
    points = F.array_distinct(F.concat(F.transform("ks", lambda k: k["x"]), F.transform("kb", lambda k: k["x"])))
    gap = lambda x, left: F.abs(cdf_at(F.col("ks"), x, left) - cdf_at(F.col("kb"), x, left))
    return both.select("start", "n", "n_before", F.array_max(F.transform(points, lambda x: F.greatest(gap(x, False), gap(x, True)))).alias("d_hat"))


def incremental(stream: DataFrame, key: str = "key") -> DataFrame:
    """Net counts of every value under insertions and removals (rows: key, ``side`` 'x' or 'y', ``value``, ``sign`` +1 or -1).

    State is a row for each (key, value) in the state store of the task that its hash picks, so neither a frequent key nor a long history
    fills one; an ``update`` batch emits the values that changed. ``incremental_distance`` tells the distances.
    """
    net = lambda side: F.sum(F.when(F.col("side") == side, F.col("sign")).otherwise(0)).alias(f"c{side}")
    return stream.groupBy(key, F.col("value").cast("double").alias("value")).agg(net("x"), net("y"))


def incremental_distance(changes: DataFrame, key: str = "key") -> DataFrame:
    """Distance of each key from all changes so far (``batch``, key, ``value``, ``cx``, ``cy``): the latest counts of each value."""
    latest = changes.groupBy(key, "value").agg(F.max_by(F.struct("cx", "cy"), "batch").alias("c")).select(key, "value", "c.cx", "c.cy").where("cx <> 0 or cy <> 0")
    return grouped_distance(latest, [key])


class IncrementalKs(StatefulProcessor):
    """Keeps, for each key, both value histograms under insertions and removals, and emits the distance after each batch.

    Input rows: key, ``side`` ('x' or 'y'), ``value`` and ``sign`` (+1 or -1). State: one map from value to its two counts.
    """

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.counts = handle.getMapState("counts", "value double", "cx long, cy long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        for part in rows:
            part = part.assign(cx=part["sign"].where(part["side"] == "x", 0), cy=part["sign"].where(part["side"] == "y", 0))
            for value, c in part.groupby("value")[["cx", "cy"]].sum().iterrows():
                old = self.counts.getValue((float(value),)) or (0, 0)
                new = int(old[0] + c["cx"]), int(old[1] + c["cy"])
                if any(new):
                    self.counts.updateValue((float(value),), new)
                elif self.counts.containsKey((float(value),)):
                    self.counts.removeKey((float(value),))
        table = pd.DataFrame([(k[0], v[0], v[1]) for k, v in self.counts.iterator()], columns=["value", "cx", "cy"]).sort_values("value")
        n, m = int(table["cx"].sum()), int(table["cy"].sum())
        d = float((table["cx"].cumsum() / n - table["cy"].cumsum() / m).abs().max()) if n and m else None
        yield pd.DataFrame({"key": [key[0]], "n": [n], "m": [m], "d": [d]})

    def close(self) -> None:
        pass


def small_incremental(stream: DataFrame, key: str = "key") -> DataFrame:
    """Distance of each key after each batch of signed rows, for many keys with few distinct values each: a key's histogram is
    read whole at every batch (needs the RocksDB state store). ``incremental`` holds at any size."""
    out = "key string, n long, m long, d double"
    return stream.groupBy(key).transformWithStateInPandas(statefulProcessor=IncrementalKs(), outputStructType=out, outputMode="Update", timeMode="None")


def use_rocksdb(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
