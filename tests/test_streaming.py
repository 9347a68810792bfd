import datetime as dt

import pytest
from pyspark.sql import functions as F

from driftks import streaming
from driftks.operators.exact import signed_distance
from driftks.sources import event_stream

SCHEMA = "event_id long, ts timestamp, value double, user_id long"


def write(spark, folder, rows):
    spark.createDataFrame(rows, SCHEMA).coalesce(1).write.mode("append").parquet(folder)


def test_late_rows_are_dropped(spark, tmp_path):
    folder, check = str(tmp_path / "in"), str(tmp_path / "check")
    day = dt.datetime(2024, 1, 1)
    write(spark, folder, [(i, day + dt.timedelta(days=i), 1.0, 1) for i in range(20)])
    s = streaming.with_lateness(event_stream(spark, folder, SCHEMA), "1 day").groupBy(F.window("ts", "1 day")).count()

    def run():
        q = s.writeStream.format("noop").outputMode("append").option("checkpointLocation", check).trigger(availableNow=True).start()
        q.awaitTermination()
        return sum(o["numRowsDroppedByWatermark"] for p in q.recentProgress for o in p["stateOperators"])

    assert run() == 0
    write(spark, folder, [(100, day, 1.0, 1), (101, day + dt.timedelta(days=25), 1.0, 1)])
    assert run() == 1


def test_removals_undo_insertions(spark, tmp_path):
    streaming.use_rocksdb(spark)
    folder = str(tmp_path / "signed")
    kind = "key string, side string, value double, sign int"
    first = [("k", "x", float(v), 1) for v in range(10)] + [("k", "y", float(v), 1) for v in range(5, 25)]
    second = [("k", "y", float(v), -1) for v in range(15, 25)] + [("k", "x", 3.0, 1)]
    for part in (first, second):
        spark.createDataFrame(part, kind).coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema(kind).option("maxFilesPerTrigger", 1).parquet(folder)
    truth = signed_distance(spark.createDataFrame(first + second, kind)).first()
    changes = streaming.run_to_folder(streaming.incremental(stream), str(tmp_path / "native"), "update")
    got = streaming.incremental_distance(changes).first()
    assert (got["n"], got["m"]) == (11, 10) and got["d"] == pytest.approx(truth["d"])
    out = streaming.run_to_folder(streaming.small_incremental(stream), str(tmp_path / "small"), "update").collect()
    last = [r for r in out if (r.n, r.m) == (11, 10)]
    assert last and last[0].d == pytest.approx(truth["d"])


def test_a_query_that_is_started_again_goes_on(spark, tmp_path):
    """Restart from a checkpoint: state is kept, rows are read once, and complete, append and update results agree with a batch."""
    folder, day = str(tmp_path / "in"), dt.datetime(2024, 1, 1)
    sums = lambda s: s.groupBy("user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    parts = [[(10 * p + i, day, float(i), i % 3) for i in range(10)] for p in range(3)]
    for p, rows in enumerate(parts):
        write(spark, folder, rows)
        stream = event_stream(spark, folder, SCHEMA)
        want = sorted(map(tuple, sums(spark.read.parquet(folder)).collect()))
        complete = streaming.run_to_folder(sums(stream), str(tmp_path / "complete"))
        assert sorted(map(tuple, complete.collect())) == want
        update = streaming.run_to_folder(sums(stream), str(tmp_path / "update"), "update")
        latest = update.groupBy("user_id").agg(F.max_by("n", "batch"), F.max_by("total", "batch"))
        assert sorted(map(tuple, latest.collect())) == want
        append = streaming.run_to_folder(stream.select("event_id"), str(tmp_path / "append"), "append")
        assert sorted(r[0] for r in append.collect()) == sorted(10 * k + i for k in range(p + 1) for i in range(10))
    q = streaming.parquet_sink(event_stream(spark, folder, SCHEMA), str(tmp_path / "files"), str(tmp_path / "check"), ["user_id"]).trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.read.parquet(str(tmp_path / "files")).count() == 30


def test_live_samples_tell_their_distance(spark, tmp_path):
    folder = str(tmp_path / "in")
    rows = [(i, dt.datetime(2024, 1, 1 + i % 14), float(i % 97) + (40.0 if i % 14 >= 7 and i % 2 else 0.0), i % 2) for i in range(4000)]
    write(spark, folder, rows)
    s = event_stream(spark, folder, SCHEMA)
    pairs = streaming.run_to_folder(streaming.two_streams(s.where("user_id = 0"), s.where("user_id = 1"), "7 days"), str(tmp_path / "two"))
    for r in streaming.live_distance(pairs).collect():
        both = spark.read.parquet(folder).where((F.col("ts") >= r["start"]) & (F.col("ts") < r["start"] + dt.timedelta(days=7)))
        marked = both.select(F.when(F.col("user_id") == 0, "x").otherwise("y").alias("side"), "value", F.lit(1).alias("sign"))
        assert abs(r["d"] - signed_distance(marked).first()["d"]) < 0.03
    weeks = streaming.run_to_folder(streaming.weekly_knots(s), str(tmp_path / "weeks"))
    drifts = streaming.window_drift(weeks).collect()
    assert len(drifts) == weeks.count() - 1 and max(r["d_hat"] for r in drifts) > 0.15


def test_observed_metrics(spark):
    from pyspark.sql import Observation

    o = Observation("profile")
    df = spark.createDataFrame([(1.0,), (None,)], "value double")
    df.observe(o, F.count("*").alias("n_rows"), F.count_if(F.col("value").isNull()).alias("n_missing")).count()
    assert o.get == {"n_rows": 2, "n_missing": 1}
