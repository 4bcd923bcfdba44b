"""Streams against their batch twins, late and repeated rows, state, and lookups."""

import pytest
from pyspark.sql import functions as F

from optbst.streaming.weights import drift_refresher, event_stream, live_depths, once, running_counts, session_counts, sliding_counts, tumbling_counts

SCHEMA = "ts timestamp_ntz, event_type string, event_id long"


def rows_of(spark, hours):
    own = spark.createDataFrame([(i, float(h)) for i, h in enumerate(hours)], "event_id long, h double")
    return own.select(F.timestamp_seconds(F.col("h") * 3600).cast("timestamp_ntz").alias("ts"), (F.col("event_id") % 5).cast("string").alias("event_type"), "event_id")


@pytest.fixture()
def files(spark, tmp_path):
    """200 hourly events in four files, in order."""
    path = str(tmp_path / "in")
    for k in range(4):
        rows_of(spark, [float(h) for h in range(50 * k, 50 * k + 50)]).coalesce(1).write.mode("append").parquet(path)
    return path


def run(spark, df, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def batch(spark, path):
    return spark.read.schema(SCHEMA).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


@pytest.mark.parametrize("make,name", [(tumbling_counts, "tumbling"), (sliding_counts, "sliding"), (session_counts, "sessions")])
def test_streamed_windows_equal_batch(spark, files, make, name):
    got = run(spark, make(event_stream(spark, files, SCHEMA), "event_type"), name, "complete")
    want = make(batch(spark, files), "event_type")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) and got.count() > 0


def test_append_mode_emits_closed_windows_only(spark, files):
    got = run(spark, tumbling_counts(event_stream(spark, files, SCHEMA), "event_type"), "closed", "append")
    want = {tuple(r) for r in tumbling_counts(batch(spark, files), "event_type").collect()}
    assert 0 < got.count() < len(want) and {tuple(r) for r in got.collect()} <= want


def test_late_and_repeated_rows(spark, tmp_path):
    path = str(tmp_path / "in")
    for k, hours in enumerate(([0, 1, 2], [100, 101], [102], [3, 103], [104])):  # hour 3 comes a batch after the watermark has passed it
        rows_of(spark, hours).withColumn("event_id", F.col("event_id") + 10 * k).coalesce(1).write.mode("append").parquet(path)
        spark._jvm.java.lang.Thread.sleep(1100)  # files are read in order of their time
    s = event_stream(spark, path, SCHEMA)
    late = tumbling_counts(s, "event_type", late="1 day").writeStream.format("memory").queryName("late").outputMode("update").trigger(availableNow=True).start()
    late.awaitTermination()
    dropped = sum(op["numRowsDroppedByWatermark"] for p in late.recentProgress for op in p["stateOperators"])
    assert dropped == 1
    twice = str(tmp_path / "twice")
    rows_of(spark, [1.0, 2, 3]).coalesce(1).write.parquet(twice)
    rows_of(spark, [1.0, 2, 3, 4]).coalesce(1).write.mode("append").parquet(twice)
    assert sorted(r["event_id"] for r in run(spark, once(event_stream(spark, twice, SCHEMA), "event_id"), "once", "append").collect()) == [0, 1, 2, 3]


def test_state_and_lookups(spark, files):
    got = run(spark, running_counts(event_stream(spark, files, SCHEMA), "event_type"), "running", "update")
    last = {r["key"]: r["n"] for r in got.groupBy("key").agg(F.max("n").alias("n")).collect()}
    assert last == {str(k): 40 for k in range(5)} and got.count() > 5
    depths = spark.createDataFrame([("0", 1), ("1", 2), ("2", 2)], "key string, depth int")
    live = run(spark, live_depths(event_stream(spark, files, SCHEMA), "event_type", depths), "live", "append")
    assert {(r["event_type"], r["depth"], r["n"]) for r in live.groupBy("event_type", "depth").agg(F.count(F.lit(1)).alias("n")).collect()} == {("0", 1, 40), ("1", 2, 40), ("2", 2, 40), ("3", None, 40), ("4", None, 40)}


def test_drift(spark):
    trees = []
    refresh = drift_refresher(0.1, lambda depth, rows: trees.append(depth))
    refresh(spark.createDataFrame([("a", 5), ("b", 5), ("c", 5)], "key string, n long"), 0)
    refresh(spark.createDataFrame([("a", 5), ("b", 6), ("c", 5)], "key string, n long"), 1)
    refresh(spark.createDataFrame([("a", 500), ("b", 5), ("c", 5)], "key string, n long"), 2)
    refresh(spark.createDataFrame([], "key string, n long"), 3)
    assert len(trees) == 2 and trees[1]["a"] == 1
    with pytest.raises(ValueError):
        drift_refresher(0.1, lambda depth, rows: None, most_keys=2)(spark.createDataFrame([("a", 1), ("b", 1), ("c", 1)], "key string, n long"), 0)
