import numpy as np
from pyspark.sql import functions as F

import __spark_entry__ as entry
from fsketch.plans import relational
from fsketch.plans.pipeline import cluster
from fsketch.sources import io
from fsketch.sources.workloads import load
from fsketch.streaming import windows


def test_stream_equals_batch_and_restarts(spark, sf, tmp_path):
    w = windows.frequencies(2)
    rows = windows.windowed(windows.events(spark, f"{sf}/events.parquet"), w)
    live = {r.start: (r.n, round(r.re0, 9)) for r in windows.run_to_memory(rows, checkpoint=str(tmp_path / "c")).collect()}
    batch = windows.windowed(io.table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")), w)
    assert live == {r.start: (r.n, round(r.re0, 9)) for r in batch.collect()}
    assert windows.drift(batch, w).where("mismatch is not null").count() == len(live) - 1


def test_late_rows_and_batches(spark, sf, tmp_path):
    seen = []
    tracker = windows.CentroidTracker(np.array([[10.0], [90.0]]), ["value"])
    windows.run_batches(windows.events(spark, f"{sf}/events.parquet"), lambda df, i: (seen.append(df.count()), tracker(df, i)), str(tmp_path / "b"))
    assert sum(seen) == 1000 and tracker.weights.sum() == 1000
    rows = windows.windowed(windows.events(spark, f"{sf}/events.parquet"), windows.frequencies(1))
    windows.run_to_files(rows, str(tmp_path / "out"), str(tmp_path / "c2"))
    done = spark.read.parquet(str(tmp_path / "out")).count()
    assert 0 < done  # windows that the watermark has closed


def test_stateful_sample(spark, sf):
    got = windows.run_to_memory(windows.bottom_sample(windows.events(spark, f"{sf}/events.parquet"), 5), "update")
    per = got.groupBy("hour_bucket").count().collect()
    assert per and all(r["count"] == 5 for r in per)


def test_model_card(spark, sf, tmp_path):
    r = cluster(load(spark, sf, "W8"), 3, solver="grouped_exact", seed_iters=2)
    io.write_model(spark, str(tmp_path / "m"), r)
    assert np.allclose(io.read_model(spark, str(tmp_path / "m"))["centroids"], r.centroids)


def test_entry(spark):
    rows = entry.entry(spark).collect()
    assert len(rows) == 3 and sum(r.n for r in rows) == 200
    assert set(entry.oracle_sql()) <= set(entry.queries())


def plan_of(df):
    return df._jdf.queryExecution().analyzed().toString()


def test_stream_dedup_leaves_rows_in_files(spark, sf):
    """What grows with the rows is in files of the tasks, not in a table of the driver's memory."""
    got = relational.Q["ops_stream_dedup"][0](spark, sf)
    assert got.inputFiles() and "MemoryPlan" not in plan_of(got)
    assert sum(r.n for r in got.collect()) == 1000
    assert windows.run_to_table(windows.events(spark, f"{sf}/events.parquet").where("event_id < 0")).count() == 0


def test_stream_sessions_leave_rows_in_files(spark, sf):
    got = relational.Q["ops_stream_session"][0](spark, sf)
    assert got.inputFiles() and "MemoryPlan" not in plan_of(got)
    assert sum(r.n * r.sessions for r in got.collect()) == 1000
    none = windows.sessions(windows.events(spark, f"{sf}/events.parquet").where("event_id < 0")).select("user_id", "n")
    assert windows.run_to_table(none, "complete").count() == 0
