"""Streams give what the batch gives, over several files and triggers, and drop rows beyond the watermark."""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from sparsegrid.streaming import streams as st


def _split(spark, sf, folder, parts=3):
    events = spark.read.parquet(f"{sf}/events.parquet").orderBy("ts")
    n = -(-events.count() // parts)
    numbered = events.withColumn("k", F.floor(F.monotonically_increasing_id() / n))
    for k in range(parts):
        numbered.where(F.col("k") == k).drop("k").coalesce(1).write.mode("append").parquet(folder)


def test_several_files(spark, sf, tmp_path):
    folder = str(tmp_path / "events.parquet")
    _split(spark, sf, folder)
    got = st.run_to_table(st.profile(st.stream_events(spark, folder, 1)))
    want = spark.read.parquet(f"{sf}/events.parquet").groupBy("user_id").agg(F.count("*").alias("nz"))
    assert sorted(got.collect()) == sorted(want.collect())


def test_late_rows_are_dropped(spark, tmp_path):
    folder = str(tmp_path / "events.parquet")
    rows = lambda times: spark.createDataFrame([(i, t, 1, "view", 1.0, "{}") for i, t in enumerate(times)], "event_id bigint, t string, user_id bigint, event_type string, value double, props string").selectExpr("event_id", "CAST(t AS TIMESTAMP_NTZ) AS ts", "user_id", "event_type", "value", "props").coalesce(1)
    for times in (["2024-01-01 00:10:00"], ["2024-01-03 00:00:00"], ["2024-01-03 00:01:00"], ["2024-01-01 00:20:00", "2024-01-03 00:05:00"]):
        rows(times).write.mode("append").parquet(folder)
        time.sleep(1.1)  # files are read in the order of their times; a watermark holds from the second trigger after it
    out = st.run_to_table(st.tumbling(st.stream_events(spark, folder, 1), "1 hour", late="1 hour"), "append")
    counts = {r.start: r.n for r in out.collect()}
    assert counts.get(1704067200) == 1, "the late row of the first hour is not counted"


def test_windows_close_once_and_late_events_are_counted(spark, tmp_path):
    rows = [[(0, 10, 1), (1, 20, 2), (2, 30, 1)], [(3, 130, 1), (4, 140, 3)], [(5, 40, 9), (6, 150, 1), (7, 260, 2), (8, 270, 5)]]
    for k, batch in enumerate(rows):
        df = spark.createDataFrame([(i, t, u) for i, t, u in batch], "event_id bigint, t bigint, user_id bigint")
        df.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        time.sleep(1.1 if k < 2 else 0)
    stream = spark.readStream.schema("event_id bigint, t bigint, user_id bigint").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    out, late = st.closed_windows(stream.withColumn("at", F.timestamp_seconds("t")), 100, 0, st.triangles_by_window)
    assert late == 1 and sorted(map(tuple, out.collect())) == [(0, 2, 0), (100, 2, 0), (200, 1, 0)]
