"""Streams against their batch twins."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from strata_descent.streaming import stream


def test_windows_and_late_rows(spark, tmp_path):
    rows = [(i, f"2024-01-01 {i // 6:02d}:{i % 6 * 10:02d}:00", "a" if i % 2 else "b", float(i)) for i in range(60)]
    df = spark.createDataFrame(rows, "event_id int, t string, event_type string, value double").withColumn("ts", F.to_timestamp("t")).drop("t")
    source = str(tmp_path / "in")
    df.coalesce(1).write.parquet(source)
    query = stream.class_stats(stream.with_late(spark.readStream.schema(df.schema).parquet(source), "1 hour"), F.window("ts", "1 hour")).writeStream.format("memory").queryName("win").outputMode("complete").start()
    query.processAllAvailable()
    query.stop()
    live = {(r.start, r.event_type): (r.n_rows, r.sum_value) for r in spark.table("win").collect()}
    batch = {(r.start, r.event_type): (r.n_rows, r.sum_value) for r in stream.class_stats(df, F.window("ts", "1 hour")).collect()}
    assert live == batch


def test_rows_later_than_the_watermark_are_dropped(spark, tmp_path):
    """A row behind the watermark changes no window that is closed; one within the delay still counts."""
    schema = "event_id int, ts timestamp, event_type string, value double"
    source = tmp_path / "in"
    make = lambda rows: spark.createDataFrame([(i, t) for i, t in rows], "event_id int, t string").select("event_id", F.to_timestamp("t").alias("ts"), F.lit("a").alias("event_type"), F.lit(1.0).alias("value"))
    first = [(1, "2024-01-01 00:10:00"), (2, "2024-01-01 05:00:00")]
    late = [(3, "2024-01-01 00:20:00"), (4, "2024-01-01 04:30:00"), (5, "2024-01-01 09:00:00")]
    make(first).coalesce(1).write.mode("append").parquet(str(source))
    query = stream.class_stats(stream.with_late(spark.readStream.schema(schema).parquet(str(source)), "1 hour"), F.window("ts", "1 hour")).writeStream.format("memory").queryName("late").outputMode("append")
    live = query.start()
    live.processAllAvailable()
    make(late).coalesce(1).write.mode("append").parquet(str(source))
    live.processAllAvailable()
    make([(6, "2024-01-01 20:00:00")]).coalesce(1).write.mode("append").parquet(str(source))
    live.processAllAvailable()
    live.stop()
    got = {r.start.hour: r.n_rows for r in spark.table("late").collect()}
    assert got[0] == 1 and got[4] == 1 and got[5] == 1


def test_reservoir_keeps_the_least_priorities(spark, tmp_path):
    df = spark.range(200).select((F.col("id") % 3).cast("int").alias("stratum"), F.col("id").alias("row_id"), (F.col("id") * 7919 % 1009).alias("priority"))
    source = str(tmp_path / "in")
    df.repartition(2).write.parquet(source)
    query = stream.reservoir(spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(source), 5).writeStream.format("memory").queryName("res").outputMode("update").start()
    query.processAllAvailable()
    query.stop()
    for s in range(3):
        best = [r.priority for r in df.where(F.col("stratum") == s).orderBy("priority").limit(5).collect()]
        # the state's last word on a stratum is among the updates
        assert set(best) <= {r.priority for r in spark.table("res").where(F.col("stratum") == s).collect()}


def test_online_step_is_the_weighted_gradient(spark):
    sink = stream.OnlineDescent({0: np.array([[0.0]]), 1: np.array([[1.0]])}, 2, 1, 0.1, lambda t: 0.5)
    batch = spark.createDataFrame([(1, 0, [0.0]), (2, 1, [1.0]), (3, 1, [2.0])], "row_id bigint, y int, x array<double>")
    sink(batch, 0)
    sink(batch, 0)  # delivered again: skipped
    assert sink.t == 1
    # residuals at W = 0 are 1/2 - onehot; each row weighs 1/3
    assert np.allclose(sink.w, -0.5 * np.array([[0.5 * 0 - 0 + 0.5 * 3 / 3], [-0.5 * 3 / 3]]))


def test_rate_stream_feeds_online_descent(spark):
    from strata_descent.sources.load import rate_examples

    sink = stream.OnlineDescent({c: np.zeros((1, 3)) for c in range(2)}, 2, 3, 0.01, lambda t: 0.5)
    query = rate_examples(spark, 3, 2, 200).writeStream.foreachBatch(sink).trigger(processingTime="1 second").start()
    import time

    until = time.time() + 40
    while sink.t < 3 and time.time() < until:
        time.sleep(0.5)
    query.stop()
    assert sink.t >= 2 and np.abs(sink.w).max() > 0 and sum(sink.seen.values()) >= 100
