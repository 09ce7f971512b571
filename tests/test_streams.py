"""Streams: late rows, restarts, state, online steps."""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from gradsift.sources import sinks
from gradsift.streaming import streams


def write(spark, path, rows):
    spark.createDataFrame(rows, "event_id long, ts string, event_type string, value double").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(path)


def source(spark, path):
    schema = "event_id long, ts timestamp, event_type string, value double"
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def test_rows_behind_the_watermark_are_dropped(spark, tmp_path):
    p, ck, out = (str(tmp_path / x) for x in ("in", "ck", "out"))

    def run():
        w = streams.stream_window_loss(source(spark, p), "tumbling", "1 hour", delay="1 hour").writeStream
        w.foreachBatch(streams.each_batch_once(out)).outputMode("append").option("checkpointLocation", ck).trigger(availableNow=True).start().awaitTermination()

    write(spark, p, [(1, "2024-01-01 00:10:00", "a", 1.0), (2, "2024-01-01 10:00:00", "a", 1.0)])
    run()
    write(spark, p, [(3, "2024-01-01 00:20:00", "a", 9.0)])  # late
    run()
    write(spark, p, [(4, "2024-01-02 10:00:00", "a", 1.0)])
    run()
    got = {str(r.start): r.n for r in spark.read.parquet(out).collect()}
    assert got["2024-01-01 00:00:00"] == 1 and got["2024-01-01 10:00:00"] == 1


def test_late_rows_are_counted(spark, tmp_path):
    p, ck, out = (str(tmp_path / x) for x in ("in", "ck", "out"))
    late = streams.LateRows()
    spark.streams.addListener(late)
    try:
        for rows in (
            [(1, "2024-01-01 00:10:00", "a", 1.0), (2, "2024-01-01 10:00:00", "a", 1.0)],
            [(3, "2024-01-01 00:20:00", "a", 9.0), (4, "2024-01-01 00:30:00", "b", 9.0), (5, "2024-01-01 10:30:00", "a", 1.0)],
        ):
            write(spark, p, rows)
            w = streams.stream_window_loss(source(spark, p), "tumbling", "1 hour", delay="1 hour").writeStream
            query = w.foreachBatch(streams.each_batch_once(out)).outputMode("append").option("checkpointLocation", ck).trigger(availableNow=True).start()
            query.awaitTermination()
        until = time.monotonic() + 60  # a listener hears of a batch some time after it
        while late.dropped.get(str(query.id)) != 2 and time.monotonic() < until:
            time.sleep(0.2)
    finally:
        spark.streams.removeListener(late)
    assert late.dropped == {str(query.id): 2}


def test_selection_is_the_same_after_a_restart(spark, tmp_path):
    p, ck, out = (str(tmp_path / x) for x in ("in", "ck", "out"))
    for k in range(3):
        write(spark, p, [(i, "2024-01-01 00:00:00", "a", float(i % 97)) for i in range(k * 100, k * 100 + 100)])
        chosen = streams.stream_select(streams.stream_rate(source(spark, p), F.col("value")), [25.0, 50.0, 75.0], "event_id")
        chosen.writeStream.foreachBatch(streams.each_batch_once(out)).option("checkpointLocation", ck).trigger(availableNow=True).start().awaitTermination()
    at_once = streams.drain(streams.stream_select(streams.stream_rate(source(spark, p), F.col("value")), [25.0, 50.0, 75.0], "event_id"))
    ids = lambda d: sorted(r.event_id for r in d.collect())
    assert ids(spark.read.parquet(out)) == ids(at_once) != []


def test_online_rater_is_replayable(spark, tmp_path):
    step = streams.online_rater(str(tmp_path), lambda b, mu: [mu[0] + b.count()], [0.0])
    batch = spark.range(5)
    step(batch, 0)
    step(batch, 1)
    step(batch, 1)
    assert spark.read.parquet(f"{tmp_path}/step=1").first()["mu"] == [10.0]


def test_source_sketch(spark, tmp_path):
    p = str(tmp_path / "in")
    spark.createDataFrame([("a", 1.0), ("a", 3.0), ("b", 2.0)], "source string, score double").coalesce(1).write.parquet(p)
    sdf = spark.readStream.schema("source string, score double").parquet(p)
    got = {r.source: (r.n, r.mean_score, r.best) for r in streams.drain(streams.stateful_source_sketch(sdf), "update").collect()}
    assert got == {"a": (2, 2.0, 3.0), "b": (1, 2.0, 2.0)}


def test_ratings_sink_prunes_bands(spark, tmp_path):
    ranked = spark.range(100).select(F.col("id").alias("doc_id"), (F.col("id") / 100).alias("pct"))
    sinks.write_ratings(ranked, str(tmp_path / "r"))
    late = sinks.read_ratings(spark, str(tmp_path / "r"), 0.25)
    assert late.count() == 75
    assert "PartitionFilters" in late._jdf.queryExecution().toString()
    sinks.export_subset(ranked, late, "doc_id", str(tmp_path / "s"), "json")
    assert spark.read.json(str(tmp_path / "s")).count() == 75
