"""Results of streams lie in files, whatever their size, and hold what was open at the end."""

from __future__ import annotations

from pyspark.sql import functions as F

from tracelake import registry, streaming

_MINUTE = 60_000_000


def test_bursts_come_from_files_and_close_at_the_end(spark, tmp_path):
    rows = [(1, "h", "read", "p:a", "f:x", 0, 1, 1), (2, "h", "read", "p:a", "f:x", 29 * _MINUTE, 1, 1), (3, "h", "read", "p:a", "f:x", 60 * _MINUTE, 1, 1), (4, "h", "read", "p:b", "f:x", 70 * _MINUTE, 1, 1)]
    events = spark.createDataFrame(rows, streaming.EVENT)
    events.unionByName(streaming.closed(events)).write.parquet(f"{tmp_path}/in")
    stream = streaming.with_time(spark.readStream.schema(streaming.EVENT).parquet(f"{tmp_path}/in"))
    got = streaming.run_to_end(streaming.bursts(stream), "closing_bursts")
    assert got.inputFiles()
    assert {(r.src_id, r.from_us, r.to_us, r.n) for r in got.collect()} == {("p:a", 0, 59 * _MINUTE, 2), ("p:a", 60 * _MINUTE, 90 * _MINUTE, 1), ("p:b", 70 * _MINUTE, 100 * _MINUTE, 1)}


def test_no_events_need_no_mark(spark):
    assert streaming.closed(spark.createDataFrame([], streaming.EVENT)).count() == 0


def test_given_bursts_hold_every_event_and_come_from_files(spark, data):
    got = registry.QUERIES["stream_bursts"](spark, data)
    assert got.inputFiles()
    assert got.agg(F.sum("n")).first()[0] == spark.read.parquet(f"{data}/events.parquet").count()


def test_rows_without_repeats_come_from_files(spark, tmp_path):
    events = spark.createDataFrame([(k % 5, "h", "read", "p:a", "f:x", k, k, 1) for k in range(10)], streaming.EVENT)
    events.write.parquet(f"{tmp_path}/in")
    got = streaming.run_to_end(streaming.once(streaming.with_time(spark.readStream.schema(streaming.EVENT).parquet(f"{tmp_path}/in"))), "once_rows")
    assert got.inputFiles() and sorted(r.event_id for r in got.collect()) == [0, 1, 2, 3, 4]
