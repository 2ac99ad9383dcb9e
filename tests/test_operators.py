"""Joins against plain loops; sources; a stream gives what the batch gives."""

from __future__ import annotations

import random

from pyspark.sql import functions as F

from tracelake import operators as O  # noqa: N812
from tracelake import sources


def _two(spark):
    rng = random.Random(1)
    a = [(i, rng.randrange(3), rng.randrange(100), rng.randrange(1, 30)) for i in range(40)]
    b = [(i, rng.randrange(3), rng.randrange(100), rng.randrange(1, 30)) for i in range(40)]
    left = spark.createDataFrame([(i, k, t, t + d) for i, k, t, d in a], "a long, k long, at long, a_to long")
    right = spark.createDataFrame([(i, k, t, t + d) for i, k, t, d in b], "b long, k long, bt long, b_to long")
    return a, b, left, right


def test_joins(spark):
    a, b, left, right = _two(spark)
    pairs = lambda df: sorted((r.a, r.b) for r in df.collect())
    for ordered in (True, False):
        want = sorted((x[0], y[0]) for x in a for y in b if x[1] == y[1] and (0 <= y[2] - x[2] < 7 if ordered else abs(y[2] - x[2]) < 7))
        assert pairs(O.band_join(left, right, ["k"], "at", "bt", 7, ordered)) == want
    want = sorted((x[0], y[0]) for x in a for y in b if x[1] == y[1] and x[2] <= y[2] + y[3] and y[2] <= x[2] + x[3])
    assert pairs(O.overlap_join(left, right, "k", ("at", "a_to"), ("bt", "b_to"), 10)) == want
    want = sorted((x[0], y[0]) for x in a for y in b if x[1] == y[1])
    assert pairs(O.salted_join(left, right, "k", 5, F.col("a"))) == want
    got = {r.a: r.last for r in O.as_of_join(left, right, "k", "at", "bt", "bt", "last").collect()}
    assert got == {x[0]: max((y[2] for y in b if y[1] == x[1] and y[2] < x[2]), default=None) for x in a}


def test_lines(spark):
    rows = spark.createDataFrame([("170 host1 webd(12) read f:host1:/a res=5 latency=3",), ("nonsense",), ("",)], "value string")
    got = sources.parse_syscall_lines(rows).collect()
    assert (got[0].seen_us, got[0].exe_name, got[0].pid, got[0].op, got[0].amount, got[0].duration_us, got[0].rest) == (170, "webd", 12, "read", 5, 3, None)
    assert got[1].rest == "nonsense" and got[1].op is None


def test_monitor_rows(spark):
    rows = spark.createDataFrame([('5,h,word,7,ReadFile,/x,"{""Length"": 9, ""Duration"": 2}"',), ("6,h,word,7,Process Exit,self,",)], "value string")
    got = sources.parse_monitor_csv(rows).collect()
    assert (got[0].op, got[0].amount, got[0].duration_us) == ("read", 9, 2)
    assert (got[1].op, got[1].amount) == ("end", 0)


def test_log_source(spark, tmp_path):
    (tmp_path / "a.log").write_text("1 h x(2) read f:1 res=3\nbad\n")
    spark.dataSource.register(sources.AuditLogSource)
    assert [tuple(r) for r in spark.read.format("auditlog").option("path", str(tmp_path)).load().collect()] == [(1, "h", "x", 2, "read", "f:1", 3, 0)]


def test_written_tables_can_be_removed(spark):
    from pathlib import Path

    from tracelake import plans

    df = plans.pin(spark.range(3))
    path = Path(plans._written[-1].removeprefix("file://"))
    assert df.count() == 3 and path.exists()
    kept, plans._written[:] = plans._written[:-1], plans._written[-1:]
    plans.cleanup(spark)
    plans._written[:] = kept
    assert not path.exists()


def test_size_of_inputs(spark, data):
    from tracelake import plans

    df = spark.read.parquet(f"{data}/lineitem.parquet")
    assert plans.input_bytes(df) > 10_000
    assert plans.up_to(df, 10) is None and plans.up_to(df, 10**6, bytes_=10) is None
    assert plans.up_to(df, 10**6).count() == df.count()


def test_relational_source_reads_ranges_and_pushes_filters(spark, tmp_path):
    url = f"jdbc:derby:{tmp_path}/store;create=true"
    rows = [(k, f"p{k % 3}") for k in range(100)] + [(None, "none")]
    spark.createDataFrame(rows, "event_id long, name string").write.mode("append").option("driver", "org.apache.derby.jdbc.EmbeddedDriver").option("createTableColumnTypes", "name VARCHAR(20)").jdbc(url, "edges")
    read = lambda **o: sources.read_jdbc(spark, url, "edges", driver="org.apache.derby.jdbc.EmbeddedDriver", **o)
    split = read(column="event_id", parts=4)
    assert split.rdd.getNumPartitions() == 4 and {tuple(r) for r in split.collect()} == set(rows) and split.count() == 101
    assert read().count() == 101 and read(columns=["name"]).columns == ["name"]
    picked = split.where("name = 'p1'")
    assert picked.count() == 33
    assert "EqualTo(name,p1)" in picked._jdf.queryExecution().toString().replace(", ", ",")


def test_last_three_of_each_user_whatever_the_partitions(spark, tmp_path):
    from tracelake import registry

    rows = [(k, 1 + k % 7, (k * 7919) % 10_007) for k in range(5000)] + [(5000, None, 5)]
    events = spark.createDataFrame(rows, "event_id long, user_id long, t long")
    events = events.select("event_id", "user_id", F.lit("view").alias("event_type"), F.lit(1.0).alias("value"), F.timestamp_micros("t").cast("timestamp_ntz").alias("ts"), F.lit('{"k": 1}').alias("props"))
    events.repartition(8).write.parquet(f"{tmp_path}/events.parquet")
    got = {(r.user_id, r.event_id) for r in registry.QUERIES["op_join_lateral_sql"](spark, str(tmp_path)).collect()}
    want = {(u, e) for u in {r[1] for r in rows} for e, _ in sorted(((r[0], r[2]) for r in rows if r[1] == u), key=lambda x: (-x[1], x[0]))[:3]}
    assert got == want
