"""Queries of the streaming operators and of ingest: the given events written as files and read as a stream."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from tracelake import plans, sources, streaming
from tracelake.model import oracle, views
from tracelake.model.store import merge_bursts, read_six
from tracelake.workloads import register

_SOME = "event_id, host, op, src_id, dst_id, start_us, end_us, amount"


def _stream(spark, sf_dir, twice: bool = False, closed: bool = False):
    folder = f"{plans.shared_dir(spark)}/tracelake/stream-{uuid.uuid4().hex}"
    events = views.events(spark, sf_dir).events.select(*_SOME.split(", "))
    events.write.parquet(folder)
    if twice:
        events.write.mode("append").parquet(folder)
    if closed:
        streaming.closed(spark.read.schema(streaming.EVENT).parquet(folder)).write.mode("append").parquet(folder)
    return streaming.with_time(spark.readStream.schema(streaming.EVENT).parquet(folder))


def _run(df, mode="append"):
    return streaming.run_to_end(df, f"s_{uuid.uuid4().hex[:12]}", mode)


@register("stream_rates", oracle.with_events("SELECT start_us // 3600000000 * 3600000000 AS from_us, host, op, count(*) AS n, CAST(sum(amount) AS BIGINT) AS amount FROM ev GROUP BY ALL"))
def stream_rates(spark, sf_dir):
    return _run(streaming.rates(_stream(spark, sf_dir)), "complete")


@register("stream_rates_sliding", oracle.with_events("SELECT w * 1800000000 AS from_us, host, op, count(*) AS n, CAST(sum(amount) AS BIGINT) AS amount FROM (SELECT start_us // 1800000000 - s AS w, host, op, amount FROM ev, range(0, 2) t(s)) GROUP BY ALL"))
def stream_rates_sliding(spark, sf_dir):
    return _run(streaming.rates(_stream(spark, sf_dir), "1 hour", "30 minutes"), "complete")


@register("stream_once", oracle.with_events("SELECT count(*) AS n, CAST(sum(event_id) AS BIGINT) AS total FROM ev"))
def stream_once(spark, sf_dir):
    return _run(streaming.once(_stream(spark, sf_dir, twice=True)).select("event_id")).agg(F.count(F.lit(1)).alias("n"), F.sum("event_id").alias("total"))


@register("stream_bursts", oracle.with_events("SELECT src_id, min(start_us) AS from_us, max(start_us) + 1800000000 AS to_us, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY src_id ORDER BY start_us) AS s FROM (SELECT *, CASE WHEN start_us - lag(start_us) OVER (PARTITION BY src_id ORDER BY start_us) < 1800000000 THEN 0 ELSE 1 END AS new FROM ev)) GROUP BY src_id, s"))
def stream_bursts(spark, sf_dir):
    return _run(streaming.bursts(_stream(spark, sf_dir, closed=True)))


@register("stream_pair", oracle.with_events("SELECT a.event_id AS e0, b.event_id AS e1, a.dst_id AS node FROM ev a JOIN ev b ON a.dst_id = b.src_id WHERE a.op = 'read' AND b.op = 'sendto' AND b.start_us >= a.start_us AND b.start_us < a.start_us + 3600000000"))
def stream_pair(spark, sf_dir):
    return _run(streaming.standing_pair(_stream(spark, sf_dir), "read", "sendto", "1 HOUR"))


@register("stream_online_forward", oracle.with_events(
    "SELECT DISTINCT host, event_id FROM r WHERE event_id IS NOT NULL", "t_mark AS (SELECT (max(start_us) // 1000 - 3600000) * 1000 AS mark FROM ev)", "use_ AS (SELECT ev.* FROM ev, t_mark WHERE end_us <= mark)",
    "t_seed AS (SELECT min(dst_id) AS node, (SELECT min(start_us) FROM ev) AS t0 FROM ev WHERE op = 'read')",
    "r(host, event_id, n, b) AS (SELECT h.host, CAST(NULL AS BIGINT), node, t0 FROM t_seed, (SELECT DISTINCT host FROM ev) h UNION SELECT r.host, x.event_id, x.dst_id, x.start_us FROM r JOIN use_ x ON x.host = r.host AND x.src_id = r.n AND x.end_us > r.b)", recursive=True,
))
def stream_online_forward(spark, sf_dir):
    e = views.events(spark, sf_dir).events
    node = e.where("op = 'read'").agg(F.min("dst_id")).first()[0]
    return _run(streaming.online_forward(_stream(spark, sf_dir), {node: e.agg(F.min("start_us")).first()[0]}))


@register("ingest_lines", oracle.with_events("SELECT event_id, start_us AS seen_us, host, split_part(subject_id, ':', 4) AS pid, op, object_id AS object, amount, end_us - start_us AS duration_us FROM ev").replace("split_part(subject_id, ':', 4) AS pid", "CAST(split_part(subject_id, ':', 4) AS BIGINT) AS pid").replace("SELECT event_id, start_us AS seen_us", "SELECT start_us AS seen_us"))
def ingest_lines(spark, sf_dir):
    lines = sources.to_lines(views.events(spark, sf_dir).events)
    return sources.parse_syscall_lines(lines).select("seen_us", "host", "pid", "op", "object", "amount", "duration_us")


@register("ingest_six_tables", oracle.with_events("SELECT category, count(*) AS n, CAST(sum(amount) AS BIGINT) AS amount FROM ev GROUP BY 1"))
def ingest_six_tables(spark, sf_dir):
    folder = f"{plans.shared_dir(spark)}/tracelake/six-{uuid.uuid4().hex}"
    views.events(spark, sf_dir).write_six(folder)
    return read_six(spark, folder).events.groupBy("category").agg(F.count(F.lit(1)).alias("n"), F.sum("amount").alias("amount"))


@register("model_bursts", oracle.with_events("SELECT src_id, dst_id, op, min(start_us) AS start_us, max(end_us) AS end_us, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY src_id, dst_id, op ORDER BY start_us, event_id) AS burst FROM (SELECT *, CASE WHEN start_us - max(end_us) OVER (PARTITION BY src_id, dst_id, op ORDER BY start_us, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) <= 86400000000 THEN 0 ELSE 1 END AS new FROM ev)) GROUP BY src_id, dst_id, op, burst"))
def model_bursts(spark, sf_dir):
    return merge_bursts(views.events(spark, sf_dir).events, 86_400_000_000).select("src_id", "dst_id", "op", "start_us", "end_us", "n")
