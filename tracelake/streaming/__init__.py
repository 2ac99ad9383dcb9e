"""Streams of audit events: windows, repeats, standing patterns, online forward tracking."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from tracelake import plans

EVENT = "event_id bigint, host string, op string, src_id string, dst_id string, start_us bigint, end_us bigint, amount bigint"


def with_time(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """Adds event time and its watermark."""
    return stream.withColumn("at", F.timestamp_micros("start_us")).withWatermark("at", late)


def once(stream: DataFrame) -> DataFrame:
    """Without repeats of an event id within the watermark."""
    return stream.dropDuplicatesWithinWatermark(["event_id"])


def rates(stream: DataFrame, length: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Events and bytes by host, operation and window (tumbling, or sliding)."""
    window = F.window("at", length, slide) if slide else F.window("at", length)
    return stream.groupBy(window.alias("w"), "host", "op").agg(F.count(F.lit(1)).alias("n"), F.sum("amount").alias("amount")).select(F.unix_micros("w.start").alias("from_us"), "host", "op", "n", "amount")


def bursts(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Runs of a process's events without a pause of more than ``gap``."""
    own = F.session_window("at", gap)
    return stream.groupBy(own.alias("s"), "src_id").agg(F.count(F.lit(1)).alias("n")).select("src_id", F.unix_micros("s.start").alias("from_us"), F.unix_micros("s.end").alias("to_us"), "n")


def standing_pair(stream: DataFrame, first_op: str, second_op: str, within: str) -> DataFrame:
    """A standing two-step search: a flow into a node, then a flow out of it within a time; state ends with the watermark."""
    a = stream.where(F.col("op") == first_op).select(F.col("event_id").alias("e0"), F.col("dst_id").alias("node"), F.col("at").alias("at0"))
    b = stream.where(F.col("op") == second_op).select(F.col("event_id").alias("e1"), F.col("src_id").alias("node1"), F.col("at").alias("at1"))
    return a.join(b, (F.col("node") == F.col("node1")) & (F.col("at1") >= F.col("at0")) & (F.col("at1") < F.col("at0") + F.expr(f"INTERVAL {within}"))).select("e0", "e1", "node")


def online_forward(stream: DataFrame, seeds: dict[str, int], longest_us: int = 600_000_000) -> DataFrame:
    """Forward tracking on a stream, by host: events that depend on the seed nodes (node: from microseconds).

    Events wait until the watermark passes their end. A later event of long
    duration can still make an earlier one depend on the seeds, so those that were
    not taken are kept for ``longest_us``, the longest duration of an event. The
    state of a host is a bound per node reached and these events.
    """

    def step(key, batches, state: GroupState):
        bounds, rows = dict(seeds), []
        if state.exists:
            names, times, held = state.get
            bounds, rows = dict(zip(names, times)), [(int(e), s, d, int(a), int(b)) for e, s, d, a, b in (r.split("|") for r in held)]
        if not state.hasTimedOut:
            for pdf in batches:
                rows += list(zip(pdf.event_id.tolist(), pdf.src_id.tolist(), pdf.dst_id.tolist(), pdf.start_us.tolist(), pdf.end_us.tolist()))
        mark = state.getCurrentWatermarkMs() * 1000
        ready: dict[str, list] = {}
        for r in rows:
            if r[4] <= mark:
                ready.setdefault(r[1], []).append(r)
        found, queue = set(), list(bounds)
        while queue:
            node = queue.pop()
            for event, _, dst, start, end in ready.get(node, ()):
                if end > bounds[node] and event not in found:
                    found.add(event)
                    if start < bounds.get(dst, 2**62):
                        bounds[dst] = start
                        queue.append(dst)
        rows = [r for r in rows if r[0] not in found and r[4] > mark - longest_us]
        state.update((list(bounds), list(bounds.values()), ["|".join(map(str, r)) for r in rows]))
        later = [r[4] for r in rows if r[4] > mark]
        if later:
            state.setTimeoutTimestamp(max(min(later) // 1000 + 1, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"host": [key[0]] * len(found), "event_id": sorted(found)})

    return stream.groupBy("host").applyInPandasWithState(
        step, "host string, event_id bigint", "names array<string>, times array<bigint>, rows array<string>", "append", GroupStateTimeout.EventTimeTimeout
    )


def closed(events: DataFrame, wait_us: int = 7_200_000_000) -> DataFrame:
    """The mark that ends a stream: an event so long after the last one that the watermark passes all that is open.

    It is no event of any node and in the append mode it never comes out of a window, as nothing is later.
    """
    last = events.agg((F.max("start_us") + wait_us).alias("start_us")).where("start_us IS NOT NULL")
    own = {f.name: F.lit(None).cast(f.dataType) for f in events.schema.fields}
    return last.select(*[F.col("start_us") if n in ("start_us", "end_us") else c.alias(n) for n, c in own.items()]).toDF(*events.columns)


#: State of streams lies on the executors' disks: it has a row for each key that is open.
_STATE, _ON_DISK = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def run_to_end(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there.

    In the append mode rows of any number go to files of the shared folder. The complete
    mode gives a table in memory, for results of bounded size.
    """
    spark = stream.sparkSession
    folder = f"{plans.shared_dir(spark)}/tracelake/{name}-{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).queryName(name).trigger(availableNow=True)
    before = spark.conf.get(_STATE, None)
    spark.conf.set(_STATE, _ON_DISK)
    try:
        if mode == "append":
            query = writer.format("parquet").option("checkpointLocation", f"{folder}-state").start(folder)
        else:
            query = writer.format("memory").start()
        query.awaitTermination()
    finally:
        spark.conf.unset(_STATE) if before is None else spark.conf.set(_STATE, before)
    plans._written += [f"{folder}-state", folder] if mode == "append" else []
    return spark.read.schema(stream.schema).parquet(folder) if mode == "append" else spark.table(name)
