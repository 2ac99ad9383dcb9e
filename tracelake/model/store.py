"""A store of entities and events, its layouts on disk, and the join of both."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tracelake import plans
from tracelake.model import schema


@dataclass(frozen=True)
class TraceStore:
    """Entities and events as frames; both are plans until something is asked.

    ``copies`` are the events once more, clustered and sorted by an end (``dst_id``,
    ``src_id``), as ``ingested`` writes them.
    """

    entities: DataFrame
    events: DataFrame
    copies: dict[str, DataFrame] | None = None

    @property
    def spark(self) -> SparkSession:
        return self.events.sparkSession

    def host(self, *hosts: str) -> TraceStore:
        """Only the events of these hosts; entities without a host stay."""
        own = F.col("host").isin(*hosts)
        events = self.events.where(own)
        copies = {k: events if k == "of" else df.where(own) for k, df in self.copies.items()} if self._whole() else None
        return TraceStore(self.entities.where(F.col("host").isNull() | own), events, copies)

    def _whole(self) -> bool:
        """The copies are those of the events; they aren't once a store was made from this one with other events."""
        return self.copies is not None and self.copies["of"] is self.events

    def along(self, end: str) -> TraceStore:
        """The same store with its events read from the copy that is sorted by ``end``, where there is one."""
        return TraceStore(self.entities, self.copies[end]) if self._whole() else self

    def at_most(self, rows: int, bytes_: int = 4 * 2**30) -> bool:
        """An ingested store is known to hold at most so many events; large ones aren't counted."""
        return self._whole() and plans.input_bytes(self.events) <= bytes_ and self.events.count() <= rows

    def edges(self) -> DataFrame:
        return self.events.select(*schema.EDGE_COLUMNS)

    def as_graph(self) -> tuple[DataFrame, DataFrame]:
        """Nodes and edges of a property graph."""
        nodes = self.entities.withColumnRenamed("entity_id", "id")
        return nodes, self.events.withColumnRenamed("src_id", "src").withColumnRenamed("dst_id", "dst")

    def widen(self) -> DataFrame:
        """Events with the attributes of both ends (src_*, dst_*)."""
        out = self.events
        for end in ("src", "dst"):
            own = self.entities.select(*[F.col(c).alias(f"{end}_{c}") for c in schema.ENTITY_COLUMNS if c != "entity_id"], F.col("entity_id").alias("key_"))
            out = out.join(own, F.col(f"{end}_id") == F.col("key_"), "left").drop("key_")
        return out

    def write_six(self, folder: str) -> None:
        """Three entity and three event tables; events by host and day."""
        for kind in schema.KINDS:
            self.entities.where(F.col("kind") == kind).write.mode("overwrite").parquet(f"{folder}/entity_{kind}")
            own = self.events.where(F.col("category") == kind)
            own.write.mode("overwrite").partitionBy("host", "day").parquet(f"{folder}/event_{kind}")

    def write_adjacency(self, folder: str, buckets: int = 64) -> None:
        """Two copies of the edges, clustered and sorted by sink and by source, with bloom filters on the node.

        A backward round then reads row groups of its frontier's sinks, a forward
        round those of its sources. Only the frontier moves.
        """
        for key in ("dst_id", "src_id"):
            own = self.events.select(*schema.EDGE_COLUMNS, "op", "amount", "host", "day").repartition(buckets, key).sortWithinPartitions(key, "start_us")
            writer = own.write.mode("overwrite").option(f"parquet.bloom.filter.enabled#{key}", "true")
            writer.option(f"parquet.bloom.filter.expected.ndv#{key}", "100000").parquet(f"{folder}/by_{key}")

    def daily_summary(self) -> DataFrame:
        """Per (src_id, dst_id, day, op): number, first start, last end, amount. Prunes days and proves that nothing is reached."""
        return self.events.groupBy("src_id", "dst_id", "day", "op").agg(
            F.count(F.lit(1)).alias("n"), F.min("start_us").alias("first_us"), F.max("end_us").alias("last_us"), F.sum("amount").alias("amount")
        )


_ingested: dict[tuple, list[str]] = {}
_schemas: dict[tuple, tuple] = {}


def ingested(spark: SparkSession, name: str, sf_dir: str, make: Callable[[], TraceStore]) -> TraceStore:
    """The store of ``make``, written once for a state of the tables in ``sf_dir`` and only opened from then on.

    Events are dealt by day and sorted by start, so that bounds on time skip files and row
    groups; two copies are clustered and sorted by sink and by source. Partitions
    are balanced by size, so a node with a third of all events is split. ``name``
    must tell all that ``make`` depends on beside the tables.
    """
    key = (spark.sparkContext.applicationId, plans.shared_dir(spark), name, plans.state_of(spark, sf_dir))
    made = make() if key not in _ingested or not all(plans.exists(spark, p) for p in _ingested[key]) else None
    if made is not None:
        paths = [plans.write(made.entities, "entities"), plans.write(made.events.hint("rebalance", "day").sortWithinPartitions("start_us"), "events")]
        held = spark.read.schema(made.events.schema).parquet(paths[1])  # so that the source is asked once
        for end in ("dst_id", "src_id"):
            paths.append(plans.write(held.hint("rebalance", end).sortWithinPartitions(end, "start_us"), f"by_{end}"))
        _ingested[key], _schemas[key] = paths, (made.entities.schema, made.events.schema)
    entity_schema, event_schema = _schemas[key]
    paths = _ingested[key]
    entities = spark.read.schema(entity_schema).parquet(paths[0])
    events, by_sink, by_source = (spark.read.schema(event_schema).parquet(p) for p in paths[1:])
    return TraceStore(entities, events, {"of": events, "dst_id": by_sink, "src_id": by_source})


def read_six(spark: SparkSession, folder: str) -> TraceStore:
    entities = [spark.read.schema(schema.entity_schema()).parquet(f"{folder}/entity_{k}") for k in schema.KINDS]
    events = [spark.read.schema(schema.event_schema()).parquet(f"{folder}/event_{k}") for k in schema.KINDS]
    return TraceStore(entities[0].unionByName(entities[1]).unionByName(entities[2]), events[0].unionByName(events[1]).unionByName(events[2]))


def extract_entities(raw: DataFrame) -> DataFrame:
    """One row per entity from rows (entity columns and seen_us): each attribute as last seen."""
    rest = [c for c in schema.ENTITY_COLUMNS if c != "entity_id"]
    return raw.groupBy("entity_id").agg(*[F.max_by(c, F.when(F.col(c).isNotNull(), F.col("seen_us"))).alias(c) for c in rest])


def merge_bursts(events: DataFrame, gap_us: int) -> DataFrame:
    """Joins parallel edges of one operation whose pauses are at most ``gap_us``. Loses detail; off by default."""
    own = Window.partitionBy("src_id", "dst_id", "op").orderBy("start_us", "event_id")
    so_far = F.max("end_us").over(own.rowsBetween(Window.unboundedPreceding, -1))
    rows = events.withColumn("new", F.coalesce((F.col("start_us") - so_far > gap_us).cast("int"), F.lit(1)))
    rows = rows.withColumn("burst", F.sum("new").over(own.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return rows.groupBy("src_id", "dst_id", "op", "burst").agg(
        F.min("event_id").alias("event_id"), F.min("start_us").alias("start_us"), F.max("end_us").alias("end_us"), F.sum("amount").alias("amount"), F.count(F.lit(1)).alias("n")
    )


def quality(store: TraceStore) -> DataFrame:
    """Counts of orphan ends, ends before starts, unknown operations and repeated ids: check, n."""
    known = store.entities.select("entity_id")
    ends = store.events.select(F.explode(F.array("src_id", "dst_id")).alias("entity_id"))
    orphans = ends.join(known, "entity_id", "left_anti").agg(F.count(F.lit(1)).alias("n")).select(F.lit("orphan_ends").alias("check"), "n")
    ops = [o for group in schema.OPS.values() for o in group]
    one = store.events.agg(
        F.count_if(F.col("end_us") < F.col("start_us")).alias("end_before_start"), F.count_if(~F.col("op").isin(*ops)).alias("unknown_op")
    ).unpivot([], ["end_before_start", "unknown_op"], "check", "n")
    again = store.events.groupBy("event_id").count().where("count > 1").agg(F.count(F.lit(1)).alias("n")).select(F.lit("repeated_ids").alias("check"), "n")
    return orphans.unionByName(one).unionByName(again)
