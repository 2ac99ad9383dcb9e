"""Results as graphs: set operations, refinement, sizes, display, export."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tracelake import plans
from tracelake.model import schema

#: Rows that a display brings to the driver.
SHOWN = 1000


@dataclass(frozen=True)
class TraceGraph:
    """A set of events (with a level where it came from a trace) over the entities of its store."""

    entities: DataFrame
    events: DataFrame

    @property
    def spark(self) -> SparkSession:
        return self.events.sparkSession

    def with_events(self, events: DataFrame) -> TraceGraph:
        return TraceGraph(self.entities, events)

    def edges(self) -> DataFrame:
        return self.events.select(*schema.EDGE_COLUMNS)

    def host(self, *hosts: str) -> TraceGraph:
        return self.with_events(self.events.where(F.col("host").isin(*hosts)))

    def nodes(self) -> DataFrame:
        """Entities that an event of the graph touches."""
        ends = self.events.select(F.explode(F.array("src_id", "dst_id")).alias("entity_id")).distinct()
        return self.entities.join(ends, "entity_id", "left_semi")

    def _bare(self) -> DataFrame:
        return self.events.drop("level")

    def union(self, other: TraceGraph) -> TraceGraph:
        every = self._bare().unionByName(other._bare()).dropDuplicates(["event_id"])
        entities = self.entities if self.entities is other.entities else self.entities.unionByName(other.entities).dropDuplicates(["entity_id"])
        return TraceGraph(entities, every)

    def intersect(self, other: TraceGraph) -> TraceGraph:
        return self.with_events(self._bare().join(other.events.select("event_id"), "event_id", "left_semi"))

    def minus(self, other: TraceGraph) -> TraceGraph:
        return self.with_events(self._bare().join(other.events.select("event_id"), "event_id", "left_anti"))

    def refine(self, nodes: Column | None = None, edges: Column | None = None) -> TraceGraph:
        """Only events that meet the condition and whose both ends do."""
        out = self.events if edges is None else self.events.where(edges)
        if nodes is not None:
            good = self.entities.where(nodes).select(F.col("entity_id").alias("good"))
            for end in ("src_id", "dst_id"):
                out = out.join(good, F.col(end) == F.col("good"), "left_semi")
        return self.with_events(out)

    def size(self) -> DataFrame:
        """One row: nodes, edges."""
        ends = self.events.select(F.explode(F.array("src_id", "dst_id")).alias("e")).agg(F.count_distinct("e").alias("nodes"))
        return ends.crossJoin(self.events.agg(F.count(F.lit(1)).alias("edges")))  # one row each

    def degrees(self) -> DataFrame:
        """Per node: node, n_in, n_out."""
        ends = self.events.select(F.explode(F.array(F.struct(F.col("src_id").alias("node"), F.lit(1).alias("o")), F.struct(F.col("dst_id").alias("node"), F.lit(0).alias("o")))).alias("x"))
        return ends.groupBy(F.col("x.node").alias("node")).agg(F.sum(1 - F.col("x.o")).alias("n_in"), F.sum("x.o").alias("n_out"))

    def entry_points(self) -> DataFrame:
        """Nodes from which events leave and into which none comes."""
        return self.events.select(F.col("src_id").alias("node")).distinct().join(self.events.select(F.col("dst_id").alias("node")), "node", "left_anti")

    def sequence(self) -> DataFrame:
        """Events in the order of time, numbered; for results, not for stores."""
        from pyspark.sql import Window

        return self.events.withColumn("nth", F.row_number().over(Window.orderBy("start_us", "event_id")))

    def show(self, as_: str = "edges") -> DataFrame | str:
        """edges and nodes are frames; dot, json and summary are texts of at most ``SHOWN`` rows."""
        if as_ == "edges":
            return self.events
        if as_ == "nodes":
            return self.nodes()
        if as_ == "summary":
            row = self.size().first()
            return f"{row['nodes']} nodes, {row['edges']} edges"
        rows = self.events.orderBy("start_us", "event_id").select("src_id", "dst_id", "op", "event_id", "start_us").limit(SHOWN)
        if as_ == "json":
            return "\n".join(r[0] for r in rows.select(F.to_json(F.struct("*"))).collect())
        if as_ == "dot":
            quote = lambda s: '"' + s.replace('"', r"\"") + '"'
            return "digraph trace {\n" + "".join(f"  {quote(r['src_id'])} -> {quote(r['dst_id'])} [label={quote(r['op'])}];\n" for r in rows.collect()) + "}"
        raise ValueError(f"can't show a graph as {as_}")

    def resident(self) -> TraceGraph:
        """Kept in memory, spilling to disk."""
        kept = self.events.persist(StorageLevel.MEMORY_AND_DISK)
        kept.count()
        return self.with_events(kept)

    def stored(self) -> TraceGraph:
        """Written out and read back for every use."""
        return self.with_events(plans.pin(self.events, "graph"))

    def pin(self) -> TraceGraph:
        return self.stored()

    def write(self, folder: str, fmt: str = "parquet") -> None:
        self.events.write.mode("overwrite").format(fmt).option("header", "true").save(f"{folder}/events")
        self.nodes().write.mode("overwrite").format(fmt).option("header", "true").save(f"{folder}/nodes")


def read_graph(spark: SparkSession, folder: str, fmt: str = "parquet") -> TraceGraph:
    events = spark.read.format(fmt).option("header", "true").schema(schema.event_schema()).load(f"{folder}/events")
    return TraceGraph(spark.read.format(fmt).option("header", "true").schema(schema.entity_schema()).load(f"{folder}/nodes"), events)
