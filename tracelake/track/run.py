"""Seeds, filters, limits, and the call that puts a trace together."""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tracelake import plans
from tracelake.graph import TraceGraph
from tracelake.model.store import TraceStore
from tracelake.track import engines


@dataclass(frozen=True)
class NodeFilter:
    """Conditions on entities (two-valued columns): only those kept, then none of those dropped."""

    keep: Column | None = None
    drop: Column | None = None


@dataclass(frozen=True)
class EdgeFilter:
    """Conditions on events."""

    keep: Column | None = None
    drop: Column | None = None


@dataclass(frozen=True)
class Limits:
    """max_hops: steps; max_span_us: event time from the point of interest; budget_s: wall clock between rounds."""

    max_hops: int | None = None
    max_span_us: int | None = None
    budget_s: float | None = None


@dataclass(frozen=True)
class Seed:
    """Where a trace begins: events, entities, or another result; one case_id each."""

    kind: str
    what: object
    case_id: int = 0

    @staticmethod
    def events(condition: Column, case_id: int = 0) -> Seed:
        return Seed("events", condition, case_id)

    @staticmethod
    def entities(condition: Column, case_id: int = 0) -> Seed:
        return Seed("entities", condition, case_id)

    @staticmethod
    def text(part: str, case_id: int = 0) -> Seed:
        """Entities whose name contains the text."""
        return Seed("entities", F.coalesce(F.col("name").contains(part), F.lit(False)), case_id)

    @staticmethod
    def graph(graph: TraceGraph, case_id: int = 0) -> Seed:
        return Seed("graph", graph, case_id)

    def resolve(self, source, direction: str, case: str | None = None) -> tuple[DataFrame, DataFrame]:
        """(case_id, node, bound) and the events that belong to the result from the start; ``case`` names a column with the case."""
        case = F.lit(self.case_id).cast("bigint").alias("case_id") if case is None else F.col(case)
        if self.kind == "entities":
            nodes = source.entities.where(self.what).select(case, F.col("entity_id").alias("node"), F.lit(engines.EVERYTHING).alias("bound"))
            return nodes, source.events.where(F.lit(False))
        own = self.what.events if self.kind == "graph" else source.events.where(self.what)
        end, bound = ("src_id", F.col("end_us")) if direction == "back" else ("dst_id", -F.col("start_us"))
        return own.select(case, F.col(end).alias("node"), bound.alias("bound")), own


def starts(seeds: list[Seed], source, direction: str) -> tuple[DataFrame, DataFrame]:
    """(case_id, node, bound) and the events given, of all seeds; seeds by conditions are one scan together."""
    nodes, given = [], []
    for kind, rows in (("events", source.events), ("entities", source.entities)):
        own = [s for s in seeds if s.kind == kind]
        if len(own) > 1:
            cases = F.array_compact(F.array(*[F.when(s.what, F.lit(s.case_id).cast("bigint")) for s in own]))
            rows = rows.where(reduce(or_, (s.what for s in own))).withColumn("case_id", F.explode(cases))
            one = Seed.events(F.lit(True)) if kind == "events" else Seed.entities(F.lit(True))
            at, held = one.resolve(replace(source, **{kind: rows}), direction, "case_id")
            nodes.append(at)
            given += [held] if kind == "events" else []
    for s in seeds:
        if s.kind == "graph" or sum(x.kind == s.kind for x in seeds) == 1:
            at, held = s.resolve(source, direction)
            nodes.append(at)
            given.append(held.withColumn("case_id", F.lit(s.case_id).cast("bigint")))
    if not given:
        given = [source.events.where(F.lit(False)).withColumn("case_id", F.lit(0).cast("bigint"))]
    return reduce(DataFrame.unionByName, nodes), reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), given)


def blocked_nodes(source, nodes: NodeFilter) -> DataFrame | None:
    """Ids of the entities that the filter keeps out; None without a filter."""
    bad = None
    if nodes.keep is not None:
        bad = ~nodes.keep
    if nodes.drop is not None:
        bad = nodes.drop if bad is None else bad | nodes.drop
    return None if bad is None else source.entities.where(bad).select(F.col("entity_id").alias("blocked"))


def admitted(source, nodes: NodeFilter, edges: EdgeFilter) -> DataFrame:
    """Events that pass the edge filter and whose both ends pass the node filter."""
    out = source.events
    if edges.keep is not None:
        out = out.where(edges.keep)
    if edges.drop is not None:
        out = out.where(~edges.drop)
    blocked = blocked_nodes(source, nodes)
    if blocked is not None:
        for end in ("src_id", "dst_id"):
            out = out.join(blocked, F.col(end) == F.col("blocked"), "left_anti")
    return out


def track_many(
    seeds: list[Seed], source, direction: str = "back", nodes: NodeFilter = NodeFilter(), edges: EdgeFilter = EdgeFilter(),
    limits: Limits = Limits(), engine: str = "auto", filter_mode: str = "during", metrics: list | None = None,
) -> DataFrame:
    """(case_id, event columns, level) of the traces of all seeds over one source in one pass.

    ``source`` is a store or a graph. ``engine``: bound, level, queue, local, or
    auto: local for a source of bounded size, else bound. With
    ``filter_mode="after"`` the whole closure is taken first and filtered then;
    filters never remove the seeds' events.
    """
    start, given = starts(seeds, source, direction)
    given = plans.pin(given, "given")  # a few events, which each round looks at
    # Rounds read the copy of the events that is sorted by the end at which they find edges.
    rows = source.along("dst_id" if direction == "back" else "src_id") if isinstance(source, TraceStore) else source
    usable = admitted(rows, nodes, edges) if filter_mode == "during" else rows.events
    in_span = F.lit(True)
    if limits.max_span_us is not None:
        span = limits.max_span_us
        edge = given.agg(F.min("start_us"), F.max("end_us")).first()
        if edge[0] is not None:
            in_span = F.col("start_us") >= edge[0] - span if direction == "back" else F.col("end_us") <= edge[1] + span
    paths = engines.directed(usable.where(in_span), direction)
    if engine == "auto" and isinstance(source, TraceStore) and source.at_most(engines.LOCAL_EDGES):
        engine = "local"
    elif engine == "auto":
        small = plans.up_to(paths, engines.LOCAL_EDGES)
        engine, paths = ("bound", paths) if small is None else ("local", small)
    options = {"budget_s": limits.budget_s} if engine == "bound" else {}
    if engine == "bound" and filter_mode == "during" and (blocked := blocked_nodes(source, nodes)) is not None:
        # Rounds look at the nodes found, so that no round joins all events with the filter.
        options["blocked"] = plans.pin(blocked, "blocked")
        paths = engines.directed(admitted(rows, NodeFilter(), edges).where(in_span), direction)
    found, steps = engines.FORMS[engine](paths, start, given.select("case_id", "event_id"), limits.max_hops, **options)
    if metrics is not None:
        metrics += steps
    columns = source.events.columns
    columns = [c for c in columns if c not in ("level", "case_id")]
    found = found.select("case_id", F.col("event_id").alias("found_id"), "level")
    out = source.events.select(*columns).join(found, F.col("event_id") == F.col("found_id")).select("case_id", *columns, "level")
    if filter_mode == "after":
        good = admitted(replace(source, events=out) if isinstance(source, TraceStore) else source.with_events(out), nodes, edges)
        out = good.select("case_id", *columns, "level")
    seeded = given.select("case_id", *columns, F.lit(0).alias("level"))
    return out.unionByName(seeded.dropDuplicates(["case_id", "event_id"]))


def track(seed: Seed, source, direction: str, **options) -> TraceGraph:
    rows = track_many([seed], source, direction, **options)
    return TraceGraph(source.entities, rows.drop("case_id"))


def track_back(seed: Seed, source, **options) -> TraceGraph:
    """All events on which the seed depends."""
    return track(seed, source, "back", **options)


def track_forward(seed: Seed, source, **options) -> TraceGraph:
    """All events that depend on the seed."""
    return track(seed, source, "forward", **options)


def intersect_traces(poi: Seed, entries: Seed, source, **options) -> TraceGraph:
    """What lies between: the forward trace of the entries inside the backward trace of the point of interest."""
    return track_forward(entries, track_back(poi, source, **options), **options)
