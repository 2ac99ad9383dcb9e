"""The forms of tracking. All take and give the same frames.

Both directions are one computation: ``key`` is the end at which an edge is found,
``next`` the end that is found then, and an edge is found from a node iff its
``t_in`` lies below the node's bound; it then offers ``t_out`` as a bound for its
next end. Backward: sink, source, start, end. Forward: source, sink, -end, -start.

edges: event_id, key, next, t_in, t_out
seeds: case_id, node, bound        the nodes to begin with
given: case_id, event_id           events that belong to the result from the start
result: case_id, event_id, level   without the given ones; a level is a number of steps
"""

from __future__ import annotations

import time
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracelake import plans

EVERYTHING = 2**62
#: A frontier of up to so many nodes is broadcast; a larger one meets the edges in a shuffle.
BROADCAST_NODES = 100_000
#: The nodes of a frontier of up to so many reach the scan as a literal list, which skips row groups sorted by node.
LITERAL_NODES = 1000
#: A source of up to so many edges is traced in one task.
LOCAL_EDGES = 2_000_000
#: The queue form asks one query per event for so many events, and takes up to so many rows from one; what is left in the queue then goes on in rounds.
QUEUE_EVENTS, QUEUE_ROWS = 200, 1000


def directed(edges: DataFrame, direction: str) -> DataFrame:
    if direction == "back":
        return edges.select("event_id", F.col("dst_id").alias("key"), F.col("src_id").alias("next"), F.col("start_us").alias("t_in"), F.col("end_us").alias("t_out"))
    return edges.select("event_id", F.col("src_id").alias("key"), F.col("dst_id").alias("next"), (-F.col("end_us")).alias("t_in"), (-F.col("start_us")).alias("t_out"))


def bound_form(
    edges: DataFrame, seeds: DataFrame, given: DataFrame, most: int | None = None, budget_s: float | None = None, blocked: DataFrame | None = None,
    level: int = 0, later: DataFrame | None = None,
) -> tuple[DataFrame, list[dict]]:
    """Rounds over nodes. The state is one bound per node reached.

    In a round each raised node finds only the edges between its old and its new
    bound, so an edge is found once and needs no comparison with those seen. The
    bounds of a round reach the scan as literals. ``blocked`` are nodes that no edge may touch:
    a seed's own node is left out at the start, others as they are found. If the
    wall clock stops it, the last entry of the steps says so (partial). ``level`` is that of
    the seeds; ``later`` are seeds that lie one level above it.
    """
    if blocked is not None:
        seeds = seeds.join(blocked, F.col("node") == F.col("blocked"), "left_anti")
    bounds = plans.pin(seeds.groupBy("case_id", "node").agg(F.max("bound").alias("bound")), "bounds")
    frontier = bounds.select("case_id", "node", F.lit(-EVERYTHING).alias("low"), F.col("bound").alias("high"))
    parts, steps, began = [], [], time.monotonic()
    while most is None or level < most:
        nodes, first, last = frontier.agg(F.count(F.lit(1)), F.min("low"), F.max("high")).first()
        if not nodes:
            break
        if budget_s is not None and level and time.monotonic() - began > budget_s:
            steps.append({"level": None, "frontier": nodes, "events": 0, "partial": True})
            break
        level += 1
        side = F.broadcast(frontier) if nodes <= BROADCAST_NODES else frontier
        near = edges.where((F.col("t_in") >= first) & (F.col("t_in") < last))
        if nodes <= LITERAL_NODES:
            near = near.where(F.col("key").isin(*{r.node for r in frontier.select("node").collect()}))
        found = near.join(side, (F.col("key") == F.col("node")) & (F.col("t_in") >= F.col("low")) & (F.col("t_in") < F.col("high")))
        found = found.join(given.select(F.col("case_id").alias("g_case"), F.col("event_id").alias("g_event")), (F.col("case_id") == F.col("g_case")) & (F.col("event_id") == F.col("g_event")), "left_anti")
        if blocked is not None:
            found = found.join(blocked, F.col("next") == F.col("blocked"), "left_anti")
        found = plans.pin(found.select("case_id", "event_id", "next", "t_out"), "found")
        offered = found.select("case_id", F.col("next").alias("node"), F.col("t_out").alias("offer"))
        if later is not None:
            offered, later = offered.unionByName(later.withColumnRenamed("bound", "offer")), None
        offered = offered.groupBy("case_id", "node").agg(F.max("offer").alias("offer"))
        known = bounds.select(F.col("case_id").alias("b_case"), F.col("node").alias("b_node"), F.col("bound").alias("old"))
        raised = offered.join(known, (F.col("case_id") == F.col("b_case")) & (F.col("node") == F.col("b_node")), "left").where(F.col("old").isNull() | (F.col("offer") > F.col("old")))
        frontier = plans.pin(raised.select("case_id", "node", F.coalesce("old", F.lit(-EVERYTHING)).alias("low"), F.col("offer").alias("high")), "frontier")
        state = bounds.unionByName(frontier.select("case_id", "node", F.col("high").alias("bound")))
        bounds = plans.pin(state.groupBy("case_id", "node").agg(F.max("bound").alias("bound")), "bounds")
        part = found.select("case_id", "event_id", F.lit(level).alias("level"))
        parts.append(part)
        steps.append({"level": level, "frontier": nodes, "events": part.count()})
    return _union(parts, seeds), steps


def level_form(edges: DataFrame, seeds: DataFrame, given: DataFrame, most: int | None = None) -> tuple[DataFrame, list[dict]]:
    """Rounds over events: all dependents of a level's events at once, less those seen before."""
    frontier = seeds.select("case_id", "node", "bound")
    seen, parts, steps, level = given.select("case_id", "event_id"), [], [], 0
    while most is None or level < most:
        level += 1
        own = frontier.groupBy("case_id", "node").agg(F.max("bound").alias("bound"))
        found = edges.join(own, (F.col("key") == F.col("node")) & (F.col("t_in") < F.col("bound"))).select("case_id", "event_id", "next", "t_out")
        found = plans.pin(found.join(seen, ["case_id", "event_id"], "left_anti"), "level")
        n = found.count()
        if not n:
            break
        parts.append(found.select("case_id", "event_id", F.lit(level).alias("level")))
        steps.append({"level": level, "frontier": None, "events": n})
        seen = plans.pin(seen.unionByName(found.select("case_id", "event_id")), "seen")
        frontier = found.select("case_id", F.col("next").alias("node"), F.col("t_out").alias("bound"))
    return _union(parts, seeds), steps


def queue_form(edges: DataFrame, seeds: DataFrame, given: DataFrame, most: int | None = None) -> tuple[DataFrame, list[dict]]:
    """The literal form: a queue on the driver and one small query for each event taken from it.

    A queue that outgrows the driver becomes a table, which :func:`bound_form` takes on.
    """
    spark = edges.sparkSession
    seen = {(r.case_id, r.event_id) for r in given.collect()}
    queue = deque((r.case_id, r.node, r.bound, 0) for r in seeds.collect())
    out, asked = [], 0
    while queue and asked < QUEUE_EVENTS:
        case, node, bound, level = queue[0]
        if most is not None and level >= most:
            break  # as are all behind it
        rows = edges.where((F.col("key") == node) & (F.col("t_in") < bound)).orderBy("event_id").limit(QUEUE_ROWS + 1).collect()
        asked += 1
        if len(rows) > QUEUE_ROWS:
            break
        queue.popleft()
        for r in rows:
            if (case, r.event_id) not in seen:
                seen.add((case, r.event_id))
                out.append((case, r.event_id, level + 1))
                queue.append((case, r.next, r.t_out, level + 1))
    found = spark.createDataFrame(out, "case_id bigint, event_id bigint, level int")
    steps = [{"level": None, "frontier": asked, "events": len(out)}]
    if not queue or (most is not None and queue[0][3] >= most):
        return found, steps
    level = queue[0][3]
    now, later = (spark.createDataFrame([q[:3] for q in queue if (q[3] == level) == own], "case_id bigint, node string, bound bigint") for own in (True, False))
    known = plans.pin(given.select("case_id", "event_id").unionByName(found.select("case_id", "event_id")), "queued")
    rest, more = bound_form(edges, now, known, most, level=level, later=later)
    return found.unionByName(rest), steps + more


def local_form(edges: DataFrame, seeds: DataFrame, given: DataFrame, most: int | None = None) -> tuple[DataFrame, list[dict]]:
    """All rounds of all cases in one task over a sorted adjacency in memory, for sources of bounded size."""
    starts = [(r.case_id, r.node, r.bound) for r in seeds.collect()]  # as many as the seeds of an investigation
    known: dict[int, list[int]] = {}
    for r in given.collect():
        known.setdefault(r.case_id, []).append(r.event_id)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches), schema=_EDGES)
        names, index = np.unique(np.concatenate([table.column(c).to_numpy() for c in ("key", "next")]), return_inverse=True) if table.num_rows else (np.array([]), np.array([], int))
        key, nxt = index[: table.num_rows], index[table.num_rows :]
        ids, t_in, t_out = (table.column(c).to_numpy() for c in ("event_id", "t_in", "t_out"))
        order = np.lexsort((ids, t_in, key))
        key, nxt, ids, t_in, t_out = (x[order] for x in (key, nxt, ids, t_in, t_out))
        begin = np.searchsorted(key, np.arange(len(names) + 1))
        place = {n: k for k, n in enumerate(names.tolist())}
        for case in sorted({c for c, _, _ in starts}):
            bound = np.full(len(names), -EVERYTHING, dtype=np.int64)
            for _, node, high in (s for s in starts if s[0] == case):
                if node in place:
                    bound[place[node]] = max(bound[place[node]], high)
            own = np.isin(ids, known.get(case, []))
            low = np.full(len(names), -EVERYTHING, dtype=np.int64)
            raised, level, found = np.flatnonzero(bound > low), 0, []
            while len(raised) and (most is None or level < most):
                level += 1
                slices = []
                for node in raised.tolist():
                    a, b = begin[node], begin[node + 1]
                    lo, hi = np.searchsorted(t_in[a:b], (low[node], bound[node]))
                    slices.append(np.arange(a + lo, a + hi))
                low[raised] = bound[raised]
                new = np.concatenate(slices)
                new = new[~own[new]]
                found.append((ids[new], np.full(len(new), level, dtype=np.int32)))
                np.maximum.at(bound, nxt[new], t_out[new])
                raised = np.flatnonzero(bound > low)
            if found:
                events, levels = np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(events), case)), pa.array(events), pa.array(levels)], names=["case_id", "event_id", "level"])

    return edges.select("event_id", "key", "next", "t_in", "t_out").coalesce(1).mapInArrow(run, "case_id bigint, event_id bigint, level int"), []


_EDGES = pa.schema([("event_id", pa.int64()), ("key", pa.string()), ("next", pa.string()), ("t_in", pa.int64()), ("t_out", pa.int64())])
FORMS = {"bound": bound_form, "level": level_form, "queue": queue_form, "local": local_form}


def _union(parts: list[DataFrame], like: DataFrame) -> DataFrame:
    if not parts:
        return like.sparkSession.createDataFrame([], "case_id bigint, event_id bigint, level int")
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
