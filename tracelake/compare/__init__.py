"""Comparison methods: plain tracing, rareness-prioritised tracing, impact propagation.

The text names the last two and leaves out their formulas. Those here follow
published descriptions of such methods; scaling and limits are choices of ours.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracelake import plans
from tracelake.compare.blocks import Blocks
from tracelake.track import Seed, track_many
from tracelake.track.engines import LOCAL_EDGES

#: A case's graph of up to so many edges is scored in one task, a larger one in blocks.
CASE_EDGES = 200_000


def plain_traces(seeds: list[Seed], source) -> DataFrame:
    """Backward closures without any control: case_id, event columns, level."""
    return track_many(seeds, source, "back")


def rareness(source, before_us: int | None = None) -> DataFrame:
    """Events with their rareness: 1 / (1 + number of (host, day) on which subject, operation and object met), reference events only."""
    events = source.events
    past = events if before_us is None else events.where(F.col("start_us") < before_us)
    seen = past.groupBy("subject_id", "op", "object_id").agg(F.count_distinct("host", "day").alias("days"))
    keys = [F.col(c).alias(f"k_{c}") for c in ("subject_id", "op", "object_id")]
    same = (F.col("subject_id") == F.col("k_subject_id")) & (F.col("op") == F.col("k_op")) & (F.col("object_id") == F.col("k_object_id"))
    out = events.join(seen.select(*keys, "days"), same, "left")
    return out.withColumn("rare", 1.0 / (1.0 + F.coalesce("days", F.lit(0)))).drop("k_subject_id", "k_op", "k_object_id", "days")


def rareness_traces(pois: list[tuple[int, int]], source, limit: int | None = None) -> DataFrame:
    """Backward traces that expand the rarest events first: case_id, event_id.

    ``pois`` are (case_id, event_id); ``limit`` counts expanded events. Priority is
    rareness * (1 + 1 / (1 + fan-out of the source)), ties by event_id. Without a
    limit the result is that of plain tracing. A source of bounded size is traced in one
    task, a larger one by :func:`_rarest_first`.
    """
    rows = rareness(source)
    fan = source.events.groupBy(F.col("src_id").alias("f_id")).agg(F.count(F.lit(1)).alias("fan"))
    rows = rows.join(fan, F.col("src_id") == F.col("f_id"))
    rows = rows.select("event_id", "src_id", "dst_id", "start_us", "end_us", (F.col("rare") * (1 + 1 / (1.0 + F.col("fan")))).alias("priority"))
    small = plans.up_to(rows, LOCAL_EDGES)
    if small is None and limit is None:
        return plain_traces([Seed.events(F.col("event_id") == e, c) for c, e in pois], source).select("case_id", "event_id").distinct()
    if small is None:
        return _rarest_first(pois, rows, limit)
    rows = small
    columns = rows.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        df = pa.Table.from_batches(held).to_pandas() if held else pd.DataFrame({c: [] for c in columns})
        df = df.sort_values(["dst_id", "start_us", "event_id"], ignore_index=True)
        ids, src, start, end, priority = (df[c].to_numpy() for c in ("event_id", "src_id", "start_us", "end_us", "priority"))
        groups = {k: (int(v[0]), int(v[-1]) + 1) for k, v in df.groupby("dst_id").indices.items()}
        place = {int(e): k for k, e in enumerate(ids.tolist())}
        for case, poi in pois:
            first = place[poi]
            found, heap, expanded = {first}, [(-np.inf, poi, first)], 0
            while heap and (limit is None or expanded < limit):
                _, _, at = heapq.heappop(heap)
                expanded += 1
                a, b = groups.get(src[at], (0, 0))
                for k in range(a, a + int(np.searchsorted(start[a:b], end[at]))):
                    if k not in found:
                        found.add(k)
                        heapq.heappush(heap, (-priority[k], int(ids[k]), k))
            own = ids[sorted(found)].astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), case)), pa.array(own)], names=["case_id", "event_id"])

    return rows.coalesce(1).mapInArrow(run, "case_id bigint, event_id bigint")


def _contenders(limit: int):
    """Leaves out edges that can't be among the first ``limit`` expanded: so many of the same sink that begin no later come before them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            df = batch.to_pandas().sort_values(["dst_id", "start_us", "priority", "event_id"], ascending=[True, True, False, True])
            keep, node, best = [], None, []
            for k, (dst, p, e) in enumerate(zip(df["dst_id"].tolist(), df["priority"].tolist(), df["event_id"].tolist())):
                if dst != node:
                    node, best = dst, []
                if len(best) < limit:
                    heapq.heappush(best, (p, -e))
                elif (p, -e) > best[0]:
                    heapq.heapreplace(best, (p, -e))
                else:
                    continue
                keep.append(k)
            yield pa.RecordBatch.from_pandas(df.iloc[keep], schema=batch.schema, preserve_index=False)

    return run


def _rarest_first(pois: list[tuple[int, int]], rows: DataFrame, limit: int) -> DataFrame:
    """Prioritised tracing of a source of any size.

    The order of expansion is worked out on the driver, which asks for the edges into the
    nodes that the best ``limit`` of a queue may expand, all cases at once, and holds only
    edges that may be expanded themselves. It gives a bound for each node expanded, at most
    ``limit`` for a case; the events below the bounds are found in one join.
    """
    spark = rows.sparkSession
    rows = plans.pin(rows.hint("rebalance", "dst_id").sortWithinPartitions("dst_id", "start_us"), "prioritised")
    first = {r.event_id: r for r in rows.where(F.col("event_id").isin([e for _, e in pois])).collect()}
    into: dict[str, tuple] = {}  # edges into a node, by their start
    none = np.array([], dtype=np.int64)

    def ask(nodes: list[str]) -> None:
        wanted = F.broadcast(spark.createDataFrame([(n,) for n in nodes], "node string"))
        found = rows.join(wanted, F.col("dst_id") == F.col("node"), "left_semi").select(*rows.columns)
        table = found.mapInArrow(_contenders(limit), found.schema).toArrow().sort_by([("dst_id", "ascending"), ("start_us", "ascending")])
        ids, start, end, priority = (table.column(c).to_numpy() for c in ("event_id", "start_us", "end_us", "priority"))
        sinks, sources = table.column("dst_id").to_pylist(), table.column("src_id").to_pylist()
        into.update({n: (none, none, none, none, []) for n in nodes})
        cuts = [0, *(k for k in range(1, len(sinks)) if sinks[k] != sinks[k - 1]), len(sinks)] if sinks else []
        for a, b in zip(cuts, cuts[1:]):
            into[sinks[a]] = (ids[a:b], start[a:b], end[a:b], priority[a:b], sources[a:b])

    heaps = {(c, e): [(-np.inf, e, first[e].src_id, first[e].end_us)] for c, e in pois}
    bounds: dict[tuple, dict[str, int]] = {key: {} for key in heaps}
    expanded = dict.fromkeys(heaps, 0)
    while True:
        missing: set[str] = set()
        for key, heap in heaps.items():
            while heap and expanded[key] < limit and heap[0][2] in into:
                _, _, node, high = heapq.heappop(heap)
                expanded[key] += 1
                low = bounds[key].get(node)
                if low is not None and low >= high:
                    continue
                bounds[key][node] = high
                ids, start, end, priority, sources = into[node]
                for k in range(0 if low is None else int(np.searchsorted(start, low)), int(np.searchsorted(start, high))):
                    if ids[k] != key[1]:
                        heapq.heappush(heap, (-float(priority[k]), int(ids[k]), sources[k], int(end[k])))
            heap[:] = heapq.nsmallest(limit - expanded[key], heap)  # no more are expanded
            missing.update(h[2] for h in heap if h[2] not in into)
        if not missing:
            break
        ask(sorted(missing))
    reached = [(c, n, b) for (c, _), own in bounds.items() for n, b in own.items()]
    below = F.broadcast(spark.createDataFrame(reached, "case_id bigint, node string, bound bigint"))
    out = rows.join(below, (F.col("dst_id") == F.col("node")) & (F.col("start_us") < F.col("bound"))).select("case_id", "event_id")
    return out.unionByName(spark.createDataFrame(pois, "case_id bigint, event_id bigint")).distinct()


def raw_features(amount, end_us, ratio, poi_amount, poi_end_us) -> np.ndarray:
    """Features before they are scaled."""
    close = 1.0 / (np.abs(amount - poi_amount) + 1e-4)
    when = np.log1p(1.0 / np.maximum(np.abs(end_us - poi_end_us) / 1e6, 1e-6))
    return np.column_stack([close, when, ratio]).astype(float)


def features(edges: pd.DataFrame, poi: pd.Series) -> np.ndarray:
    """Per edge: closeness of amount, closeness in time, in-degree over out-degree of the source; each scaled to 0..1."""
    inward, outward = edges["dst_id"].value_counts(), edges["src_id"].value_counts()
    ratio = outward.reindex(edges["src_id"]).to_numpy() / np.maximum(inward.reindex(edges["src_id"]).fillna(0).to_numpy(), 1)
    x = raw_features(edges["amount"], edges["end_us"], ratio, poi["amount"], poi["end_us"])
    span = x.max(axis=0) - x.min(axis=0)
    return (x - x.min(axis=0)) / np.where(span > 0, span, 1.0)


def projection(x: np.ndarray, mode: str = "learned") -> np.ndarray:
    """Direction that parts two clusters of edges best (or equal weights): k-means, then the discriminant of the two."""
    if mode == "fixed" or len(x) < 4:
        return np.full(x.shape[1], 1.0 / x.shape[1])
    centres = np.array([x[x.sum(axis=1).argmin()], x[x.sum(axis=1).argmax()]])
    for _ in range(50):
        near = ((x[:, None, :] - centres[None]) ** 2).sum(axis=2).argmin(axis=1)
        new = np.array([x[near == k].mean(axis=0) if (near == k).any() else centres[k] for k in (0, 1)])
        if np.allclose(new, centres):
            break
        centres = new
    within = sum(np.cov(x[near == k].T, bias=True) * (near == k).sum() for k in (0, 1) if (near == k).sum() > 1)
    return direction(np.atleast_2d(within), centres)


def direction(within: np.ndarray, centres: np.ndarray) -> np.ndarray:
    """Discriminant of two clusters by their centres and the scatter within them."""
    out = np.linalg.pinv(within + 1e-6 * np.eye(centres.shape[1])) @ (centres[1] - centres[0])
    norm = np.abs(out).sum()
    return out / norm if norm > 0 else np.full(len(out), 1.0 / len(out))


def propagate(edges: pd.DataFrame, weight: np.ndarray, poi: pd.Series, eps: float = 1e-6, most_rounds: int = 50) -> pd.Series:
    """Scores of nodes: 1 at the point of interest, else the weighted scores of the nodes they flow to."""
    nodes, at = np.unique(np.concatenate([edges["src_id"], edges["dst_id"]]), return_inverse=True)
    src, dst = at[: len(edges)], at[len(edges) :]
    score = np.zeros(len(nodes))
    goal = int(np.searchsorted(nodes, poi["dst_id"]))
    score[goal] = 1.0
    for _ in range(most_rounds):
        new = np.zeros(len(nodes))
        np.add.at(new, src, weight * score[dst])
        new = np.minimum(new, 1.0)
        new[goal] = 1.0
        change, score = np.abs(new - score).max(), new
        if change < eps:
            break
    return pd.Series(score, index=nodes)


def rank_entries(edges: pd.DataFrame, score: pd.Series, n: int) -> list[str]:
    """Best n nodes without incoming edges of every kind, by score, then id; scores that agree to 12 significant digits are equal."""
    entries = sorted(set(edges["src_id"]) - set(edges["dst_id"]))
    out = []
    for kind in ("p", "f", "n"):
        own = sorted((e for e in entries if e[0] == kind), key=lambda e: (-float(f"{score[e]:.11e}"), e))
        out += own[:n]
    return out


def _forward(edges: pd.DataFrame, start: list[str]) -> set[int]:
    """Numbers of the edges of the forward trace of nodes inside a graph."""
    by_src = {k: v for k, v in edges.groupby("src_id").indices.items()}
    end, begin, dst = edges["end_us"].to_numpy(), edges["start_us"].to_numpy(), edges["dst_id"].to_numpy()
    bound = {n: -(2**62) for n in start}
    queue, found = list(start), set()
    while queue:
        node = queue.pop()
        for k in by_src.get(node, ()):
            if end[k] > bound[node]:
                found.add(int(k))
                if begin[k] < bound.get(dst[k], 2**62):
                    bound[dst[k]] = begin[k]
                    queue.append(dst[k])
    return found


def impact_traces(pois: list[tuple[int, int]], source, entries: int = 3, weights: str = "learned", graphs: DataFrame | None = None) -> DataFrame:
    """Impact propagation per case: case_id, event_id.

    The backward graph of each point of interest is weighted and scored; the best
    ``entries`` entry points of each kind are traced forward inside it. The graphs
    come from one distributed pass.
    """
    return impact_sweep(pois, source, [entries], weights, graphs).drop("entries")


def impact_sweep(pois: list[tuple[int, int]], source, counts: list[int], weights: str = "learned", graphs: DataFrame | None = None) -> DataFrame:
    """Impact propagation with several numbers of entries, which share the scores: entries, case_id, event_id.

    A graph of up to ``CASE_EDGES`` edges is held by one task; larger ones are scored and traced as :class:`Blocks`.
    """
    columns = ("case_id", "event_id", "src_id", "dst_id", "start_us", "end_us", "amount")
    if graphs is None:
        graphs = plans.pin(plain_traces([Seed.events(F.col("event_id") == e, c) for c, e in pois], source).select(*columns), "plain")
    graphs, wanted = graphs.select(*columns), dict(pois)

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        edges = pdf.sort_values("event_id", ignore_index=True)
        case = int(edges["case_id"].iloc[0])
        poi = edges[edges["event_id"] == wanted[case]].iloc[0]
        x = features(edges, poi)
        w = np.clip(x @ projection(x, weights), 0.0, None) + 1e-9
        total = pd.Series(w).groupby(edges["src_id"]).transform("sum").to_numpy()
        score = propagate(edges, w / total, poi)
        out = []
        for n in counts:
            found = _forward(edges, rank_entries(edges, score, n)) | {int(edges.index[edges["event_id"] == wanted[case]][0])}
            out.append(pd.DataFrame({"entries": n, "case_id": case, "event_id": edges["event_id"].iloc[sorted(found)]}))
        return pd.concat(out)

    large = [r.case_id for r in graphs.groupBy("case_id").count().where(F.col("count") > CASE_EDGES).collect()]
    out = graphs.where(~F.col("case_id").isin(large)).groupBy("case_id").applyInPandas(one, "entries int, case_id bigint, event_id bigint")
    if not large:
        return out
    rest = graphs.where(F.col("case_id").isin(large))
    given = rest.where(F.col("event_id").isin([wanted[c] for c in large])).collect()  # one for each case, or a few that meet others
    blocks = Blocks(rest, {r.case_id: r for r in given if r.event_id == wanted[r.case_id]})
    return out.unionByName(blocks.forward(blocks.scores(weights), counts))
