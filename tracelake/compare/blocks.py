"""Impact propagation over graphs of any size.

A case's nodes are numbered in blocks of bounded size, and its edges are packed by the
blocks of their ends into rows of arrays. Scores and bounds are one vector for each block.
A round joins edges with vectors, works out what each row of edges adds, and puts that
together by block; a task holds some blocks, never a case.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tracelake import plans

#: Nodes of a block and edges of a row, about.
BLOCK_NODES, BLOCK_EDGES = 2**16, 100_000
#: Vectors of up to so many bytes are broadcast to the edges; larger ones meet them in a shuffle.
BROADCAST_BYTES = 2**27
FAR = 2**62

_PACKED = "case_id bigint, i int, j int, part int, n bigint, src binary, dst binary, event binary, start binary, end binary, x binary, low array<double>, high array<double>"
_VECTOR = "case_id bigint, b int, vec binary, change double"


def _each(df: DataFrame, fn: Callable[[dict], dict | None], schema: str) -> DataFrame:
    """One row, or none, for each row."""
    to = pa.schema([(n, _ARROW[t]) for n, t in (c.split() for c in schema.split(", "))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                got = fn(batch.slice(k, 1).to_pylist()[0])
                if got is not None:
                    yield pa.RecordBatch.from_pylist([got], schema=to)

    return df.mapInArrow(run, schema)


_ARROW = {"bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "binary": pa.binary(), "array<double>": pa.list_(pa.float64())}


class Blocks:
    """The graphs of cases in blocks. ``pois``: case to the event of interest (event_id, dst_id, end_us, amount)."""

    def __init__(self, graphs: DataFrame, pois: dict):
        self.spark, self.pois = graphs.sparkSession, pois
        if self.spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch", None) is None:
            self.spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", "16m")  # a row here is of some MB
        ends = F.array(*[F.struct(F.col(c).alias("node"), F.lit(o).alias("o"), F.lit(1 - o).alias("n")) for c, o in (("src_id", 1), ("dst_id", 0))])
        nodes = graphs.select("case_id", F.explode(ends).alias("e")).groupBy("case_id", F.col("e.node").alias("node")).agg(F.sum("e.o").alias("outward"), F.sum("e.n").alias("inward"))
        nodes = plans.pin(nodes, "impact-nodes")
        sizes = nodes.groupBy("case_id").agg(F.count(F.lit(1)), F.sum("outward")).collect()
        dealt = []
        for case, n, edges in sizes:
            across = -(-n // BLOCK_NODES)
            dealt.append((case, across, max(1, -(-edges // (BLOCK_EDGES * across * across)))))
        self.edges_of = {case: edges for case, _, edges in sizes}
        deal = F.broadcast(self.spark.createDataFrame(dealt, "case_id bigint, across int, parts int"))
        nodes = nodes.join(deal, "case_id").withColumn("block", F.pmod(F.xxhash64("node"), "across").cast("int"))
        place = F.row_number().over(Window.partitionBy("case_id", "block").orderBy("node")) - 1
        self.nodes = plans.pin(nodes.withColumn("place", place), "impact-nodes")
        self.size = {(r.case_id, r.block): r.n for r in self.nodes.groupBy("case_id", "block").agg(F.count(F.lit(1)).alias("n")).collect()}
        self.packed = self._pack(graphs)
        self.scale = {}
        for case in self.edges_of:
            own = [r for r in self._bounds if r.case_id == case]
            low, high = np.min([r.low for r in own], axis=0), np.max([r.high for r in own], axis=0)
            self.scale[case] = low, np.where(high > low, high - low, 1.0)

    def _pack(self, graphs: DataFrame) -> DataFrame:
        from tracelake.compare import raw_features

        ratio = F.col("outward") / F.greatest("inward", F.lit(1))
        a = self.nodes.select(F.col("case_id").alias("a_case"), F.col("node").alias("a_node"), F.col("block").alias("i"), F.col("place").alias("src"), ratio.alias("ratio"), "outward", "parts")
        b = self.nodes.select(F.col("case_id").alias("b_case"), F.col("node").alias("b_node"), F.col("block").alias("j"), F.col("place").alias("dst"))
        rows = graphs.join(a, (F.col("case_id") == F.col("a_case")) & (F.col("src_id") == F.col("a_node")))
        # The edges of a source stay together unless they alone fill a row.
        part = F.pmod(F.when(F.col("outward") > BLOCK_EDGES, F.hash("event_id")).otherwise(F.hash("src_id")), "parts").alias("part")
        rows = rows.select("case_id", "i", part, "event_id", "src", "dst_id", "start_us", "end_us", "amount", "ratio")
        rows = rows.join(b, (F.col("case_id") == F.col("b_case")) & (F.col("dst_id") == F.col("b_node")))
        rows = rows.select("case_id", "i", "j", "part", "event_id", "src", "dst", "start_us", "end_us", "amount", "ratio")
        pois = {c: (p.amount, p.end_us) for c, p in self.pois.items()}
        to = pa.schema([(n, _ARROW[t]) for n, t in (c.split() for c in _PACKED.split(", "))])

        def pack(table: pa.Table) -> pa.Table:
            table = table.sort_by("event_id")
            get = lambda c, kind=None: table.column(c).to_numpy().astype(kind) if kind else table.column(c).to_numpy()
            case = table.column("case_id")[0].as_py()
            x = raw_features(get("amount"), get("end_us"), get("ratio"), *pois[case])
            row = {c: table.column(c)[0].as_py() for c in ("case_id", "i", "j", "part")} | {
                "n": table.num_rows, "src": get("src", np.int32).tobytes(), "dst": get("dst", np.int32).tobytes(), "event": get("event_id").tobytes(), "start": get("start_us").tobytes(),
                "end": get("end_us").tobytes(), "x": x.tobytes(), "low": x.min(axis=0).tolist(), "high": x.max(axis=0).tolist(),
            }
            return pa.Table.from_pylist([row], schema=to)

        keys = ["case_id", "i", "j", "part"]
        tasks = max(1, -(-sum(self.edges_of.values()) // (4 * BLOCK_EDGES)))
        packed = plans.pin(rows.repartition(tasks, *keys).groupBy(*keys).applyInArrow(pack, _PACKED), "impact-edges")
        self._bounds = packed.select("case_id", "low", "high").collect()
        return packed

    def _cases(self, df: DataFrame, cases) -> DataFrame:
        return df.where(F.col("case_id").isin(list(cases)))

    def _beside(self, edges: DataFrame, vectors: DataFrame, at: str, name: str) -> DataFrame:
        """Edges with the vector of the block of one of their ends."""
        side = vectors.select(F.col("case_id").alias(f"{name}_case"), F.col("b").alias(f"{name}_b"), F.col("vec").alias(name))
        if 8 * sum(self.size.values()) <= BROADCAST_BYTES:
            side = F.broadcast(side)
        return edges.join(side, (F.col("case_id") == F.col(f"{name}_case")) & (F.col(at) == F.col(f"{name}_b")))

    def _start(self, fill: Callable[[int, int, int], np.ndarray]) -> DataFrame:
        """Vectors of all blocks: fill(case, block, size)."""
        size = self.size
        keys = self.spark.createDataFrame(list(size), "case_id bigint, b int")
        return plans.pin(_each(keys, lambda r: r | {"vec": fill(r["case_id"], r["b"], size[r["case_id"], r["b"]]).tobytes(), "change": 0.0}, _VECTOR), "impact-vectors")

    def projections(self, mode: str) -> dict[int, np.ndarray]:
        """Of each case, as :func:`tracelake.compare.projection` has it."""
        from tracelake.compare import direction

        out = {c: np.full(3, 1 / 3) for c in self.edges_of}
        active = {c for c, n in self.edges_of.items() if mode != "fixed" and n >= 4}
        if not active:
            return out
        scale, edges = self.scale, self.packed.select("case_id", "i", "j", "part", "event", "x")

        def ask(cases, fn) -> dict[int, list]:
            def run(r):
                low, span = scale[r["case_id"]]
                got = fn(r, (np.frombuffer(r["x"]).reshape(-1, 3) - low) / span)
                return {"case_id": r["case_id"], "i": r["i"], "j": r["j"], "part": r["part"], "got": np.asarray(got, dtype=float).ravel().tolist()}

            rows = _each(self._cases(edges, cases), run, "case_id bigint, i int, j int, part int, got array<double>").collect()
            return {c: [np.array(r.got) for r in sorted(rows, key=lambda r: (r.i, r.j, r.part)) if r.case_id == c] for c in cases}

        def ends(r, x):
            total, event = x.sum(axis=1), np.frombuffer(r["event"], dtype=np.int64)
            return np.concatenate([np.r_[t[k], event[k], x[k]] for t, k in ((total, total.argmin()), (-total, total.argmax()))])

        centres = {}
        for c, rows in ask(active, ends).items():
            centres[c] = np.array([min((tuple(r[at : at + 5]) for r in rows))[2:] for at in (0, 5)])
        split = lambda x, centre: ((x[:, None, :] - centre[None]) ** 2).sum(axis=2).argmin(axis=1)
        last: dict[int, tuple] = {}
        moving, rounds = set(active), 0
        while moving and rounds < 50:
            rounds += 1

            def sums(r, x, held=dict(centres)):
                near = split(x, held[r["case_id"]])
                return [[(near == k).sum(), *x[near == k].sum(axis=0)] for k in (0, 1)]

            for c, rows in ask(moving, sums).items():
                total = np.sum(rows, axis=0).reshape(2, 4)
                new = np.array([t[1:] / t[0] if t[0] else centres[c][k] for k, t in enumerate(total)])
                last[c] = centres[c], new
                if np.allclose(new, centres[c]):
                    moving.discard(c)
                else:
                    centres[c] = new

        def scatter(r, x, held=dict(last)):
            old, mean = held[r["case_id"]]
            near = split(x, old)
            off = x - mean[near]
            return off.T @ off

        for c, rows in ask(active, scatter).items():
            out[c] = direction(np.sum(rows, axis=0).reshape(3, 3), centres[c])
        return out

    def scores(self, mode: str, eps: float = 1e-6, most_rounds: int = 50) -> DataFrame:
        """Vectors of scores, as :func:`tracelake.compare.propagate` has them."""
        size, scale, across = self.size, self.scale, self.projections(mode)

        def weigh(r):
            low, span = scale[r["case_id"]]
            x = (np.frombuffer(r["x"]).reshape(-1, 3) - low) / span
            return np.clip(x @ across[r["case_id"]], 0.0, None) + 1e-9

        def add(r, value):
            vec = np.bincount(np.frombuffer(r["src"], dtype=np.int32), value, size[r["case_id"], r["i"]])
            at = np.flatnonzero(vec)  # a row of edges has few of a block's sources
            return {"case_id": r["case_id"], "b": r["i"], "j": r["j"], "part": r["part"], "at": at.tobytes(), "vec": vec[at].tobytes()}

        added = "case_id bigint, b int, j int, part int, at binary, vec binary"

        def whole(table: pa.Table) -> np.ndarray:
            rows = table.filter(pc.greater_equal(table.column("j"), 0)).sort_by([("j", "ascending"), ("part", "ascending")])
            out = np.zeros(size[table.column("case_id")[0].as_py(), table.column("b")[0].as_py()])
            for at, vec in zip(rows.column("at"), rows.column("vec")):
                out[np.frombuffer(at.as_py(), dtype=np.int64)] += np.frombuffer(vec.as_py())
            return out

        to = pa.schema([(n, _ARROW[t]) for n, t in (c.split() for c in _VECTOR.split(", "))])

        def one(table: pa.Table, vec: np.ndarray, change: float) -> pa.Table:
            return pa.Table.from_pylist([{"case_id": table.column("case_id")[0].as_py(), "b": table.column("b")[0].as_py(), "vec": vec.tobytes(), "change": change}], schema=to)

        parts = _each(self.packed.select("case_id", "i", "j", "part", "src", "x"), lambda r: add(r, weigh(r)), added)
        totals = plans.pin(parts.groupBy("case_id", "b").applyInArrow(lambda t: one(t, whole(t), 0.0), _VECTOR), "impact-totals")
        edges = self._beside(self.packed.select("case_id", "i", "j", "part", "src", "dst", "x"), totals, "i", "total")

        def share(r):
            total = np.frombuffer(r["total"])[np.frombuffer(r["src"], dtype=np.int32)]
            return {k: r[k] for k in ("case_id", "i", "j", "part", "src", "dst")} | {"w": (weigh(r) / total).tobytes()}

        edges = plans.pin(_each(edges, share, "case_id bigint, i int, j int, part int, src binary, dst binary, w binary"), "impact-weights")
        found = self.nodes.join(F.broadcast(self.spark.createDataFrame([(c, p.dst_id) for c, p in self.pois.items()], "case_id bigint, node string")), ["case_id", "node"])
        goal = {(r.case_id, r.block): r.place for r in found.select("case_id", "block", "place").collect()}

        def first(case, block, n):
            out = np.zeros(n)
            if (case, block) in goal:
                out[goal[case, block]] = 1.0
            return out

        def combine(table: pa.Table) -> pa.Table:
            key = table.column("case_id")[0].as_py(), table.column("b")[0].as_py()
            old = np.frombuffer(table.filter(pc.less(table.column("j"), 0)).column("vec")[0].as_py())
            new = np.minimum(whole(table), 1.0)
            if key in goal:
                new[goal[key]] = 1.0
            return one(table, new, float(np.abs(new - old).max()))

        vectors, done, active, rounds = self._start(first), [], set(self.edges_of), 0
        while active and rounds < most_rounds:
            rounds += 1
            near = self._beside(self._cases(edges, active), vectors, "j", "score")
            parts = _each(near, lambda r: add(r, np.frombuffer(r["w"]) * np.frombuffer(r["score"])[np.frombuffer(r["dst"], dtype=np.int32)]), added)
            old = vectors.select("case_id", "b", F.lit(-1).alias("j"), F.lit(-1).alias("part"), F.lit(None).cast("binary").alias("at"), "vec")
            vectors = plans.pin(parts.unionByName(old).groupBy("case_id", "b").applyInArrow(combine, _VECTOR), "impact-vectors")
            still = {r.case_id for r in vectors.groupBy("case_id").agg(F.max("change").alias("change")).where(F.col("change") >= eps).collect()}
            if active - still:
                done.append(self._cases(vectors, active - still))
                vectors = self._cases(vectors, still)
            active = still
        for d in done:
            vectors = vectors.unionByName(d)
        return vectors

    def ranked(self, scores: DataFrame, most: int) -> DataFrame:
        """The best nodes without incoming edges: case_id, block, place, rank within their kind."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for case, block, vec in zip(*(batch.column(k) for k in range(3))):
                    own = np.frombuffer(vec.as_py())
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(np.full(len(own), case.as_py())), pa.array(np.full(len(own), block.as_py(), dtype=np.int32)), pa.array(np.arange(len(own), dtype=np.int32)), pa.array(own)],
                        names=["case_id", "block", "place", "score"],
                    )

        each = scores.select("case_id", "b", "vec").mapInArrow(run, "case_id bigint, block int, place int, score double")
        entries = self.nodes.where("inward = 0").withColumn("kind", F.substring("node", 1, 1)).where(F.col("kind").isin("p", "f", "n"))
        rank = F.row_number().over(Window.partitionBy("case_id", "kind").orderBy(F.format_string("%.11e", "score").cast("double").desc(), "node"))
        return entries.join(each, ["case_id", "block", "place"]).withColumn("rank", rank).where(F.col("rank") <= most).select("case_id", "block", "place", "rank")

    def forward(self, scores: DataFrame, counts: list[int]) -> DataFrame:
        """Forward traces of the best 1, 2, ... entries of each kind inside the graphs: entries, case_id, event_id.

        More entries only lower the bounds, so each count goes on from those of the one before.
        """
        pois = {c: p.event_id for c, p in self.pois.items()}
        begin: dict[tuple, list] = {}
        for r in self.ranked(scores, max(counts)).collect():  # a few for each case and kind
            begin.setdefault((r.case_id, r.block), []).append((r.place, r.rank))

        def offers(r):
            """Lower bounds of the sinks than those known."""
            src, dst = (np.frombuffer(r[c], dtype=np.int32) for c in ("src", "dst"))
            start, end, low, old = (np.frombuffer(r[c], dtype=np.int64) for c in ("start", "end", "low", "old" if "old" in r else "low"))
            hit, new = end > low[src], old.copy()
            np.minimum.at(new, dst[hit], start[hit])
            at = np.flatnonzero(new < old)
            return {"case_id": r["case_id"], "b": r["j"], "at": at.tobytes(), "vec": new[at].tobytes()} if len(at) else None

        to = pa.schema([(n, _ARROW[t]) for n, t in (c.split() for c in _VECTOR.split(", "))])

        def combine(table: pa.Table) -> pa.Table:
            vec = np.frombuffer(table.filter(pc.is_null(table.column("at"))).column("vec")[0].as_py(), dtype=np.int64).copy()
            for at, own in zip(table.column("at"), table.column("vec")):
                if at.is_valid:
                    place = np.frombuffer(at.as_py(), dtype=np.int64)  # each once
                    vec[place] = np.minimum(vec[place], np.frombuffer(own.as_py(), dtype=np.int64))
            return pa.Table.from_pylist([{"case_id": table.column("case_id")[0].as_py(), "b": table.column("b")[0].as_py(), "vec": vec.tobytes(), "change": float(table.num_rows - 1)}], schema=to)

        def found(count: int):
            def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for batch in batches:
                    for at in range(batch.num_rows):
                        r = batch.slice(at, 1).to_pylist()[0]
                        event, end, low = (np.frombuffer(r[c], dtype=np.int64) for c in ("event", "end", "low"))
                        own = event[(end > low[np.frombuffer(r["src"], dtype=np.int32)]) | (event == pois[r["case_id"]])]
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), count, dtype=np.int32)), pa.array(np.full(len(own), r["case_id"])), pa.array(own)], names=["entries", "case_id", "event_id"])

            return run

        edges, across = self.packed.select("case_id", "i", "j", "src", "dst", "start", "end"), any(b for _, b in self.size)
        vectors, out = self._start(lambda case, block, n: np.full(n, FAR, dtype=np.int64)), None
        for count in sorted(counts):

            def enter(r, count=count):
                vec = np.frombuffer(r["vec"], dtype=np.int64).copy()
                vec[[place for place, rank in begin.get((r["case_id"], r["b"]), ()) if rank <= count]] = -FAR
                return r | {"vec": vec.tobytes(), "change": 0.0}

            vectors, done, active = plans.pin(_each(vectors, enter, _VECTOR), "impact-bounds"), [], set(self.edges_of)
            while active:
                near, offered = self._beside(self._cases(edges, active), vectors, "i", "low"), "case_id bigint, b int, at binary, vec binary"
                parts = _each(near.where("i = j"), offers, offered)
                if across:
                    parts = parts.unionByName(_each(self._beside(near.where("i != j"), vectors, "j", "old"), offers, offered))
                old = vectors.select("case_id", "b", F.lit(None).cast("binary").alias("at"), "vec")
                vectors = plans.pin(parts.unionByName(old).groupBy("case_id", "b").applyInArrow(combine, _VECTOR), "impact-bounds")
                still = {r.case_id for r in vectors.where("change > 0").select("case_id").distinct().collect()}
                done.append(self._cases(vectors, active - still))
                vectors, active = self._cases(vectors, still), still
            for d in done:
                vectors = vectors.unionByName(d)
            near = self._beside(self.packed.select("case_id", "i", "src", "event", "end"), vectors, "i", "low")
            own = near.select("case_id", "src", "event", "end", "low").mapInArrow(found(count), "entries int, case_id bigint, event_id bigint")
            out = own if out is None else out.unionByName(own)
        return out
