"""Near-duplicate vectors by cover-tree dual traversal, and nearest neighbours by collision counting."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tracelake.llm import common, components, grouped

COSINE = 0.93
#: Vectors that choose the cells of the top of the trees. Any choice gives the same links.
CENTRE_SAMPLE = 20_000
CELL = 2048
MOST_CELLS = 256
BLOCK = 2048
#: Inner nodes of one block's tree.
MOST_NODES = 128


def usable(vector: Column) -> Column:
    """False for a vector that is null, empty, zero or holds a null or non-finite component."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return vector.isNotNull() & ~F.coalesce(bad, F.lit(True)) & F.coalesce(F.exists(vector, lambda x: x != 0), F.lit(False))


def matrix(column) -> np.ndarray:
    """The vectors of a list column, of equal lengths, in double precision."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.zeros((0, 0))
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)


def unit(x: np.ndarray) -> np.ndarray:
    top = np.abs(x).max(axis=1, keepdims=True) if x.size else 1.0
    x = x / top
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    square = (a * a).sum(axis=1)[:, None] + (b * b).sum(axis=1)[None, :] - 2.0 * (a @ b.T)
    return np.sqrt(np.maximum(square, 0.0))


def greedy_order(x: np.ndarray, most: int, least: float) -> tuple[np.ndarray, np.ndarray]:
    """Points in the order of their distance to those before, and that distance.

    All points farther than r from their predecessors are a net of radius r, and
    the nets of falling radii are nested. Ends after ``most`` points or when all
    lie within ``least``.
    """
    chosen, radius = [0], [np.inf]
    near = distances(x, x[:1])[:, 0]
    while len(chosen) < min(most, len(x)):
        far = int(near.argmax())
        if near[far] <= least:
            break
        chosen.append(far)
        radius.append(float(near[far]))
        near = np.minimum(near, distances(x, x[far : far + 1])[:, 0])
    return np.array(chosen), np.array(radius)


class CoverTree:
    """Nested levels of centres with halving radii over the rows of ``x``.

    A level has the index of its centres, for each centre its parent's place in
    the level above, and the true covering radius of all points below it.
    """

    def __init__(self, x: np.ndarray, least: float) -> None:
        self.x = x
        order, gap = greedy_order(x, MOST_NODES, least)
        reach = [2.0]
        while reach[-1] > max(least, gap[-1] if len(gap) < MOST_NODES else least):
            reach.append(reach[-1] / 2)
        nets = sorted({max(1, int((gap > r).sum())) for r in reach} | {1, len(order)})
        self.levels = []
        above = None
        for size in nets:
            own = order[:size]
            if above is None:
                parent = np.zeros(size, dtype=np.int64)
                home = np.zeros(len(x), dtype=np.int64)
            else:
                # a point stays below its parent's centre: choose among the centre's children
                parent = above[own]
                d = distances(x, x[own])
                d[above[:, None] != parent[None, :]] = np.inf
                home = d.argmin(axis=1)
            reach_of = np.zeros(size)
            np.maximum.at(reach_of, home, np.sqrt(((x - x[own][home]) ** 2).sum(axis=1)))
            self.levels.append((own, parent, reach_of))
            above = home
        self.home = above

    def leaves(self) -> list[np.ndarray]:
        order = np.argsort(self.home, kind="stable")
        return np.split(order, np.cumsum(np.bincount(self.home, minlength=len(self.levels[-1][0])))[:-1])


def near_nodes(a: CoverTree, b: CoverTree, within: float) -> np.ndarray:
    """Dual traversal: pairs of lowest nodes that can hold points within ``within`` of each other.

    A pair is opened only if its parents' pair was, and survives if its centres
    are at most the two covering radii and the threshold apart. The tree with
    fewer levels waits at its last.
    """
    alive = np.ones((1, 1), dtype=bool)
    for k in range(max(len(a.levels), len(b.levels))):
        i, j = min(k, len(a.levels) - 1), min(k, len(b.levels) - 1)
        (ca, pa_, ra), (cb, pb, rb) = a.levels[i], b.levels[j]
        if k:
            alive = alive[pa_ if i == k else np.arange(len(ca))][:, pb if j == k else np.arange(len(cb))]
        alive = alive & (distances(a.x[ca], b.x[cb]) <= ra[:, None] + rb[None, :] + within + 1e-9)
    return alive


def links_between(a: np.ndarray, b: np.ndarray | None, cosine: float):
    """Yields (rows of a, rows of b, mask) that hold every pair with at least ``cosine``; b None: a with itself."""
    within = float(np.sqrt(max(0.0, 2.0 - 2.0 * cosine)))
    left = CoverTree(a, within / 2)
    right = left if b is None else CoverTree(b, within / 2)
    y = a if b is None else b
    alive, la, lb = near_nodes(left, right, within), left.leaves(), right.leaves()
    for i, rows in enumerate(la):
        cols = [lb[j] for j in np.flatnonzero(alive[i])]
        if len(rows) and cols:
            cols = np.sort(np.concatenate(cols))
            mask = a[rows] @ y[cols].T >= cosine
            if b is None:
                mask &= rows[:, None] != cols[None, :]
            if mask.any():
                yield rows, cols, mask


def _cells(classes: DataFrame) -> tuple[dict, int]:
    """Centres per (label, dimension) that has more than one cell: unit vectors in greedy order."""
    sizes = classes.groupBy("label", "dim").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > CELL)
    sizes = sizes.orderBy(F.desc("n"), "label", "dim").limit(1000).collect()
    total = sum(r["n"] for r in sizes)
    if not total:
        return {}, 0
    share = F.lit(0.0)
    for r in sizes:
        many = min(MOST_CELLS, -(-r["n"] // CELL)) * 8
        rate = min(1.0, many / r["n"], CENTRE_SAMPLE / total * 4)
        share = F.when((F.col("label") == r["label"]) & (F.col("dim") == r["dim"]), F.lit(rate)).otherwise(share)
    draw = F.shiftrightunsigned(F.col("c1"), 33) / F.lit(float(2**31))
    sample = classes.where(draw < share).select("label", "dim", "c1", "vector").orderBy("label", "dim", "c1").limit(CENTRE_SAMPLE).toArrow()
    keys = list(zip(sample.column("label").to_pylist(), sample.column("dim").to_pylist()))
    out = {}
    for r in sizes:
        own = [k for k, key in enumerate(keys) if key == (r["label"], r["dim"])]
        if len(own) > 1:
            x = unit(matrix(sample.column("vector").take(pa.array(own))))
            order, _ = greedy_order(x, min(MOST_CELLS, -(-r["n"] // CELL)), 0.0)
            out[(r["label"], r["dim"])] = x[order]
    return out, total


def near_duplicates(rows: DataFrame, cosine: float = COSINE, vec_id: str = "vec_id", vector: str = "embedding", label: str = "label") -> DataFrame:
    """Per row of ``rows``: vec_id, n_links, component_id, kept.

    Links are all pairs of vectors of one label (null: none) and one dimension
    whose cosine is at least ``cosine``. Equal vectors are one node with a
    multiplicity. Nodes go to the cell of the nearest centre of their label; two
    nodes within t of each other are in one cell, or the one is no farther than
    2 t from being in the other's cell, so each node also visits such cells of
    lower number. A cell is compared in blocks; a block pair runs the dual
    traversal and gives counts and a spanning forest, never pairs.

    Vectors that are null, empty, zero or hold a null or non-finite component
    have no links, their own component, and are kept. A row without vec_id is
    compared like the others; its component is null if it links with none. Rows
    that share a vec_id are vectors of their own. An empty table gives an empty
    result.
    """
    spark = rows.sparkSession
    n = common.partitions(spark)
    own = rows.select(F.col(vec_id).cast("bigint").alias("vec_id"), F.col(vector).cast("array<double>").alias("vector"), F.col(label).alias("label"))
    good = F.col("label").isNotNull() & usable(F.col("vector"))
    own = own.withColumn("c1", F.when(good, F.xxhash64("label", "vector"))).withColumn("c2", F.when(good, F.xxhash64(F.lit(7), "vector", "label")))
    classes = own.where(good).groupBy("c1", "c2").agg(
        F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("many"), F.first("label").alias("label"), F.first("vector").alias("vector")
    )
    classes = common.written(classes.withColumn("dim", F.size("vector")), "cover-classes")
    centres, _ = _cells(classes)
    within = float(np.sqrt(max(0.0, 2.0 - 2.0 * cosine)))

    def place(batches):
        for batch in batches:
            keys = list(zip(batch.column("label").to_pylist(), batch.column("dim").to_pylist()))
            cells, visits = [[0]] * len(keys), [[]] * len(keys)
            for key in {k for k in keys if k in centres}:
                at = [k for k, x in enumerate(keys) if x == key]
                d = distances(unit(matrix(batch.column("vector").take(pa.array(at)))), centres[key])
                home = d.argmin(axis=1)
                bound = d[np.arange(len(at)), home] + 2 * within + 1e-9
                for k, h, x in zip(at, home.tolist(), d <= bound[:, None]):
                    cells[k], visits[k] = [h], np.flatnonzero(x[:h]).tolist()
            where = pa.array([c + v for c, v in zip(cells, visits)], pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([*batch.columns, where], names=[*batch.schema.names, "cells"])

    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in classes.schema.fields)
    placed = common.written(classes.mapInArrow(place, f"{fields}, cells array<int>"), "cover-cells")
    narrow = placed.select("label", "dim", F.posexplode("cells").alias("pos", "cell"))
    counts = narrow.groupBy("label", "dim", "cell").agg(
        F.ceil(F.count_if(F.col("pos") == 0) / BLOCK).cast("int").alias("homes"), F.ceil(F.count_if(F.col("pos") > 0) / BLOCK).cast("int").alias("guests")
    )
    spread = placed.select("label", "dim", "c1", "c2", "rep", "many", "vector", F.posexplode("cells").alias("pos", "cell"))
    spread = spread.join(counts, ["label", "dim", "cell"]).where((F.col("homes") > 0) & ((F.col("pos") == 0) | (F.col("homes") > 0)))
    home = F.col("pos") == 0
    block = F.pmod(F.xxhash64("c1", "c2"), F.when(home, F.col("homes")).otherwise(F.col("guests"))).cast("int")
    spread = spread.withColumn("block", block)
    # A home block meets every home block and every guest block; a guest block every home block.
    others = F.when(home, F.sequence(F.lit(0), F.col("homes") + F.col("guests") - 1)).otherwise(F.sequence(F.lit(0), F.col("homes") - 1))
    spread = spread.withColumn("other", F.explode(others))
    meets_guest = home & (F.col("other") >= F.col("homes"))
    left = F.when(~home, F.col("other")).when(meets_guest, F.col("block")).otherwise(F.least("block", "other"))
    right = F.when(~home, F.col("homes") + F.col("block")).when(meets_guest, F.col("other")).otherwise(F.greatest("block", "other"))
    spread = spread.withColumn("left", left).withColumn("right", right)
    spread = spread.withColumn("first", home & (F.col("block") == F.col("left"))).withColumn("task", F.xxhash64("label", "dim", "cell", "left", "right"))

    def compare(batches):
        for table, bounds in grouped.whole_groups(batches, ["task", "left", "right"]):
            col = {k: table.column(k).to_numpy(zero_copy_only=False) for k in ("left", "right", "first", "c1", "c2", "rep", "many")}
            for s, e in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
                x = unit(matrix(table.column("vector").slice(s, e - s)))
                first = col["first"][s:e].astype(bool)
                same = col["left"][s] == col["right"][s]
                if not same and (first.all() or not first.any()):
                    continue
                ia = np.arange(e - s) if same else np.flatnonzero(first)
                ib = ia if same else np.flatnonzero(~first)
                found, forest, group = np.zeros(e - s, dtype=np.int64), [], np.arange(e - s)
                many = col["many"][s:e]
                for rows_, cols_, mask in links_between(x[ia], None if same else x[ib], cosine):
                    ra, rb = ia[rows_], ib[cols_]
                    found[ra] += mask @ many[rb]
                    if not same:
                        found[rb] += mask.T @ many[ra]
                    for k, r in enumerate(ra.tolist()):
                        near = rb[mask[k]]
                        roots, at = np.unique(group[near], return_index=True)
                        new = roots != group[r]
                        if new.any():
                            forest += [(r, int(near[p])) for p in at[new]]
                            group[np.isin(group, np.append(roots, group[r]))] = min(int(roots[0]), int(group[r]))
                at = np.flatnonzero(found)
                take = lambda c: col[c][s:e]  # noqa: B023, E731
                if len(at):
                    null = pa.nulls(len(at), pa.int64())
                    yield pa.RecordBatch.from_arrays([pa.array(take("c1")[at]), pa.array(take("c2")[at]), pa.array(found[at]), null, null], names=["c1", "c2", "found", "a", "b"])
                if forest:
                    null = pa.nulls(len(forest), pa.int64())
                    reps = pa.array(table.column("rep").slice(s, e - s).to_pylist(), pa.int64())
                    ends = [reps.take(pa.array([f[k] for f in forest])) for k in (0, 1)]
                    yield pa.RecordBatch.from_arrays([null, null, null, *ends], names=["c1", "c2", "found", "a", "b"])

    spread = spread.select("task", "left", "right", "first", "c1", "c2", "rep", "many", "vector")
    out = spread.repartition(n, "task").sortWithinPartitions("task", "left", "right").mapInArrow(compare, "c1 bigint, c2 bigint, found bigint, a bigint, b bigint")
    out = common.written(out, "cover-found")
    totals = out.where("found is not null").groupBy("c1", "c2").agg(F.sum("found").alias("found"))
    groups = components.components(out.where("a is not null and b is not null").select("a", "b"))
    known = classes.select("c1", "c2", "rep", "many").join(totals, ["c1", "c2"], "left").join(groups, F.col("rep") == F.col("node"), "left")
    known = known.select("c1", "c2", (F.coalesce("found", F.lit(0)) + F.col("many") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component"))
    result = own.select("vec_id", "c1", "c2").join(known, ["c1", "c2"], "left")
    return result.select(
        "vec_id", F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"), F.coalesce("component", "vec_id").alias("component_id")
    ).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


PROJECTIONS = 64
WIDTH = 2.7
COLLISIONS = 47
GROWTH = 1.25
#: Vectors of a cell, about; a cell of more than SEGMENT is indexed in parts.
NEAR_CELL = 8192
SEGMENT = 65_536
#: Centres of the cells come from a sample of this many vectors at most; any choice gives right answers.
MOST_CENTRES = 1024


class CollisionIndex:
    """Sorted single projections of one segment of vectors."""

    def __init__(self, x: np.ndarray, ids: np.ndarray, seed: int = 4) -> None:
        self.x, self.ids = x, ids
        self.lines = np.random.default_rng(seed).standard_normal((x.shape[1], PROJECTIONS))
        self.scale = max(float(np.abs(x).max()), 1e-300)
        shadow = (x / self.scale) @ self.lines
        n = len(ids)
        self.order = np.argsort(shadow, axis=0, kind="stable").T.ravel().copy()
        # The sorted lines one after the other, each moved beyond the one before,
        # are one sorted array: a window on every line is one look-up.
        self.span = 4.0 * float(np.abs(shadow).max()) + 1.0
        self.shift = np.arange(PROJECTIONS) * self.span
        self.flat = (np.sort(shadow, axis=0).T + self.shift[:, None]).ravel()
        self.first = np.arange(PROJECTIONS) * n
        self.start = max(float(shadow.std()) * 0.05, 1e-9)

    def nearest(self, q: np.ndarray, own_id: int, k: int, bound: float = np.inf) -> tuple[np.ndarray, np.ndarray]:
        """The k nearest found within ``bound``: ids and distances; ties go to the smaller id.

        The window around the query's place on every line grows with the radius.
        A vector that shares the windows of at least ``COLLISIONS`` lines is
        verified. The search ends when k verified vectors lie within the radius,
        when the radius reaches the bound, or when the windows hold everything. A round
        touches what its windows gain, not the whole segment.
        """
        n = len(self.ids)
        at = (q / self.scale) @ self.lines + self.shift
        low = np.clip(np.searchsorted(self.flat, at), self.first, self.first + n)
        high = low.copy()
        hits = np.zeros(n, dtype=np.uint8)
        ids, dist = np.zeros(0, np.int64), np.zeros(0)
        radius = self.start
        while True:
            a = np.clip(np.searchsorted(self.flat, at - WIDTH * radius / 2), self.first, low)
            b = np.clip(np.searchsorted(self.flat, at + WIDTH * radius / 2), high, self.first + n)
            begin, size = np.concatenate([a, high]), np.concatenate([low - a, b - high])
            low, high = a, b
            stop = np.cumsum(size)
            if stop[-1]:
                places = self.order[np.repeat(begin - (stop - size), size) + np.arange(stop[-1])]
                if 4 * len(places) < n:
                    met, times = np.unique(places, return_counts=True)
                else:  # counting by place costs the segment once, less than sorting so many
                    times = np.bincount(places, minlength=n)
                    met = np.flatnonzero(times)
                    times = times[met]
                before = hits[met]
                hits[met] = before + times.astype(np.uint8)
                new = met[(hits[met] >= COLLISIONS) & (before < COLLISIONS)]
                new = new[self.ids[new] != own_id]
                if len(new):
                    d = np.sqrt(((self.x[new] - q) ** 2).sum(axis=1))
                    ids, dist = np.append(ids, self.ids[new]), np.append(dist, d)
                    best = np.lexsort((ids, dist))[:k]
                    ids, dist = ids[best], dist[best]
            if (len(ids) >= k and dist[-1] <= radius * self.scale) or radius * self.scale >= bound:
                break
            if (high - low == n).all():
                break
            radius *= GROWTH
        return ids, dist


def _near_centres(base: DataFrame, count: int) -> dict[int, np.ndarray]:
    """Centres by dimension, in greedy order, from a sample by hash. Their number follows the number of vectors."""
    share = min(1.0, 2.0 * CENTRE_SAMPLE / max(count, 1))
    draw = F.shiftrightunsigned(F.xxhash64("vec_id", "vector"), 33) / F.lit(float(2**31))
    held = base.where(draw < share).select("dim", "vector").limit(CENTRE_SAMPLE * 4).toArrow()  # about 2 * CENTRE_SAMPLE rows
    dims = held.column("dim").to_numpy()
    out = {}
    for dim in np.unique(dims).tolist():
        own = np.flatnonzero(dims == dim)
        x = matrix(held.column("vector").take(pa.array(own)))
        many = max(1, min(MOST_CENTRES, round(count * len(own) / len(dims) / NEAR_CELL)))
        x = x[np.random.default_rng(3).permutation(len(x))[: 16 * many]]
        order, _ = greedy_order(x, many, 0.0)
        out[dim] = x[order]
    return out


def _from_centres(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    with np.errstate(all="ignore"):
        return distances(x, centres)


def nearest(rows: DataFrame, queries: DataFrame, k: int = 10, vec_id: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """Per query its k nearest rows found: query_id, rank, vec_id, score (Euclidean distance).

    Both frames have vec_id and a vector. Every usable row is indexed in the cell of its
    nearest centre; large cells in several segments. A query first asks its own cell; the
    k-th distance found there bounds what is worth finding, and by the triangle inequality
    only cells whose centre is nearer than the bound and the cell's radius are asked then. So
    cells cost no neighbour, whatever the centres; data without structure make a query ask
    all cells. Rows with the query's own vec_id are no candidates; ties go to the
    smaller vec_id. Unusable vectors, vectors of another dimension than the
    query's, and rows without vec_id take no part. Repeated rows are candidates
    each. Without queries or rows the result is empty.
    """

    def clean(df):
        out = df.select(F.col(vec_id).cast("bigint").alias("vec_id"), F.col(vector).cast("array<double>").alias("vector"))
        return out.where(usable(F.col("vector")) & F.col("vec_id").isNotNull()).withColumn("dim", F.size("vector"))

    base, asked = clean(rows), clean(queries)
    centres = _near_centres(base, base.count())

    def place(batches):
        for batch in batches:
            dims = batch.column("dim").to_numpy()
            cell, far = np.zeros(len(dims), dtype=np.int32), np.full(len(dims), np.inf)
            for dim in np.unique(dims).tolist():
                at = np.flatnonzero(dims == dim)
                if dim in centres:
                    d = np.nan_to_num(_from_centres(matrix(batch.column("vector").take(pa.array(at))), centres[dim]), nan=np.inf)
                    cell[at], far[at] = d.argmin(axis=1), d.min(axis=1)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(cell), pa.array(far)], names=[*batch.schema.names, "cell", "far"])

    fields = "vec_id bigint, vector array<double>, dim int"
    base = common.written(base.mapInArrow(place, f"{fields}, cell int, far double"), "near-base")
    # At most MOST_CENTRES rows for each dimension.
    cells = {(r.dim, r.cell): (r.n, r.radius) for r in base.groupBy("dim", "cell").agg(F.count(F.lit(1)).alias("n"), F.max("far").alias("radius")).collect()}
    first, many = {}, 0  # each cell's first segment
    for key in sorted(cells):
        first[key] = many
        many += -(-cells[key][0] // SEGMENT)
    if not many:
        return asked.select(F.col("vec_id").alias("query_id"), F.lit(1).alias("rank"), "vec_id", F.lit(0.0).alias("score")).where(F.lit(False))

    def segments_of(key):
        return range(first[key], first[key] + -(-cells[key][0] // SEGMENT))

    def ask(batches):
        """Segments to ask: of the nearest cell without a bound, of all others that the bound allows with one."""
        for batch in batches:
            dims, bounds = batch.column("dim").to_numpy(), batch.column("bound").to_numpy(zero_copy_only=False)
            lists = [[] for _ in dims]
            for dim in np.unique(dims).tolist():
                keys = [key for key in sorted(cells) if key[0] == dim]
                if not keys:
                    continue
                at = np.flatnonzero(dims == dim)
                x, c = matrix(batch.column("vector").take(pa.array(at))), centres.get(dim)
                if c is None:  # no vector of this dimension was drawn, so all are in one cell
                    d = np.zeros((len(at), 1))
                else:
                    own = c[[key[1] for key in keys]]
                    d = np.nan_to_num(_from_centres(x, own), nan=0.0, posinf=0.0)
                    # The distances are sums that cancel; what they may be off by never leaves a cell out.
                    d -= 1e-6 * (np.abs(x).max(axis=1)[:, None] + np.abs(own).max(axis=1)[None, :]) * np.sqrt(x.shape[1])
                radius = np.array([cells[key][1] for key in keys])
                for row, k_ in enumerate(at.tolist()):
                    home = int(d[row].argmin())
                    if np.isnan(bounds[k_]):
                        lists[k_] = list(segments_of(keys[home]))
                    else:
                        near = np.flatnonzero(d[row] - radius <= bounds[k_])
                        lists[k_] = [s for j in near.tolist() if j != home for s in segments_of(keys[j])]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(lists, pa.list_(pa.int32()))], names=[*batch.schema.names, "segments"])

    def search(batches):
        # Rows of a segment come before its queries, so only the segment is held;
        # the queries, however many, pass by.
        here, held, index = None, [], None
        for batch in batches:
            bounds = grouped.starts(batch, ["segment", "dim", "asks"])
            for s, e in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
                part = batch.slice(s, e - s)
                place = (part.column("segment")[0].as_py(), part.column("dim")[0].as_py())
                if place != here:
                    here, held, index = place, [], None
                if not part.column("asks")[0].as_py():
                    held.append(part)
                    continue
                if held:
                    table, held = pa.Table.from_batches(held), []
                    index = CollisionIndex(matrix(table.column("vector")), table.column("vec_id").to_numpy())
                if index is None:
                    continue
                own_ids, most = part.column("vec_id").to_numpy(), np.nan_to_num(part.column("bound").to_numpy(zero_copy_only=False), nan=np.inf)
                for q, own_id, top in zip(matrix(part.column("vector")), own_ids.tolist(), most.tolist()):
                    found, score = index.nearest(q, own_id, k, top)
                    if len(found):
                        query = pa.array(np.full(len(found), own_id))
                        yield pa.RecordBatch.from_arrays([query, pa.array(found), pa.array(score)], names=["query_id", "vec_id", "score"])

    table = rows.sparkSession.createDataFrame([(*key, first[key], len(segments_of(key))) for key in sorted(cells)], "c_dim int, c_cell int, c_first int, c_many int")
    indexed = base.join(F.broadcast(table), (F.col("dim") == F.col("c_dim")) & (F.col("cell") == F.col("c_cell")))
    segment = (F.col("c_first") + F.pmod(F.xxhash64("vec_id"), F.col("c_many"))).cast("int")
    indexed = indexed.select("vec_id", "vector", "dim", F.lit(None).cast("double").alias("bound"), segment.alias("segment"), F.lit(False).alias("asks"))

    def found_by(asks):
        spread = asks.mapInArrow(ask, f"{fields}, bound double, segments array<int>")
        spread = spread.select("vec_id", "vector", "dim", "bound", F.explode("segments").alias("segment"), F.lit(True).alias("asks"))
        # By range, as hashes of few segment numbers would put several into one task.
        both = indexed.unionByName(spread).repartitionByRange(many, "segment").sortWithinPartitions("segment", "dim", "asks")
        return common.written(both.mapInArrow(search, "query_id bigint, vec_id bigint, score double"), "near-found")

    by_query = Window.partitionBy("query_id").orderBy("score", "vec_id")
    asked = common.written(asked, "near-queries")
    at_home = found_by(asked.withColumn("bound", F.lit(float("nan"))))
    # Queries that share a vec_id have one answer; the farthest bound of theirs holds for all.
    kth = at_home.withColumn("r", F.row_number().over(by_query)).where(F.col("r") == k).select(F.col("query_id").alias("b_id"), F.col("score").alias("b_score"))
    again = asked.join(kth, F.col("vec_id") == F.col("b_id"), "left").select("vec_id", "vector", "dim", F.coalesce("b_score", F.lit(float("inf"))).alias("bound"))
    found = at_home.unionByName(found_by(again))
    rank = F.row_number().over(by_query)
    return found.select("query_id", rank.cast("int").alias("rank"), "vec_id", "score").where(F.col("rank") <= k)
