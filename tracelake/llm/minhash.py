"""Near-duplicate documents by min-max hashing, with every link confirmed on full shingle sets.

Each of ``PERMUTATIONS`` hash functions is evaluated once per shingle and gives
two signature slots: its smallest and its largest value. Both agree between two
sets with the probability of their Jaccard similarity, so half the evaluations
give the signature, and the estimate from both has the lower variance. Slots are
banded; documents that share a band meet.

Groups of copies never turn into all their pairs:

* equal sets are one node from the start;
* while buckets hold many pairs, a *star round* compares each member of a bucket
  with one centre only. What is linked by then is one component, and pairs inside
  a component need no comparison, so a large group of near copies costs about as
  many comparisons as it has members, and its buckets drop out;
* the pairs that are left, of different components, are compared inside tasks, in
  blocks, on one-byte sketches of the signatures; a pair that an earlier band has
  already brought together is left out, told by 32 bits of the band keys (one
  slot byte each would take some pairs that never met for met, and lose them);
* what leaves such a task is one row per member with the list of its partners,
  only for partners whose estimate is at most :func:`margin` below the threshold
  (about five standard deviations of the estimate at the threshold);
* the same tasks then get the members' texts, compare full sets, and give a
  spanning forest of the confirmed links. Blocks are cut by members and by
  shingles, so a task's texts stay bounded but for a single very long one.
"""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracelake.llm import common, components, grouped, textvec
from tracelake.llm.textvec import U

PERMUTATIONS = 64
#: Bands are as long as they can be with at most this probability to miss a pair at the threshold.
MISSED = 1e-6
BLOCK = 1024
#: Shingles of a block's members together, about.
BLOCK_SHINGLES = 2**20
#: Star rounds go on while a member has more pairs than this left, on average, and as long as they halve the pairs.
FEW_PAIRS = 16
#: Standard deviations of the estimate.
DEVIATIONS = 4.911
#: Up to so many ids of documents to compare, texts are filtered by a broadcast of them.
BROADCAST_IDS = 2_000_000
#: 100 * intersection >= PERCENT * union, where no other percentage is given.
PERCENT = 85
K = 5

_RNG = np.random.default_rng(85)
_A = _RNG.integers(0, 2**63, PERMUTATIONS, dtype=U) * U(2) + U(1)
_B = _RNG.integers(0, 2**63, PERMUTATIONS, dtype=U)
_MIX = _RNG.integers(0, 2**63, 2 * PERMUTATIONS, dtype=U) * U(2) + U(1)


def band_rows(percent: int) -> int:
    """Slots of a band for a threshold."""
    missed = lambda rows: (1 - (percent / 100) ** rows) ** (2 * PERMUTATIONS // rows)
    return max((r for r in range(1, 2 * PERMUTATIONS + 1) if missed(r) <= MISSED), default=1)


#: Bytes of a sketch at the default threshold: one for each slot, then four for each band's key.
SKETCH = 2 * PERMUTATIONS + 4 * (2 * PERMUTATIONS // band_rows(PERCENT))


def margin(percent: int) -> float:
    """How far below the threshold an estimate may be."""
    return DEVIATIONS * (percent / 100 * (1 - percent / 100) / (2 * PERMUTATIONS)) ** 0.5


def min_max(sets: list[np.ndarray]) -> np.ndarray:
    """Signatures, one row per non-empty set: minimum and maximum of every permutation in turn."""
    every = np.concatenate(sets)
    starts = np.concatenate([[0], np.cumsum([len(s) for s in sets[:-1]])]).astype(np.int64)
    out = np.empty((len(sets), 2 * PERMUTATIONS), dtype=U)
    for p in range(PERMUTATIONS):
        values = every * _A[p] + _B[p]
        out[:, 2 * p] = np.minimum.reduceat(values, starts)
        out[:, 2 * p + 1] = np.maximum.reduceat(values, starts)
    return out


def signatures(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """Per row of ``docs``: doc_id, text_hash, n_shingles, h1 and h2 (hash of the set), keys (of the bands), sketch.

    A sketch has a byte for each slot, then four for each band's key. A text
    without words, or null, has n_shingles 0 and nulls.
    """
    each = band_rows(percent)
    count = 2 * PERMUTATIONS // each
    width = 2 * PERMUTATIONS + 4 * count

    def sign(batches):
        for batch in batches:
            data, offsets = textvec.raw(batch.column("text"))
            for a, b in textvec.slices(np.diff(offsets)):
                base = offsets[a]
                sets = textvec.shingle_sets(data[base : offsets[b]], offsets[a : b + 1] - base, K)
                size = np.array([len(s) for s in sets], dtype=np.int64)
                full = size > 0
                own = [s for s in sets if len(s)]
                h = np.zeros((2, b - a), dtype=U)
                keys, sketches = np.zeros((0, count), dtype=U), np.zeros((0, width), dtype=np.uint8)
                if own:
                    slots = min_max(own)
                    bands = (slots * _MIX)[:, : count * each].reshape(-1, count, each).sum(axis=2, dtype=U)
                    keys = textvec.mixed(bands + np.arange(count, dtype=U))
                    sketches = np.hstack([((slots >> U(24)) ^ slots).astype(np.uint8), keys.astype("<u4").view(np.uint8)])
                    starts = np.concatenate([[0], np.cumsum(size[full])[:-1]])
                    every = np.concatenate(own)
                    h[0, full] = textvec.mixed(np.add.reduceat(textvec.mixed(every + U(1)), starts) + size[full].astype(U))
                    h[1, full] = textvec.mixed(np.add.reduceat(textvec.mixed(every ^ U(0x5DEECE66D)), starts))
                mask = pa.array(~full)
                lists = np.full((b - a, count), 0, dtype=U)
                lists[full] = keys
                blobs = iter(sketches)
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("doc_id").slice(a, b - a).cast(pa.int64()),
                        batch.column("text_hash").slice(a, b - a),
                        pa.array(size),
                        pa.array(h[0].view(np.int64), mask=mask.to_numpy(zero_copy_only=False)),
                        pa.array(h[1].view(np.int64), mask=mask.to_numpy(zero_copy_only=False)),
                        pa.ListArray.from_arrays(np.arange(0, (b - a + 1) * count, count, dtype=np.int32), pa.array(lists.ravel().view(np.int64))),
                        pa.array([next(blobs).tobytes() if x else None for x in full.tolist()], pa.binary()),
                    ],
                    names=["doc_id", "text_hash", "n_shingles", "h1", "h2", "keys", "sketch"],
                )

    rows = docs.select("doc_id", "text", F.xxhash64("text").alias("text_hash"))
    return rows.mapInArrow(sign, "doc_id bigint, text_hash bigint, n_shingles bigint, h1 bigint, h2 bigint, keys array<bigint>, sketch binary")


def _block_pairs(m: int, sides: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs of a group: all of them, or only those across its two blocks."""
    if sides is None:
        return np.triu_indices(m, 1)
    left, right = np.flatnonzero(sides), np.flatnonzero(~sides)
    return np.repeat(left, len(right)), np.tile(right, len(left))


def _close(sketch: np.ndarray, band: int, i: np.ndarray, j: np.ndarray, percent: int = PERCENT) -> np.ndarray:
    """Which pairs of a bucket of ``band`` are worth a full comparison, in this bucket."""
    keep = np.zeros(len(i), dtype=bool)
    least = (percent / 100 - margin(percent)) * 2 * PERMUTATIONS
    slots = sketch[:, : 2 * PERMUTATIONS]
    keys = np.ascontiguousarray(sketch[:, 2 * PERMUTATIONS :]).view("<u4")[:, :band]
    for a in range(0, len(i), 20_000):
        x, y = i[a : a + 20_000], j[a : a + 20_000]
        good = (slots[x] == slots[y]).sum(axis=1) >= least
        at = np.flatnonzero(good)
        if band and len(at):
            earlier = (keys[x[at]] == keys[y[at]]).any(axis=1)
            good[at[earlier]] = False
        keep[a : a + 20_000] = good
    return keep


def _candidates(batches, percent):
    """Rows (task, node, partners) for the buckets, or block pairs of buckets, of a sorted stream."""
    for table, bounds in grouped.whole_groups(batches, ["key", "left", "right"]):
        cols = {n: table.column(n).to_numpy(zero_copy_only=False) for n in ("task", "band", "left", "right", "block", "node", "component", "size")}
        sketch = np.frombuffer(b"".join(table.column("sketch").to_pylist()), dtype=np.uint8).reshape(table.num_rows, -1)
        task, node, partners = [], [], []
        for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
            if b - a < 2:
                continue
            sides = None if cols["left"][a] == cols["right"][a] else cols["block"][a:b] == cols["left"][a]
            i, j = _block_pairs(b - a, sides)
            own, size = cols["component"][a:b], cols["size"][a:b]
            apart = (own[i] != own[j]) & (100 * np.minimum(size[i], size[j]) >= percent * np.maximum(size[i], size[j]))
            i, j = i[apart], j[apart]
            keep = _close(sketch[a:b], int(cols["band"][a]), i, j, percent)
            i, j = i[keep], j[keep]
            if not len(i):
                continue
            order = np.argsort(i, kind="stable")
            i, j = i[order], j[order]
            own, at = np.unique(i, return_index=True)
            lists = dict(zip(own.tolist(), np.split(cols["node"][a:b][j], at[1:])))
            for k in np.union1d(i, j).tolist():
                task.append(int(cols["task"][a]))
                node.append(int(cols["node"][a + k]))
                partners.append(lists.get(k, np.zeros(0, np.int64)))
        if task:
            yield pa.RecordBatch.from_arrays([pa.array(task, pa.int64()), pa.array(node, pa.int64()), pa.array(partners, pa.list_(pa.int64()))], names=["task", "node", "partners"])


def _shared(mine: np.ndarray, many: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Sizes of intersections of one sorted set with others, and the others' sizes."""
    sizes = np.array([len(s) for s in many])
    joined = np.concatenate(many)
    hit = mine[np.minimum(np.searchsorted(mine, joined), len(mine) - 1)] == joined
    return np.add.reduceat(hit, np.concatenate([[0], np.cumsum(sizes)[:-1]]), dtype=np.int64), sizes


def _sets(column) -> list[np.ndarray]:
    data, offsets = textvec.raw(column)
    out: list[np.ndarray] = []
    for a, b in textvec.slices(np.diff(offsets)):
        out += textvec.shingle_sets(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], K)
    return out


def _confirm(batches, percent):
    """Links (a, b) of nodes on full sets: a spanning forest of each task's."""
    for table, bounds in grouped.whole_groups(batches, ["task"]):
        nodes = table.column("node").to_numpy(zero_copy_only=False)
        partners = table.column("partners").to_pylist()
        sets = _sets(table.column("text"))
        left, right = [], []
        for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
            places = {int(n): k for k, n in enumerate(nodes[a:b].tolist())}
            forest = grouped.Forest(b - a)
            for k in range(a, b):
                others = [p for n in partners[k] if (p := places[n]) != k - a and forest.root(p) != forest.root(k - a)]
                if not others:
                    continue
                shared, sizes = _shared(sets[k], [sets[a + p] for p in others])
                for p in np.flatnonzero(100 * shared >= percent * (len(sets[k]) + sizes - shared)).tolist():
                    forest.join(k - a, others[p])
            for x, y in forest.links:
                left.append(int(nodes[a + x]))
                right.append(int(nodes[a + y]))
        if left:
            yield pa.RecordBatch.from_arrays([pa.array(left, pa.int64()), pa.array(right, pa.int64())], names=["a", "b"])


def _near(batches, percent):
    """Of rows (node, centre, two sketches) those whose estimate is worth a full comparison."""
    least = (percent / 100 - margin(percent)) * 2 * PERMUTATIONS
    for batch in batches:
        if not batch.num_rows:
            continue
        own, centre = (np.frombuffer(b"".join(batch.column(c).to_pylist()), dtype=np.uint8).reshape(batch.num_rows, -1)[:, : 2 * PERMUTATIONS] for c in ("sketch", "c_sketch"))
        keep = pa.array((own == centre).sum(axis=1) >= least)
        yield batch.select(["node", "centre"]).filter(keep)


def _stars(batches, percent):
    """Links (a, b) of rows (node, centre, two texts); the rows of a centre follow each other."""
    last, held = None, None
    for batch in batches:
        nodes, centres = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("node", "centre"))
        texts, hubs = batch.column("text"), batch.column("c_text")
        linked = np.zeros(batch.num_rows, dtype=bool)
        for a, b in textvec.slices(pc.binary_length(texts).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)):
            for k, mine in enumerate(_sets(texts.slice(a, b - a)), a):
                if centres[k] != last:
                    last, held = centres[k], _sets(hubs.slice(k, 1))[0]
                shared, sizes = _shared(held, [mine])
                linked[k] = 100 * shared[0] >= percent * (len(held) + sizes[0] - shared[0])
        yield pa.RecordBatch.from_arrays([pa.array(nodes[linked]), pa.array(centres[linked])], names=["a", "b"])


def _texts(docs: DataFrame, sets: DataFrame, nodes: DataFrame) -> DataFrame:
    """node and text for the wanted ``nodes`` (written): one row each, however often a row is repeated."""
    wanted = sets.select("node", "rep", "text_hash").join(nodes.select(F.col("node").alias("w")), F.col("node") == F.col("w"), "left_semi")
    wanted = common.written(wanted, "minhash-wanted")
    if wanted.count() <= BROADCAST_IDS:  # else the join shuffles all texts once
        wanted = F.broadcast(wanted)
    rows = docs.select(F.col("doc_id").alias("t_id"), "text", F.xxhash64("text").alias("t_hash"))
    rows = rows.join(wanted, (F.col("t_id") == F.col("rep")) & (F.col("t_hash") == F.col("text_hash")))
    return rows.groupBy("node").agg(F.first("text").alias("text"))


def _star_round(docs: DataFrame, sets: DataFrame, members: DataFrame, percent: int, turn: int) -> DataFrame:
    """Links between members and one centre of each bucket (the smallest node, later a random one)."""
    order = F.struct((F.xxhash64("node", F.lit(turn)) if turn else F.lit(0).cast("bigint")).alias("h"), "node", "component", "size")
    centres = members.groupBy(F.col("key").alias("c_key")).agg(F.min(order).alias("c"))
    ratio = 100 * F.least("size", "c.size") >= percent * F.greatest("size", "c.size")
    pairs = members.join(centres, F.col("key") == F.col("c_key")).where((F.col("component") != F.col("c.component")) & ratio)
    pairs = pairs.select("node", F.col("c.node").alias("centre")).distinct()
    sketches = sets.select("node", "sketch")
    pairs = pairs.join(sketches, "node").join(sketches.toDF("centre", "c_sketch"), "centre").select("node", "centre", "sketch", "c_sketch")
    pairs = common.written(pairs.mapInArrow(partial(_near, percent=percent), "node bigint, centre bigint"), "minhash-stars")
    texts = common.written(_texts(docs, sets, pairs.select(F.explode(F.array("node", "centre")).alias("node")).distinct()), "minhash-texts")
    rows = pairs.join(texts, "node").join(texts.toDF("centre", "c_text"), "centre").select("node", "centre", "text", "c_text")
    return rows.mapInArrow(partial(_stars, percent=percent), "a bigint, b bigint")


def _with_components(members: DataFrame, links: DataFrame | None) -> DataFrame:
    """Members with their component so far, of the buckets that hold more than one; written."""
    if links is not None:
        known = components.components(links)
        members = members.drop("component").join(known.toDF("k_node", "component"), F.col("node") == F.col("k_node"), "left").drop("k_node")
        members = members.withColumn("component", F.coalesce("component", "node"))
    mixed = members.groupBy(F.col("key").alias("m_key")).agg(F.min("component").alias("low"), F.max("component").alias("high")).where("low < high")
    return common.written(members.join(mixed.select("m_key"), F.col("key") == F.col("m_key"), "left_semi"), "minhash-members")


def _pairs_left(members: DataFrame) -> tuple[int, int]:
    """Pairs of members of one bucket and different components, and members."""
    per = members.groupBy("key", "component").agg(F.count(F.lit(1)).cast("double").alias("n"))
    per = per.groupBy("key").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("n")).alias("inside"))
    pairs, rows = per.agg(F.sum((F.col("n") * F.col("n") - F.col("inside")) / 2), F.sum("n")).first()
    return int(pairs or 0), int(rows or 0)


def _links(docs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) of nodes whose components are those of all pairs at the threshold."""
    n = common.partitions(docs.sparkSession)
    members = sets.select("node", F.col("n_shingles").alias("size"), F.posexplode("keys").alias("band", "key"))
    members = _with_components(members.withColumn("component", F.col("node")), None)
    links, (pairs, rows) = None, _pairs_left(members)
    turn, before = 0, None
    while pairs > FEW_PAIRS * rows and (before is None or pairs <= before / 2):
        new = common.written(_star_round(docs, sets, members, percent, turn), "minhash-links")
        links = new if links is None else links.unionByName(new)
        members = _with_components(members, links)
        turn, before, (pairs, rows) = turn + 1, pairs, _pairs_left(members)
    crowds = members.groupBy(F.col("key").alias("c_key")).agg(
        F.ceil(F.greatest(F.count(F.lit(1)) / BLOCK, F.sum("size") / BLOCK_SHINGLES)).cast("int").alias("blocks")
    )
    met = members.join(crowds, F.col("key") == F.col("c_key"))
    met = met.withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    met = met.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    met = met.withColumn("left", F.least("block", "other")).withColumn("right", F.greatest("block", "other"))
    met = met.select("key", "band", "left", "right", "block", "node", "component", "size", F.xxhash64("key", "left", "right").alias("task"))
    met = met.join(sets.select("node", "sketch"), "node")
    near = met.repartition(n, "task").sortWithinPartitions("key", "left", "right").mapInArrow(partial(_candidates, percent=percent), "task bigint, node bigint, partners array<bigint>")
    near = common.written(near, "minhash-near")
    texts = _texts(docs, sets, near.select("node").distinct())
    tasks = near.join(texts, "node").select("task", "node", "partners", "text")
    last = tasks.repartition(n, "task").sortWithinPartitions("task").mapInArrow(partial(_confirm, percent=percent), "a bigint, b bigint")
    return last if links is None else links.unionByName(last)


def _found(docs: DataFrame, percent: int) -> DataFrame:
    """Per row of ``docs``: doc_id, text_hash, n_shingles, component_id, group (null for a row that is linked with nothing)."""
    signed = common.written(signatures(docs, percent), "minhash-signatures")
    of_id = F.struct("doc_id", "text_hash")
    sets = signed.where("h1 is not null and doc_id is not null").groupBy("h1", "h2").agg(
        F.min(of_id).alias("id"), F.first("n_shingles").alias("n_shingles"), F.first("keys").alias("keys"), F.first("sketch").alias("sketch")
    )
    # Two sets can have one smallest doc_id; a node is a set, by a number that is unique and, once written, stays.
    sets = sets.select("h1", "h2", F.col("id.doc_id").alias("rep"), F.col("id.text_hash").alias("text_hash"), F.monotonically_increasing_id().alias("node"), "n_shingles", "keys", "sketch")
    sets = common.written(sets, "minhash-sets")
    groups = components.components(_links(docs, sets, percent)).toDF("g_node", "group")
    grouped_ = sets.select("h1", "h2", "rep", "node").join(groups, F.col("node") == F.col("g_node"), "left").withColumn("group", F.coalesce("group", "node"))
    least = grouped_.where("g_node is not null").groupBy(F.col("group").alias("l_group")).agg(F.min("rep").alias("least"))
    of_set = grouped_.join(least, F.col("group") == F.col("l_group"), "left")
    of_set = of_set.select(F.col("h1").alias("s1"), F.col("h2").alias("s2"), "group", F.coalesce("least", "rep").alias("component"))
    found = signed.join(of_set, (F.col("h1") == F.col("s1")) & (F.col("h2") == F.col("s2")), "left")
    has_id = F.col("doc_id").isNotNull()
    return found.select(
        "doc_id", "text_hash", "n_shingles", F.when(has_id, F.coalesce("component", "doc_id")).alias("component_id"), F.when(has_id, F.col("group")).alias("group")
    )


def near_duplicates(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """Per row of ``docs``: doc_id, n_shingles, component_id, kept.

    Reads doc_id and text. Documents of a Jaccard similarity of ``percent`` or more
    are linked; bands and margin follow it. component_id is the smallest doc_id that links reach;
    kept says that it is the row's own. Rows that share a doc_id and
    differ in text are compared as documents of their own. A text without words links with nothing; a row without
    doc_id is linked with nothing, has component_id null and is kept. An empty
    table gives an empty result.
    """
    kept = F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True))
    return _found(docs, percent).select("doc_id", "n_shingles", "component_id", kept.alias("kept"))


def one_of_each(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """One row of each group of near-duplicates, with the columns of ``docs``; needs doc_id and text.

    It is the row of the smallest doc_id, of several texts under that id the one with the
    smallest hash, of rows that repeat id and text any one. Rows that share a doc_id and differ in
    text are documents of their own. Rows without doc_id or words are in no group and stay.
    An empty table gives an empty result.
    """
    t_id, t_hash, l_id, l_hash, held = common.fresh(docs, "t_id", "t_hash", "l_id", "l_hash", "held")
    found = common.written(_found(docs.select("doc_id", "text"), percent).where("group is not null"), "minhash-groups")
    # Rows of the smallest id of a group are few texts, however often they are repeated.
    first = found.where("doc_id = component_id").groupBy("group", "doc_id", "text_hash").agg(F.count(F.lit(1)).alias("rows"))
    chosen = first.groupBy(F.col("group").alias("c_group")).agg(F.min("text_hash").alias("one"), F.sum("rows").alias("all")).where("all > 1")
    first = common.written(first.join(chosen, F.col("group") == F.col("c_group")), "minhash-first")
    lost = found.where("doc_id <> component_id").select("doc_id", "text_hash").unionByName(first.where("text_hash <> one").select("doc_id", "text_hash"))
    rows = docs.withColumn(t_hash, F.xxhash64("text"))
    same = (F.col("doc_id") == F.col(l_id)) & (F.col(t_hash) == F.col(l_hash))
    rows = rows.join(lost.distinct().toDF(l_id, l_hash), same, "left_anti")
    repeated = first.where("text_hash = one and rows > 1").select("doc_id", "text_hash").toDF(l_id, l_hash)
    if repeated.isEmpty():
        return rows.select(*docs.columns)
    once = rows.join(repeated, same, "left_semi").groupBy(F.col("doc_id").alias(t_id), F.col(t_hash)).agg(F.first(F.struct(*docs.columns)).alias(held))
    return rows.join(repeated, same, "left_anti").select(*docs.columns).unionByName(once.select(f"{held}.*"))
