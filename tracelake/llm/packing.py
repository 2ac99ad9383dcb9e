"""Best-fit packing of token sequences into windows, bettered by swap-based local search.

What matters to a bin is only which lengths it holds, so packing works on the
histogram of lengths: bins of the same content are one *pattern* with a count.
The histogram has at most ``window`` entries however many documents there are,
and this is all that the driver sees. Documents are then dealt to the places of
the patterns by an exact, salted rank within their length.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections import Counter
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tracelake.llm import common, tokens

WINDOW = 2048


def pieces(docs: DataFrame, vocabulary: str, window: int = WINDOW, keep_ids: bool = False) -> DataFrame:
    """Per piece: doc_id, piece, start, length, ids_crc32 (and ids, if kept).

    A document is the ids of its text (null: none) followed by id 0. Documents
    longer than ``window`` are cut so that only the first piece may be shorter.
    Rows that repeat each other, or have no doc_id, are documents of their own; other
    columns are left out. An empty table gives an empty result.
    """
    fields = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint" + ", ids array<int>" * keep_ids

    def cut(batches):
        for batch in batches:
            doc_ids = batch.column("doc_id")
            for row, ids, offsets in tokens.token_ids(batch.column("text"), vocabulary):
                out = {"row": [], "piece": [], "start": [], "length": [], "crc": [], "ids": []}
                for k, (a, b) in enumerate(zip(offsets[:-1].tolist(), offsets[1:].tolist())):
                    own = np.append(ids[a:b], np.uint32(0)).astype("<u4")
                    begin, n = 0, 0
                    while begin < len(own):
                        size = (len(own) - 1) % window + 1 if begin == 0 else window
                        part = own[begin : begin + size]
                        for name, value in (("row", row + k), ("piece", n), ("start", begin), ("length", size), ("crc", zlib.crc32(part.tobytes()))):
                            out[name].append(value)
                        if keep_ids:
                            out["ids"].append(part.astype(np.int32))
                        begin, n = begin + size, n + 1
                columns = [doc_ids.take(pa.array(out["row"], pa.int64())).cast(pa.int64()), pa.array(out["piece"], pa.int32())]
                columns += [pa.array(out[c], pa.int64()) for c in ("start", "length", "crc")]
                if keep_ids:
                    columns.append(pa.array(out["ids"], pa.list_(pa.int32())))
                names = ["doc_id", "piece", "start", "length", "ids_crc32"] + ["ids"] * keep_ids
                yield pa.RecordBatch.from_arrays(columns, names=names)

    return docs.select("doc_id", "text").mapInArrow(cut, fields)


def best_fit(histogram: dict[int, int], window: int) -> list[tuple[tuple[int, ...], int]]:
    """Best-fit decreasing on counts: patterns (lengths, longest first) and how many bins have each.

    A bin is filled with the longest length that still fits, again and again.
    That pattern is repeated while all its lengths last, so there are at most
    about two patterns for each distinct length.
    """
    left = {k: n for k, n in histogram.items() if n}
    order = sorted(left)
    out = []
    while order:
        pattern, room = Counter(), window
        at = len(order)
        while room and at:
            at = bisect_left(order, room + 1, 0, at)
            if not at:
                break
            size = order[at - 1]
            fit = min(room // size, left[size] - pattern[size])
            pattern[size] += fit
            room -= fit * size
            at -= 1
        times = min(left[k] // c for k, c in pattern.items() if c)
        used = tuple(k for k in sorted(pattern, reverse=True) for _ in range(pattern[k]))
        out.append((used, times))
        for k, c in pattern.items():
            left[k] -= c * times
            if not left[k]:
                del order[bisect_left(order, k)]
    return out


def local_search(bins: list[list[int]], window: int) -> list[list[int]]:
    """:func:`search` on single bins."""
    found = search(Counter(tuple(sorted(b)) for b in bins if b), window)
    return [list(lengths) for lengths, times in found for _ in range(times)]


def search(patterns: dict[tuple[int, ...], int], window: int) -> list[tuple[tuple[int, ...], int]]:
    """Moves and swaps between underfull bins; each must raise the sum of squared fills.

    For a pair of patterns (lengths in rising order), or two bins of one pattern:
    move one document, exchange one for one, two for one, one for two. A move is made
    in as many pairs of bins as there are. Since the sum of fills is constant, a gain
    means that a fuller bin gets fuller and an emptier one emptier, until it has
    nothing. It ends when no pair has a move, or with as few bins as can hold the lengths.
    """
    count = Counter({p: n for p, n in patterns.items() if n and sum(p) < window})
    full = Counter({p: n for p, n in patterns.items() if n and sum(p) >= window})
    least = -(-sum(sum(p) * n for p, n in count.items()) // window)
    bins = sum(count.values())
    todo = [(-sum(p), p) for p in count]
    heapify(todo)
    done: list[tuple[int, tuple[int, ...]]] = []  # no move between any two of them
    masks: dict[tuple[int, ...], tuple[int, int, int, int]] = {}

    def of(p):
        if p not in masks:
            masks[p] = _masks(p, window)
        return masks[p]

    def take(p, times):
        count[p] -= times
        at = bisect_left(done, (sum(p), p))
        if not count[p]:
            del count[p]
            masks.pop(p, None)
            if at < len(done) and done[at][1] == p:
                del done[at]

    def put(p, times):
        old, count[p] = count[p], count[p] + times
        at = bisect_left(done, (sum(p), p))
        known = at < len(done) and done[at][1] == p
        if known and old == 1:  # two bins of it may have a move
            del done[at]
        if not known or old == 1:
            heappush(todo, (-sum(p), p))

    while todo and bins > least:
        fill, p = heappop(todo)
        fill = -fill
        at = bisect_left(done, (fill, p))
        if p not in count or (at < len(done) and done[at][1] == p):
            continue
        for other, q in [*done, (fill, p)]:
            if p not in count:
                break
            times = count[p] // 2 if p == q else min(count[p], count[q])
            big, small = (p, q) if fill >= other else (q, p)
            if not times or not _may_move(of(big), of(small)):
                continue
            moved = _moved(big, small, window)
            take(p, times)
            take(q, times)
            for new in moved:
                if sum(new) == window:
                    full[new] += times
                    least, bins = least - times, bins - times
                elif new:
                    put(new, times)
                else:
                    bins -= times
        if p in count:
            insort(done, (fill, p))
    return sorted((full + count).items())


def _masks(p: tuple[int, ...], window: int) -> tuple[int, int, int, int]:
    """Sets of numbers as bits: the lengths that one, and two, documents for this bin may have in all; those that it can give."""
    many = Counter(p)
    ones = sorted(many)
    twos = {x + y for k, x in enumerate(ones) for y in ones[k:] if x != y or many[x] > 1}
    span = (1 << (window - sum(p))) - 1
    for_one = for_two = 0
    for x in ones:
        for_two |= span << (x + 1)
    for_one = for_two | span << 1
    for x in twos:
        for_one |= span << (x + 1)
    return for_one, for_two, sum(1 << x for x in ones), sum(1 << x for x in twos)


def _may_move(big: tuple[int, int, int, int], small: tuple[int, int, int, int]) -> bool:
    """Whether :func:`_step` has a move."""
    return bool(big[0] & small[2] or big[1] & small[3])


def _moved(big: tuple[int, ...], small: tuple[int, ...], window: int) -> tuple[tuple[int, ...], tuple[int, ...]]:
    """Both bins after all moves between them."""
    a, b = Counter(big), Counter(small)
    room = window - sum(big)
    while b and room and (move := _step(a, b, room)):
        out, into = move
        for x in out:
            a, b = a - Counter((x,)), b + Counter((x,))
        for x in into:
            a, b = a + Counter((x,)), b - Counter((x,))
        room += sum(out) - sum(into)
    return tuple(sorted(a.elements())), tuple(sorted(b.elements()))


def _step(big: Counter, small: Counter, room: int) -> tuple[list[int], list[int]] | None:
    """The move out of and into ``big`` that fills it most; None if there is none."""
    best, move = 0, None
    mine, ones = sorted(small), sorted(big)
    at = bisect_left(mine, room + 1)
    if at:
        best, move = mine[at - 1], ([], [mine[at - 1]])
    for x in ones:
        at = bisect_left(mine, x + room + 1)
        if at and mine[at - 1] - x > best:
            best, move = mine[at - 1] - x, ([x], [mine[at - 1]])
    if best == room:
        return move
    for k, x in enumerate(ones):
        for y in ones[k:]:
            if x + y + best >= mine[-1]:
                break
            if x == y and big[x] < 2:
                continue
            at = bisect_left(mine, x + y + room + 1)
            if at and mine[at - 1] - x - y > best:
                best, move = mine[at - 1] - x - y, ([x, y], [mine[at - 1]])
    for k, x in enumerate(mine):
        for y in mine[k:]:
            if x + y - room > ones[-1]:
                break
            if x == y and small[x] < 2:
                continue
            at = bisect_left(ones, x + y - room)
            if at < len(ones) and x + y - ones[at] > best:
                best, move = x + y - ones[at], ([ones[at]], [x, y])
    return move


def plan(histogram: dict[int, int], window: int = WINDOW) -> list[tuple[tuple[int, ...], int]]:
    """Patterns of bins for a histogram of lengths.

    Best fit first, then local search over all underfull patterns with their counts.
    """
    found = search(_summed(best_fit(histogram, window)), window)
    return [(tuple(sorted(p, reverse=True)), n) for p, n in found]


def _summed(patterns: list[tuple[tuple[int, ...], int]]) -> Counter:
    out: Counter = Counter()
    for lengths, times in patterns:
        out[tuple(sorted(lengths))] += times
    return out


def pack(parts: DataFrame, window: int = WINDOW) -> DataFrame:
    """Adds sequence_id and offset to rows that have doc_id, piece and length.

    Every row gets a place; the places of a sequence follow each other without a
    gap. Rows are ranked within their length by (hash of all columns, doc_id, piece); the rank
    is a rank within a slice of the length plus the counts of the slices before,
    so a length that a third of all rows have is no hot spot; the more rows, the
    more slices. An empty table gives an empty result.
    """
    names = parts.columns
    key, piece_of, rank, ahead = common.fresh(parts, "k_hash", "k_slice", "k_rank", "k_ahead")
    rows = parts.withColumn(key, F.xxhash64(*names))
    bits = common.slice_bits(parts.count())
    rows = rows.withColumn(piece_of, F.shiftrightunsigned(F.col(key), 64 - bits).cast("int"))
    counts = rows.groupBy("length", piece_of).count()
    histogram: Counter = Counter()
    held = counts.groupBy("length").agg(F.sum("count").alias("n")).collect()  # at most `window` rows
    for row in held:
        histogram[int(row["length"])] += int(row["n"])
    slots = _slots(plan(histogram, window))
    before = Window.partitionBy("length").orderBy(piece_of).rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.select(
        F.col("length").alias(f"{ahead}_length"), F.col(piece_of).alias(f"{ahead}_slice"),
        F.coalesce(F.sum("count").over(before), F.lit(0)).alias(ahead),
    )
    inside = Window.partitionBy("length", piece_of).orderBy(key, "doc_id", "piece")
    rows = rows.withColumn(rank, F.row_number().over(inside) - 1)
    rows = rows.join(counts, (F.col("length") == F.col(f"{ahead}_length")) & (F.col(piece_of) == F.col(f"{ahead}_slice")))
    rows = rows.select(*names, (F.col(rank) + F.col(ahead)).alias(rank))

    def place(batches):
        for batch in batches:
            length = batch.column("length").to_numpy(zero_copy_only=False)
            ranks = batch.column(rank).to_numpy(zero_copy_only=False)
            sequence, offset = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            order = np.argsort(length, kind="stable")
            bounds = np.flatnonzero(np.concatenate([[True], np.diff(length[order]) != 0]))
            for a, b in zip(bounds.tolist(), [*bounds[1:].tolist(), len(order)]):
                at = order[a:b]
                begin, base, each, first = slots[int(length[at[0]])]
                k = np.searchsorted(begin, ranks[at], side="right") - 1
                inner = ranks[at] - begin[k]
                sequence[at] = base[k] + inner // each[k]
                offset[at] = first[k] + inner % each[k] * length[at]
            columns = [batch.column(n) for n in names] + [pa.array(sequence), pa.array(offset)]
            yield pa.RecordBatch.from_arrays(columns, names=[*names, "sequence_id", "offset"])

    kept = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in parts.schema.fields)
    return rows.mapInArrow(place, f"{kept}, sequence_id bigint, offset bigint")


def _slots(patterns: list[tuple[tuple[int, ...], int]]) -> dict[int, tuple[np.ndarray, ...]]:
    """For each length: first rank, first sequence, places per sequence and first offset of each pattern that has it."""
    found: dict[int, list[list[int]]] = {}
    sequence = 0
    for lengths, times in patterns:
        offset = 0
        for size, many in sorted(Counter(lengths).items(), reverse=True):
            own = found.setdefault(size, [])
            begin = own[-1][0] + own[-1][4] if own else 0
            own.append([begin, sequence, many, offset, many * times])
            offset += size * many
        sequence += times
    return {k: tuple(np.array(c, dtype=np.int64) for c in list(zip(*v))[:4]) for k, v in found.items()}


def packed(docs: DataFrame, vocabulary: str, window: int = WINDOW, keep_ids: bool = False) -> DataFrame:
    """All pieces of ``docs`` with their sequences; needs doc_id and text.

    ``vocabulary`` is the path of a tokenizer file. With ``keep_ids`` the ids
    come along; else only their checksum does, which keeps shuffles small. A null or
    empty text is one piece, of id 0. Rows without doc_id and rows that repeat each other
    are packed each; other columns, whatever their names, are left out.
    An empty table gives an empty result.
    """
    parts = common.written(pieces(docs, vocabulary, window, keep_ids), "pack-pieces")
    return pack(parts, window)
