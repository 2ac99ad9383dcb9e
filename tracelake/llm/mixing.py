"""Mixing sources to target weights by weighted fair queueing (DataFrame functions only).

Each source is a queue whose documents stand in a hashed order. A document's
virtual finish time is the number of its source's words up to and including it,
divided by the source's target. The mix takes documents of all queues by finish
time until the budget is spent, so that at every moment each source has given
words in proportion to its target.

Exact running sums never put one source into one task: documents of a source are
cut by their hash into slices of even size, sums run inside a slice, and the
sums of whole slices are added from a small table. The number of slices follows
from the number of rows, so that a slice stays at about a million; the order, and
with it the mix, is the same for any number.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tracelake.llm import common

#: Weights of the sources in code-point order, repeating.
WEIGHTS = (3.0, 1.0, 2.0)
#: The mix holds this share of all words.
BUDGET = 1.5
#: No document is taken more often than this.
EPOCHS = 2
#: Slices of the virtual time in one unit of it, at least.
TIME_SLICES = 1024


def source_targets(sizes: DataFrame, weights=WEIGHTS, budget: float = BUDGET, epochs: int = EPOCHS) -> DataFrame:
    """One row per source: source, source_size, target.

    ``sizes`` has source and size. Weights go to sources in code-point order
    (null last) and repeat. Targets share ``budget`` times all words by weight;
    a target stops at ``epochs`` times its source's words and what is left goes
    to the others by weight, until none is above. Where all stop, the mix is
    smaller than the budget. A source without words gets 0.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    turn = (F.row_number().over(by_name) - 1) % len(weights)
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (turn + 1).cast("int"))
    per = per.withColumn("weight", weight).withColumn("limit", F.col("source_size") * F.lit(float(epochs)))
    # Filling by level: in the order of limit / weight, a source stops at its limit
    # if the level that the rest would share without it lies above.
    every = Window.partitionBy()
    order = Window.orderBy(F.col("limit") / F.col("weight"), F.col("source").asc_nulls_last())
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    onward = order.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    per = (
        per.withColumn("spent", F.coalesce(F.sum("limit").over(before), F.lit(0.0)))
        .withColumn("rest", F.sum("weight").over(onward))
        .withColumn("level", (F.sum("source_size").over(every) * F.lit(float(budget)) - F.col("spent")) / F.col("rest"))
        .withColumn("full", F.col("limit") <= F.col("level") * F.col("weight"))
    )
    # Behind the first source that doesn't stop, the computed levels only fall.
    level = F.max(F.when(~F.col("full"), F.col("level"))).over(every)
    target = F.when(F.col("full"), F.col("limit")).otherwise(level * F.col("weight"))
    return per.select("source", "source_size", target.alias("target"))


def mix(docs: DataFrame, weights=WEIGHTS, budget: float = BUDGET, epochs: int = EPOCHS, seed: int = 17) -> DataFrame:
    """Per row of ``docs``: doc_id, source, size, source_size, target, and copies: how often it is taken.

    Reads doc_id, text and source only. Size is the number of words (null: 0). Whole documents are taken in the order of their virtual
    finish time while the running total stays within the budget; ties go by
    source, order hash, doc_id and epoch. Empty documents are taken with the
    first epoch that reaches them, at no cost. Rows that repeat each other are
    documents of their own. An empty table gives an empty result.
    """
    key = F.xxhash64(F.lit(seed), F.col("doc_id"), F.col("size"))
    narrow = docs.select("doc_id", "source", common.word_count(F.col("text")).alias("size"))
    narrow = common.written(narrow.withColumn("hash", key), "mix-sizes")
    targets = common.written(source_targets(narrow, weights, budget, epochs), "mix-targets")
    rows = narrow.count()
    times = common.written(_positions(narrow, targets, common.slice_bits(rows)), "mix-times")
    fine = max(TIME_SLICES, 2 ** common.slice_bits(rows * epochs))
    held = times.crossJoin(F.broadcast(_cut(times, targets, budget, epochs, fine)))
    copies = F.lit(0)
    for epoch in range(epochs):
        finish = _finish(epoch)
        before = _time_slice(finish, fine) < F.col("e_slice")
        within = F.coalesce(_place(finish, epoch) <= F.col("last"), F.lit(False))
        copies = copies + F.when(before | within, 1).otherwise(0)
    return held.select("doc_id", "source", "size", "source_size", "target", copies.alias("copies"))


def _positions(narrow: DataFrame, targets: DataFrame, bits: int) -> DataFrame:
    """Adds source_size, target and upto: the words of the source up to this row, in hash order."""
    rows = narrow.withColumn("slice", F.shiftrightunsigned(F.col("hash"), 64 - bits).cast("int"))
    whole = rows.groupBy("source", "slice").agg(F.sum("size").alias("slice_size"))
    ahead = Window.partitionBy("source").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    whole = whole.select(
        F.col("source").alias("o_source"), F.col("slice").alias("o_slice"), F.coalesce(F.sum("slice_size").over(ahead), F.lit(0)).alias("ahead")
    )
    inside = Window.partitionBy("source", "slice").orderBy("hash", "doc_id", "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = rows.withColumn("within", F.sum("size").over(inside))
    rows = rows.join(whole, F.col("source").eqNullSafe(F.col("o_source")) & (F.col("slice") == F.col("o_slice")))
    small = targets.select(F.col("source").alias("t_source"), "source_size", "target")
    return rows.join(small, F.col("source").eqNullSafe(F.col("t_source"))).select(
        "doc_id", "source", "size", "hash", "source_size", "target", (F.col("ahead") + F.col("within")).alias("upto")
    )


def _time_slice(finish, fine: int):
    return F.least(finish * fine, F.lit(4.0 * fine)).cast("int")


def _finish(epoch):
    """Virtual finish time; a source without target is done at once."""
    words = F.col("upto") + F.lit(epoch) * F.col("source_size")
    return F.when(F.col("target") > 0, words / F.col("target")).otherwise(F.lit(0.0))


def _place(finish, epoch):
    """What the global order compares, as one struct."""
    return F.struct(
        finish.alias("finish"), F.coalesce(F.col("source"), F.lit("\U0010ffff")).alias("source"), F.col("hash").alias("hash"),
        F.coalesce(F.col("doc_id"), F.lit(-(2**63))).alias("doc_id"), F.col("size").alias("size"), F.lit(epoch).alias("epoch"),
    )


def _cut(times: DataFrame, targets: DataFrame, budget: float, epochs: int, fine: int) -> DataFrame:
    """One row: the last place in the global order whose running total is within the budget."""
    items = None
    for epoch in range(epochs):
        part = times.select(_place(_finish(epoch), epoch).alias("place"))
        items = part if items is None else items.unionAll(part)
    # Fair queueing spreads the words evenly over the virtual time, so slices of
    # the time are a range sort with even parts. Only sums of slices meet.
    items = items.where("place.size > 0").withColumn("slice", _time_slice(F.col("place.finish"), fine))
    total = targets.agg(F.coalesce(F.sum("source_size"), F.lit(0)).alias("all")).select((F.col("all") * F.lit(float(budget))).alias("budget"))
    sums = items.groupBy("slice").agg(F.sum("place.size").alias("slice_size"))
    ahead = Window.orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("ahead", F.coalesce(F.sum("slice_size").over(ahead), F.lit(0)))
    crossing = sums.crossJoin(F.broadcast(total)).where("ahead <= budget").select("slice", "ahead", "budget")
    # The slice in which the budget ends: the last that begins within it.
    edge = crossing.agg(F.max(F.struct("slice", "ahead", "budget")).alias("e")).select(
        F.col("e.slice").alias("e_slice"), F.col("e.ahead").alias("e_ahead"), F.col("e.budget").alias("e_budget")
    )
    last = items.join(F.broadcast(edge), F.col("slice") == F.col("e_slice"))
    run = Window.partitionBy("slice").orderBy("place").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    inside = last.withColumn("total", F.col("e_ahead") + F.sum("place.size").over(run)).where("total <= e_budget")
    best = inside.agg(F.max("place").alias("last"))
    return best.crossJoin(F.broadcast(edge.select("e_slice"))).select("last", "e_slice")


def taken(docs: DataFrame, **options) -> DataFrame:
    """Per row of ``docs``: doc_id, size, source_size, target, taken (words, repeats counted)."""
    out = mix(docs, **options)
    return out.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))


def mixed(docs: DataFrame, **options) -> DataFrame:
    """The documents of the mix: each row as often as it is taken, with the columns of ``docs``.

    Needs doc_id, text and source. Rows that share doc_id, source and size stand next to each other in
    their queue, so only those at whose place the budget ends are taken unequally often:
    the extra copies go to the first of them by the hash of all their columns. All
    together are as many as :func:`mix` takes. An empty table gives an empty result.
    """
    k_id, k_source, k_size, k_all, k_rows, words, copies, turn, nth, ahead = common.fresh(docs, "k_id", "k_source", "k_size", "k_all", "k_rows", "words", "copies", "turn", "nth", "ahead")
    counts = mix(docs, **options).groupBy(F.col("doc_id").alias(k_id), F.col("source").alias(k_source), F.col("size").alias(k_size)).agg(
        F.sum("copies").alias(k_all), F.count(F.lit(1)).alias(k_rows)
    )
    counts = common.written(counts.where(F.col(k_all) > 0), "mix-copies")
    same = F.col("doc_id").eqNullSafe(F.col(k_id)) & F.col("source").eqNullSafe(F.col(k_source)) & (F.col(words) == F.col(k_size))
    rows = docs.withColumn(words, common.word_count(F.col("text")))
    even = F.col(k_all) % F.col(k_rows) == 0
    held = rows.join(counts.where(even), same).withColumn(copies, (F.col(k_all) / F.col(k_rows)).cast("int"))
    out = held.withColumn(words, F.explode(F.sequence(F.lit(1), F.col(copies)))).select(*docs.columns)
    uneven = counts.where(~even)
    if uneven.isEmpty():  # at most one key of each source and epoch
        return out
    # Rows that are alike in all columns are counted, so no task holds a key's rows however many they are.
    alike = rows.join(F.broadcast(uneven), same).groupBy(*docs.columns, k_id, k_source, k_size, k_all, k_rows).agg(F.count(F.lit(1)).alias(nth))
    alike = alike.withColumn(turn, F.xxhash64(*docs.columns))
    before = Window.partitionBy(k_id, k_source, k_size).orderBy(turn, *docs.columns).rowsBetween(Window.unboundedPreceding, -1)
    alike = alike.withColumn(ahead, F.coalesce(F.sum(nth).over(before), F.lit(0)))
    each, extra = F.floor(F.col(k_all) / F.col(k_rows)), F.col(k_all) % F.col(k_rows)
    more = F.least(F.greatest(extra - F.col(ahead), F.lit(0)), F.col(nth))
    alike = alike.withColumn(copies, (each * F.col(nth) + more).cast("int")).where(F.col(copies) > 0)
    return out.unionByName(alike.withColumn(words, F.explode(F.sequence(F.lit(1), F.col(copies)))).select(*docs.columns))
