"""Quotation linking in conversations (DataFrame functions only).

A line's quote level is the number of its leading ``>`` signs. The lines of level
0 are the message's own. Quoted lines, and passages (neighbouring lines of one level
up to a blank one) joined to one line, are hashed in a normal form and joined to the
messages that first said such a line, paragraph or text: in the same conversation at
an earlier turn, else in the smallest other one. The parent of a message is the
earlier turn that most quoted lines of the lowest level that links come from (ties:
the later turn); a message without such lines answers the turn before it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tracelake.llm import common

# Possessive, as a plain loop over a group recurses once for each sign.
_QUOTE = r"^((?:[\x20\t]?>)++)[\x20\t]?"
_SAID = r"(?i)^on .{1,200} wrote:\s*$"
#: Turns of one conversation that are ranked together.
SLICE = 64


def _level(line: Column) -> Column:
    return F.length(F.regexp_replace(F.regexp_extract(line, _QUOTE, 1), "[^>]", ""))


def _normal(line: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(F.regexp_replace(line, _QUOTE, "")), r"[^\p{L}\p{N}]+", " "))


def link(turns: DataFrame) -> DataFrame:
    """Per row: conv_id, turn, role, reply_turn, quoted_conv, quoted_turn, quote_level, quoted_lines, linked_lines, position, text.

    Needs conv_id, turn, role and text. reply_turn is the parent; null at the
    first turn. quoted_conv and quoted_turn say where most linked lines were said
    first, also in another conversation. position orders the conversation by
    (parent, turn), from 1. text has no quoted lines and no line that only names
    who is quoted; null stays null. Rows without conv_id or turn are linked with
    nothing and have a null parent. Rows that share conv_id and turn are one message for
    linking and come out each. An empty table gives an empty result.
    """
    rows = turns.select("conv_id", "turn", "role", "text")
    lines = F.split(F.coalesce("text", F.lit("")), "\n")
    quoted = F.filter(lines, lambda x: _level(x) > 0)
    own = F.array_join(F.filter(lines, lambda x: (_level(x) == 0) & ~x.rlike(_SAID)), "\n")
    plain = F.coalesce(F.instr("text", ">"), F.lit(0)) == 0
    rows = rows.withColumn("quoted", F.when(plain, F.array().cast("array<string>")).otherwise(quoted))
    keep = F.when(plain, F.col("text")).otherwise(F.trim(own, F.lit("\n")))
    rows = rows.withColumn("kept", F.when(F.col("text").isNotNull(), keep))
    rows = common.written(rows, "quotes-turns")

    asked = rows.where((F.size("quoted") > 0) & F.col("conv_id").isNotNull() & F.col("turn").isNotNull()).withColumn("row", F.monotonically_increasing_id())
    asked = asked.select("conv_id", "turn", "row", F.posexplode(F.split("text", "\n")).alias("at", "raw"))
    asked = asked.select("conv_id", "turn", "row", "at", _level(F.col("raw")).alias("level"), _normal(F.col("raw")).alias("line"))
    asked = common.written(asked.withColumn("level", F.when(F.col("line") != "", F.col("level")).otherwise(0)), "quotes-lines")
    inside = Window.partitionBy("row").orderBy("at")
    asked = asked.withColumn("passage", F.sum((F.col("level") != F.lag("level", 1, 0).over(inside)).cast("int")).over(inside)).where("level > 0")
    joined = asked.groupBy("row", "passage").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("at", "line"))), lambda x: x["line"]), " ").alias("line"))
    joined = joined.select("row", "passage", F.xxhash64("line").alias("whole"))
    asked = asked.join(joined, ["row", "passage"])
    keys = F.array_distinct(F.array(F.xxhash64("line"), F.col("whole")))
    asked = common.written(asked.select("conv_id", "turn", "row", "at", "level", F.posexplode(keys).alias("joined", "h")), "quotes-asked")
    wanted = asked.select(F.col("h").alias("w")).distinct()
    said = rows.where("conv_id is not null and turn is not null and kept is not null")
    every = F.concat(F.split("kept", "\n"), F.split("kept", r"\n\s*\n"), F.array("kept"))
    said = said.select("conv_id", "turn", F.explode(F.array_distinct(F.transform(every, lambda x: F.xxhash64(_normal(x))))).alias("h"))
    said = said.join(wanted, F.col("h") == F.col("w"), "left_semi")
    first_here = said.groupBy(F.col("conv_id").alias("c"), F.col("h").alias("hh")).agg(F.min("turn").alias("t"))
    first_here = common.written(first_here, "quotes-first")
    anywhere = common.written(first_here.groupBy(F.col("hh").alias("ha")).agg(F.min(F.struct(F.col("c"), F.col("t"))).alias("a")), "quotes-anywhere")
    second = first_here.join(anywhere, (F.col("hh") == F.col("ha")) & (F.col("c") != F.col("a.c")))
    second = second.groupBy(F.col("hh").alias("hb")).agg(F.min(F.struct(F.col("c"), F.col("t"))).alias("b"))
    here = asked.join(first_here, (F.col("conv_id") == F.col("c")) & (F.col("h") == F.col("hh")) & (F.col("t") < F.col("turn")), "left")
    found = here.join(anywhere, F.col("h") == F.col("ha"), "left").join(second, F.col("h") == F.col("hb"), "left")
    other = F.when(F.col("a.c") != F.col("conv_id"), F.col("a")).otherwise(F.col("b"))
    near, far = F.col("t").isNotNull(), other.isNotNull()
    # A line links by itself before its passage does, and here before elsewhere.
    source = F.when(near, F.struct(F.col("joined").alias("order"), F.col("conv_id").alias("c"), F.col("t").alias("t"))).when(
        far, F.struct((F.col("joined") + 2).alias("order"), other["c"].alias("c"), other["t"].alias("t"))
    )
    found = found.groupBy("conv_id", "turn", "row", "at", "level").agg(F.min(source).alias("source")).where("source is not null")
    found = found.select("conv_id", "turn", "level", F.col("source.c").alias("q_conv"), F.col("source.t").alias("q_turn"))
    votes = found.groupBy("conv_id", "turn", "q_conv", "q_turn", "level").agg(F.count(F.lit(1)).alias("votes"))
    own_conv = F.col("q_conv") == F.col("conv_id")
    parents = votes.groupBy(F.col("conv_id").alias("p_conv"), F.col("turn").alias("p_turn")).agg(F.max(F.when(own_conv, F.struct(-F.col("level"), "votes", "q_turn"))).alias("near"))
    votes = votes.groupBy("conv_id", "turn", "q_conv", "q_turn").agg(F.sum("votes").alias("votes"))
    order = F.struct(F.col("votes"), own_conv.cast("int").alias("inside"), F.col("q_turn"), F.col("q_conv"))
    best = votes.groupBy(F.col("conv_id").alias("b_conv"), F.col("turn").alias("b_turn")).agg(F.sum("votes").alias("linked_lines"), F.max(order).alias("top"))
    best = best.join(parents, (F.col("b_conv") == F.col("p_conv")) & (F.col("b_turn") == F.col("p_turn"))).drop("p_conv", "p_turn")

    keys = rows.where("conv_id is not null and turn is not null").select(F.col("conv_id").alias("k_conv"), F.col("turn").alias("k_turn")).distinct()
    keys = keys.withColumn("slice", F.floor(F.col("k_turn") / SLICE))
    latest = keys.groupBy("k_conv", "slice").agg(F.max("k_turn").alias("latest"))
    latest = latest.withColumn("latest", F.lag("latest").over(Window.partitionBy("k_conv").orderBy("slice")))
    step = Window.partitionBy("k_conv", "slice").orderBy("k_turn")
    keys = keys.withColumn("before", F.lag("k_turn").over(step)).join(latest, ["k_conv", "slice"])
    keys = keys.join(best, (F.col("k_conv") == F.col("b_conv")) & (F.col("k_turn") == F.col("b_turn")), "left")
    keys = keys.withColumn("reply_turn", F.coalesce("near.q_turn", "before", "latest"))
    # The rank by (parent, turn): within a slice of parents, plus all rows of the slices before.
    parent = F.coalesce("reply_turn", F.lit(-(2**40)))
    keys = keys.withColumn("p", parent).withColumn("p_slice", F.floor(parent / SLICE))
    sums = keys.groupBy("k_conv", "p_slice").agg(F.count(F.lit(1)).alias("m"))
    ahead = Window.partitionBy("k_conv").orderBy("p_slice").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select("k_conv", "p_slice", F.coalesce(F.sum("m").over(ahead), F.lit(0)).alias("ahead"))
    rank = F.row_number().over(Window.partitionBy("k_conv", "p_slice").orderBy("p", "k_turn"))
    keys = keys.withColumn("rank", rank).join(sums, ["k_conv", "p_slice"])
    keys = keys.select(
        "k_conv", "k_turn", "reply_turn", F.col("top.q_conv").alias("quoted_conv"), F.col("top.q_turn").alias("quoted_turn"), "linked_lines", (F.col("rank") + F.col("ahead")).alias("position")
    )
    out = rows.join(keys, (F.col("conv_id") == F.col("k_conv")) & (F.col("turn") == F.col("k_turn")), "left")
    return out.select(
        "conv_id", "turn", "role", "reply_turn", "quoted_conv", "quoted_turn",
        F.coalesce(F.array_max(F.transform("quoted", _level)), F.lit(0)).alias("quote_level"),
        F.size("quoted").cast("bigint").alias("quoted_lines"), F.coalesce("linked_lines", F.lit(0)).alias("linked_lines"),
        F.col("position").cast("bigint").alias("position"), F.col("kept").alias("text"),
    )
