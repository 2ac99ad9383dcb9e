"""Relational operators that investigations need and Spark has no single call for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def band_join(left: DataFrame, right: DataFrame, keys: list[str], left_time: str, right_time: str, width: int, ordered: bool = True) -> DataFrame:
    """Pairs with equal keys whose right time lies less than ``width`` after the left (or on either side).

    Times are cut into buckets of ``width``; a left row meets the right rows of its
    own bucket and the next (and the one before), so the join is by equality. Worth
    it where a key has many rows. Column names of both sides differ, but for keys.
    """
    steps = [0, 1] if ordered else [-1, 0, 1]
    a = left.withColumn("bucket_", F.explode(F.array(*[F.floor(F.col(left_time) / width) + k for k in steps])))
    b = right.withColumn("bucket_", F.floor(F.col(right_time) / width))
    gap = F.col(right_time) - F.col(left_time)
    rule = (gap >= 0) & (gap < width) if ordered else F.abs(gap) < width
    return a.join(b, [*keys, "bucket_"]).where(rule).drop("bucket_")


def as_of_join(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, value: str, out: str) -> DataFrame:
    """Adds to each left row the value of the last right row of its key before it (strictly), by one window over both."""
    columns = left.columns
    a = left.select(*columns, F.col(left_time).alias("t_"), F.lit(1).alias("side_"), F.lit(None).cast(right.schema[value].dataType).alias("v_"))
    b = right.select(F.col(key), F.col(right_time).alias("t_"), F.lit(2).alias("side_"), F.col(value).alias("v_"))
    both = a.unionByName(b, allowMissingColumns=True)
    before = Window.partitionBy(key).orderBy("t_").rangeBetween(Window.unboundedPreceding, -1)
    last = F.max(F.when(F.col("side_") == 2, F.struct("t_", "v_"))).over(before)
    return both.withColumn(out, last["v_"]).where("side_ = 1").select(*columns, out)


def overlap_join(left: DataFrame, right: DataFrame, key: str, left_span: tuple[str, str], right_span: tuple[str, str], width: int) -> DataFrame:
    """Pairs with equal keys whose spans share a moment; each pair once, in the bucket where the later one begins."""
    def cut(df, span, name):
        return df.withColumn(name, F.explode(F.sequence(F.floor(F.col(span[0]) / width), F.floor(F.col(span[1]) / width))))

    a, b = cut(left, left_span, "bucket_"), cut(right, right_span, "bucket_")
    meet = (F.col(left_span[0]) <= F.col(right_span[1])) & (F.col(right_span[0]) <= F.col(left_span[1]))
    once = F.col("bucket_") == F.floor(F.greatest(F.col(left_span[0]), F.col(right_span[0])) / width)
    return a.join(b, [key, "bucket_"]).where(meet & once).drop("bucket_")


def salted_join(big: DataFrame, small: DataFrame, key: str, salts: int, spread_by: Column) -> DataFrame:
    """Inner join in which each key's rows of the big side go to ``salts`` places; the small side is repeated for each."""
    a = big.withColumn("salt_", F.pmod(F.xxhash64(spread_by), F.lit(salts)).cast("int"))
    b = small.withColumn("salt_", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [key, "salt_"]).drop("salt_")


def top_per_group(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group, numbered."""
    return df.withColumn("nth", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("nth") <= k)


def sessions(df: DataFrame, key: str, time: str, gap: int) -> DataFrame:
    """Adds session: its number within the key, a new one after a pause of more than ``gap``."""
    own = Window.partitionBy(key).orderBy(time)
    new = (F.col(time) - F.lag(time).over(own) > gap).cast("int")
    return df.withColumn("session", F.sum(F.coalesce(new, F.lit(0))).over(own.rowsBetween(Window.unboundedPreceding, Window.currentRow)))


def distinct_sketch(df: DataFrame, by: list[str], column: str) -> DataFrame:
    """Mergeable sketches of distinct values per group, and the estimate of their union."""
    per = df.groupBy(*by).agg(F.hll_sketch_agg(column, F.lit(14)).alias("sketch"))
    return per.agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("estimate"), F.count(F.lit(1)).alias("groups"))


def frequencies(df: DataFrame, column: str, eps: float = 0.001) -> DataFrame:
    """A mergeable count-min sketch of a column, as bytes."""
    return df.agg(F.count_min_sketch(F.col(column), F.lit(eps), F.lit(0.99), F.lit(7)).alias("sketch"))
