"""Connected components of links, distributed: alternating large-star and small-star."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracelake.llm import common


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """Per node that a link touches: node, component (the smallest node reachable).

    ``links`` has long columns a and b, in any direction, repeats and self-links
    allowed. Each round joins every node to the smallest neighbour it knows;
    minima are pre-aggregated, so a node with very many links is no hot spot.
    Raises if ``most_rounds`` don't suffice (they do for any graph that fits the
    bound of log-squared rounds).
    """
    edges = links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    edges = common.written(edges, "cc")
    before = None
    for _ in range(most_rounds):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("w")).select("u", F.least("u", "w").alias("low"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("low").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("low"))
        small = large.join(low, "u").where("v <> low").select(F.col("v").alias("u"), F.col("low").alias("v"))
        done = common.written(small.unionByName(low.select("u", F.col("low").alias("v"))).distinct(), "cc")
        common.drop_written(edges)
        edges = done
        now = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {most_rounds} rounds")
    roots = edges.select(F.col("v").alias("u"), "v").distinct()
    return edges.unionByName(roots).select(F.col("u").alias("node"), F.col("v").alias("component"))
