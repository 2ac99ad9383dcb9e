"""Measures of results: reduction, miss and noise ratio, F1, words, time, cost, study tables."""

from __future__ import annotations

import statistics
import threading
import time
import uuid

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def accuracy(results: DataFrame, truth: DataFrame, full_edges: int | None = None, denominator: str = "result", methods: DataFrame | None = None) -> DataFrame:
    """Per method and case: edges, tp, fp, fn, miss_ratio, noise_ratio, f1 (and reduction).

    results: method, case_id, event_id; truth: case_id, event_id. The noise ratio
    divides by the result's events, or with ``denominator="full"`` by all events.
    It is 0 for an empty result; reduction is null then. ``methods`` (method), if given, spares a second pass over the results.
    """
    methods = results.select("method").distinct() if methods is None else methods
    wanted = methods.join(truth.groupBy("case_id").agg(F.count(F.lit(1)).alias("relevant")), F.lit(True))
    real = truth.withColumn("real", F.lit(1))
    hit = results.join(real, ["case_id", "event_id"], "left").groupBy("method", "case_id").agg(F.count(F.lit(1)).alias("edges"), F.coalesce(F.sum("real"), F.lit(0)).alias("tp"))
    out = wanted.join(hit, ["method", "case_id"], "left").fillna(0, ["edges", "tp"])
    out = out.withColumn("fp", F.col("edges") - F.col("tp")).withColumn("fn", F.col("relevant") - F.col("tp"))
    below = F.col("edges") if denominator == "result" or full_edges is None else F.lit(full_edges)
    out = out.withColumn("miss_ratio", F.round(F.col("fn") / F.col("relevant"), 6)).withColumn("noise_ratio", F.when(F.col("edges") > 0, F.round(F.col("fp") / below, 6)).otherwise(0.0))
    out = out.withColumn("f1", F.round(F.col("tp") / (F.col("tp") + (F.col("fp") + F.col("fn")) / 2), 6))
    if full_edges is not None:
        out = out.withColumn("reduction", F.when(F.col("edges") > 0, F.round(F.lit(float(full_edges)) / F.col("edges"), 6)))
    return out.drop("relevant")


def reduction(full: int, edges: int) -> float | None:
    return full / edges if edges else None


def summarise(df: DataFrame, by: Column, *measures: str) -> DataFrame:
    """Means over cases by method and family, and in all (family null)."""
    return df.withColumn("family", by).rollup("method", "family").agg(*[F.round(F.avg(m), 6).alias(m) for m in measures]).where("method is not null")


def words(text: str) -> int:
    """Query length: words parted by white space."""
    return len(text.split())


def needle(relevant: int, full: int) -> float:
    return relevant / full


def time_query(make, rounds: int = 10, timeout_s: float = 1800.0) -> dict:
    """Mean, spread and rounds of running a plan to the end, caches cleared between; a round beyond the limit is cancelled and counted, not averaged."""
    took, late = [], 0
    for _ in range(rounds):
        df = make()
        context, group = df.sparkSession.sparkContext, f"timed-{uuid.uuid4().hex}"
        df.sparkSession.catalog.clearCache()
        stopped = threading.Event()

        def stop(context=context, group=group, stopped=stopped):
            stopped.set()
            context.cancelJobGroup(group)

        context.setJobGroup(group, "timed query", interruptOnCancel=True)
        timer = threading.Timer(timeout_s, stop)
        began = time.monotonic()
        timer.start()
        try:
            df.write.format("noop").mode("overwrite").save()
        except Exception:
            if not stopped.is_set():
                raise
        finally:
            timer.cancel()
            for name in ("spark.jobGroup.id", "spark.job.description", "spark.job.interruptOnCancel"):
                context.setLocalProperty(name, None)
        seconds = time.monotonic() - began
        late += seconds > timeout_s
        if seconds <= timeout_s:
            took.append(seconds)
    return {"mean_s": statistics.mean(took) if took else None, "deviation_s": statistics.pstdev(took) if took else None, "rounds": len(took), "timeouts": late}


def speedup(base: list[float], other: list[float]) -> dict:
    """Ratio of means, and the least and largest ratio per case."""
    each = [a / b for a, b in zip(base, other)]
    return {"of_means": statistics.mean(base) / statistics.mean(other), "least": min(each), "most": max(each)}


def join_cost(a: float, b: float, distinct: float) -> float:
    """Rows touched by an equi-join."""
    return a + b + a * b / max(distinct, 1.0)


def recursive_cost(levels: list[float], degree: float) -> float:
    """Rows touched by one recursive statement whose rounds repeat events for every path."""
    return sum(n * (1 + degree) for n in levels)


def stepwise_cost(steps: list[dict]) -> float:
    """Rows touched by stepwise tracking: nodes asked for and events admitted."""
    return float(sum((s["frontier"] or 0) + s["events"] for s in steps))


def study_summary(responses: DataFrame) -> DataFrame:
    """Per task and language: people, mean minutes and queries of those who finished, share that finished."""
    done = F.col("finished")
    return responses.groupBy("task", "language").agg(
        F.count(F.lit(1)).alias("people"), F.round(F.avg(F.when(done, F.col("minutes"))), 6).alias("minutes"),
        F.round(F.avg(F.when(done, F.col("queries"))), 6).alias("queries"), F.round(F.count_if(done) / F.count(F.lit(1)), 6).alias("share_finished"),
    )


def likert(answers: DataFrame, points: int = 5) -> DataFrame:
    """Per question: answers, and the shares below, at and above the middle of the scale; nulls don't count."""
    at, middle = F.col("answer"), (points + 1) / 2
    share = lambda c, name: F.round(F.count_if(c) / F.count(F.lit(1)), 6).alias(name)
    given = answers.where(at.isNotNull())
    return given.groupBy("question").agg(F.count(F.lit(1)).alias("answers"), share(at < middle, "disagree"), share(at == middle, "neutral"), share(at > middle, "agree"))
