"""Comparison methods and measures by their invariants."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from tests.test_track import _EVENT, brute, random_rows
from tracelake import measure
from tracelake.compare import features, impact_traces, projection, propagate, rareness_traces
from tracelake.model.store import TraceStore


def _store(spark, rows):
    events = spark.createDataFrame([(i, "h", "file", "read", a, b, s, e, i % 9) for i, a, b, s, e in rows], _EVENT)
    events = events.withColumns({"subject_id": F.col("src_id"), "object_id": F.col("dst_id"), "day": F.lit("2024-01-01")})
    return TraceStore(events.select(F.col("src_id").alias("entity_id")).distinct(), events)


def test_prioritised_without_limit_is_plain(spark):
    rows = random_rows(11, 80)
    s = _store(spark, rows)
    full = {r.event_id for r in rareness_traces([(0, 40)], s).collect()}
    assert full == set(brute(rows, 40))
    assert {r.event_id for r in rareness_traces([(0, 40)], s, 3).collect()} <= full


def test_impact_is_part_of_the_backward_graph_and_grows(spark):
    rows = random_rows(12, 80)
    s = _store(spark, rows)
    found = [{r.event_id for r in impact_traces([(0, 40)], s, n).collect()} for n in (1, 3, 50)]
    assert found[0] <= found[1] <= found[2] <= set(brute(rows, 40))


def test_scores_lie_between_0_and_1():
    edges = pd.DataFrame({"src_id": ["a", "b", "b", "c"], "dst_id": ["b", "c", "d", "d"], "amount": [1, 2, 3, 3], "end_us": [1, 2, 3, 4], "event_id": [1, 2, 3, 4]})
    poi = edges.iloc[3]
    x = features(edges, poi)
    assert x.min() >= 0 and x.max() <= 1
    w = np.clip(x @ projection(x), 0, None) + 1e-9
    w = w / pd.Series(w).groupby(edges["src_id"]).transform("sum").to_numpy()
    score = propagate(edges, w, poi)
    assert score["d"] == 1 and (score >= 0).all() and (score <= 1).all()


def test_measures(spark):
    truth = spark.createDataFrame([(1, 1), (1, 2), (1, 3), (2, 9)], "case_id long, event_id long")
    res = spark.createDataFrame([("m", 1, 1), ("m", 1, 2), ("m", 1, 7), ("m", 1, 8)], "method string, case_id long, event_id long")
    rows = {r.case_id: r for r in measure.accuracy(res, truth, 100).collect()}
    assert (rows[1].tp, rows[1].fp, rows[1].fn) == (2, 2, 1)
    assert rows[1].noise_ratio == 0.5 and rows[1].miss_ratio == 0.333333 and rows[1].reduction == 25.0
    assert rows[1].f1 == round(2 / 3.5, 6)
    assert rows[2].edges == 0 and rows[2].noise_ratio == 0 and rows[2].reduction is None and rows[2].miss_ratio == 1
    assert measure.words("a  b\nc") == 3


def test_story_on_the_planted_case(spark, data):
    from tracelake import registry

    got = {r.event_id - 10_000_002_000 for r in registry.QUERIES["case_study"](spark, data).collect()}
    assert got == {1, 2, 13, 17, 18, 19, 20}


def test_every_case_is_searched(spark, data):
    from tracelake.studies import cases_search

    assert {r.case_id for r in cases_search(spark, data).select("case_id").distinct().collect()} == set(range(1, 31))


def test_words_and_study_tables_are_read_from_given_tables(spark, data):
    from tracelake import registry

    tables = {"rq4_words": "documents", "rq5_study": "orders", "rq5_likert": "orders"}
    for name, table in tables.items():
        got = registry.QUERIES[name](spark, data)
        assert any(table in f for f in got.inputFiles()), name
    orders = spark.read.parquet(f"{data}/orders.parquet").count()
    assert sum(r.people for r in registry.QUERIES["rq5_study"](spark, data).collect()) == orders
    assert sum(r.answers for r in registry.QUERIES["rq5_likert"](spark, data).collect()) == orders


def test_prioritised_tracing_of_a_large_source_is_that_of_a_small_one(spark, monkeypatch):
    from tracelake import compare

    rows = random_rows(11, 150)
    s = _store(spark, rows)
    ask = lambda limit: {(r.case_id, r.event_id) for r in rareness_traces([(0, 40), (1, 90)], s, limit).collect()}
    limits = (1, 4, 15, 1000, None)
    want = [ask(n) for n in limits]
    assert want[0] < want[2] <= want[4]
    monkeypatch.setattr(compare, "LOCAL_EDGES", 10)
    assert [ask(n) for n in limits] == want


def test_impact_in_blocks_is_that_of_one_task(spark, monkeypatch):
    from tracelake import compare
    from tracelake.compare import blocks

    s = _store(spark, random_rows(5, 150))
    ask = lambda: {tuple(r) for r in compare.impact_sweep([(0, 40), (1, 90), (2, 140)], s, [1, 3, 50]).collect()}
    want = ask()
    assert {n for n, _, _ in want} == {1, 3, 50}
    monkeypatch.setattr(compare, "CASE_EDGES", 3)
    monkeypatch.setattr(blocks, "BLOCK_NODES", 4)
    monkeypatch.setattr(blocks, "BLOCK_EDGES", 10)
    assert ask() == want
