"""Ingested stores, layouts, graphs in files, sessions, timing."""

from __future__ import annotations

import shutil
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from tests.test_track import random_rows, store
from tracelake import measure, plans, sources
from tracelake.graph import TraceGraph, read_graph
from tracelake.model import views
from tracelake.model.store import ingested
from tracelake.session import Session
from tracelake.track import NodeFilter, Seed, track_back, track_forward
from tracelake.track.run import intersect_traces


def _ids(df) -> list[int]:
    return sorted(r[0] for r in df.select("event_id").collect())


def test_ingested_once_until_the_tables_change(spark, data, tmp_path):
    for name in ("events", "customer", "nation", "region", "part"):
        shutil.copy(f"{data}/{name}.parquet", tmp_path)
    made = []

    def make():
        made.append(1)
        return views.events(spark, str(tmp_path))

    first = ingested(spark, "t", str(tmp_path), make)
    want = _ids(views.events(spark, str(tmp_path)).events)
    assert all(_ids(df) == want for df in first.copies.values()) and _ids(ingested(spark, "t", str(tmp_path), make).events) == want and len(made) == 1
    half = spark.read.parquet(f"{data}/events.parquet").where("event_id < 500").toPandas()
    half.to_parquet(tmp_path / "events.parquet", coerce_timestamps="us", index=False)
    assert len(_ids(ingested(spark, "t", str(tmp_path), make).events)) == len(half) and len(made) == 2
    shutil.rmtree(next(p for p in plans._written if "by_src_id" in p and p in _last()).removeprefix("file://"))
    assert len(_ids(ingested(spark, "t", str(tmp_path), make).events)) == len(half) and len(made) == 3


def _last() -> list[str]:
    from tracelake.model import store as module

    return list(module._ingested.values())[-1]


@pytest.mark.parametrize("direction", ["back", "forward"])
def test_rounds_over_the_sorted_copies(spark, data, direction):
    kept, plain = ingested(spark, "events", data, lambda: views.events(spark, data)), views.events(spark, data)
    trace, drop = (track_back if direction == "back" else track_forward), NodeFilter(drop=F.col("kind") == "network")
    seed = Seed.events(F.col("event_id") == 500)
    assert kept.along("dst_id").events is kept.copies["dst_id"]
    assert _ids(trace(seed, kept, nodes=drop, engine="bound").events) == _ids(trace(seed, plain, nodes=drop, engine="local").events)
    assert _ids(trace(seed, kept.host("host2"), engine="bound").events) == _ids(trace(seed, plain.host("host2"), engine="local").events)


def test_copies_of_other_events_are_not_read(spark, data):
    kept = ingested(spark, "events", data, lambda: views.events(spark, data))
    fewer = replace(kept, events=kept.events.where("event_id > 300"))
    assert fewer.along("dst_id") is fewer and fewer.host("host1").copies is None


def test_one_plan_for_small_stores_finds_the_same(spark):
    from tracelake.lang import parse
    from tracelake.search import search

    s = store(spark, random_rows(6, 60))
    find = parse('FIND IN STORE("h") ENTITIES a, b, c STEPS a -> b THEN b -> c;')[0]
    chosen = search(find, s, eager=None)
    assert chosen.rows == {} and {tuple(r) for r in chosen.bindings.collect()} == {tuple(r) for r in search(find, s).bindings.collect()}


def test_layouts(spark, data, tmp_path):
    s = ingested(spark, "events", data, lambda: views.events(spark, data))
    want = _ids(s.events)
    nodes, edges = s.as_graph()
    assert "id" in nodes.columns and {"src", "dst"} <= set(edges.columns)
    wide = s.widen()
    assert _ids(wide) == want and {"src_name", "dst_name"} <= set(wide.columns)
    s.write_adjacency(str(tmp_path), 2)
    for key in ("dst_id", "src_id"):
        assert _ids(spark.read.parquet(f"{tmp_path}/by_{key}")) == want


def test_graph_in_files_and_between(spark, data, tmp_path):
    s = ingested(spark, "events", data, lambda: views.events(spark, data))
    back = track_back(Seed.events(F.col("event_id") == 500), s)
    ends = {x for r in back.events.collect() for x in (r.src_id, r.dst_id)}
    assert {r.entity_id for r in back.nodes().collect()} == ends
    back.write(str(tmp_path))
    assert _ids(read_graph(spark, str(tmp_path)).events) == _ids(back.events)
    entry = Seed.events(F.col("event_id") == min(_ids(back.events)))
    between = _ids(intersect_traces(Seed.events(F.col("event_id") == 500), entry, s).events)
    assert set(between) == set(_ids(back.events)) & set(_ids(track_forward(entry, back).events)) and between


def test_session_tells_and_repeats(spark, data):
    session = Session(ingested(spark, "events", data, lambda: views.events(spark, data)))
    text = 'g := FIND IN STORE("host1") ENTITIES f: file, p: process, s: network STEPS f -read-> p THEN WITHIN 24h p -sendto-> s; h := TRACE BACKWARD FROM g IN STORE("host1") MAX HOPS 2;'
    session.run(text)
    before = {n: _ids(g.events) for n, g in session.catalog.graphs.items()}
    assert "score" in session.explain(text) and "engine auto" in session.explain(text)
    session.replay()
    assert {n: _ids(g.events) for n, g in session.catalog.graphs.items()} == before and len(session.record) == 2
    assert all(v > 0 for v in session.catalog.footprint().values())
    session.catalog.drop("g")
    assert set(session.catalog.graphs) == {"h"} and isinstance(session.catalog["h"], TraceGraph)


def test_timing(spark):
    quick = measure.time_query(lambda: spark.range(10), rounds=2)
    assert quick["rounds"] == 2 and quick["timeouts"] == 0
    slow = measure.time_query(lambda: spark.range(0, 10**13, 1, 4).selectExpr("sum(hash(id))"), rounds=1, timeout_s=1.5)
    assert slow == {"mean_s": None, "deviation_s": None, "rounds": 0, "timeouts": 1}
    assert spark.range(3).count() == 3
    assert measure.speedup([4.0, 9.0], [2.0, 3.0]) == {"of_means": 2.6, "least": 2.0, "most": 3.0} and measure.needle(2, 8) == 0.25


def test_log_source_keeps_what_it_does_not_understand(spark, tmp_path):
    (tmp_path / "a.log").write_text("1 h x(2) read f:1 res=3\nbad\n")
    spark.dataSource.register(sources.AuditLogSource)
    got = spark.read.format("auditlog").option("path", str(tmp_path)).option("rest", "true").load().collect()
    assert [r.rest for r in got] == [None, "bad"] and got[0].amount == 3 and got[1].op is None
