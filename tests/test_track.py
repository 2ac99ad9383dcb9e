"""Forms of tracking against a plain work list, and the rules at their edges."""

from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from tracelake.graph import TraceGraph
from tracelake.model import schema
from tracelake.model.store import TraceStore
from tracelake.track import EdgeFilter, Limits, NodeFilter, Seed, track_back, track_forward, track_many
from tracelake.track.baselines import run_track_sql, track_paths

_EVENT = "event_id bigint, host string, category string, op string, src_id string, dst_id string, start_us bigint, end_us bigint, amount bigint"


def store(spark, rows):
    """rows: (event_id, src, dst, start, end)"""
    events = spark.createDataFrame([(i, "h", "file", "read", a, b, s, e, 1) for i, a, b, s, e in rows], _EVENT)
    nodes = sorted({x for _, a, b, _, _ in rows for x in (a, b)}) or ["none"]
    entities = spark.createDataFrame([(n, n[0], n, f"/{n}" if n[0] == "f" else None) for n in nodes], "entity_id string, kind string, name string, path string")
    return TraceStore(entities, events)


def brute(rows, first, direction="back", most=None, allowed=lambda r: True):
    """Event -> level by a queue of events."""
    poi = next(r for r in rows if r[0] == first)
    level, queue = {first: 0}, [poi]
    while queue:
        e = queue.pop(0)
        if most is not None and level[e[0]] >= most:
            continue
        for r in rows:
            hit = r[2] == e[1] and r[3] < e[4] if direction == "back" else r[1] == e[2] and e[3] < r[4]
            if hit and r[0] not in level and allowed(r):
                level[r[0]] = level[e[0]] + 1
                queue.append(r)
    return level


def random_rows(seed, n=120):
    rng = random.Random(seed)
    return [(i, f"{rng.choice('pfn')}{rng.randrange(14)}", f"{rng.choice('pfn')}{rng.randrange(14)}", s := rng.randrange(300), s + rng.choice((0, 0, 1, 5, 60))) for i in range(n)]


def levels(graph):
    return {r.event_id: r.level for r in graph.events.select("event_id", "level").collect()}


@pytest.mark.parametrize("direction", ["back", "forward"])
def test_local_form_is_the_work_list(spark, direction):
    for seed in range(6):
        rows = random_rows(seed)
        s = store(spark, rows)
        poi = rows[60][0]
        for most in (None, 1, 3):
            got = (track_back if direction == "back" else track_forward)(Seed.events(F.col("event_id") == poi), s, limits=Limits(max_hops=most), engine="local")
            assert levels(got) == brute(rows, poi, direction, most)


@pytest.mark.parametrize("engine", ["bound", "level"])
def test_distributed_forms_are_the_work_list(spark, engine):
    rows = random_rows(7, 60)
    s = store(spark, rows)
    assert levels(track_back(Seed.events(F.col("event_id") == 30), s, limits=Limits(max_hops=4), engine=engine)) == brute(rows, 30, most=4)


def test_queue_form(spark):
    rows = [(1, "f1", "p1", 0, 1), (2, "p1", "f2", 5, 6), (3, "f2", "p2", 9, 10), (4, "f9", "p2", 20, 21)]
    assert levels(track_back(Seed.events(F.col("event_id") == 3), store(spark, rows), engine="queue")) == {3: 0, 2: 1, 1: 2}


def test_ties_and_bounds(spark):
    # start(a) < end(b), strictly; a node reached again with a higher bound is expanded again
    rows = [(1, "f1", "p1", 10, 10), (2, "p1", "f2", 5, 10), (3, "f3", "p1", 9, 9), (10, "a1", "b1", 0, 1), (11, "b1", "c1", 5, 20), (12, "b1", "d1", 8, 9), (13, "c1", "d1", 10, 11), (14, "d1", "e1", 30, 31), (15, "x1", "b1", 12, 13)]
    s = store(spark, rows)
    for engine in ("local", "level"):
        assert set(levels(track_back(Seed.events(F.col("event_id") == 2), s, engine=engine))) == {2, 3}
        assert levels(track_back(Seed.events(F.col("event_id") == 14), s, engine=engine)) == brute(rows, 14)


def test_self_loops_cycles_and_no_match(spark):
    rows = [(1, "p1", "p1", 0, 5), (2, "p1", "f1", 3, 9), (3, "f1", "p1", 2, 4)]
    s = store(spark, rows)
    assert levels(track_back(Seed.events(F.col("event_id") == 2), s)) == brute(rows, 2)
    empty = track_back(Seed.events(F.col("event_id") == 99), s)
    assert empty.events.count() == 0 and "level" in empty.events.columns


def test_duality_monotone_hops_and_filters(spark):
    rows = random_rows(3, 80)
    s = store(spark, rows)
    back = {i: set(brute(rows, i)) for i in (10, 40)}
    seeds = [Seed.events(F.col("event_id") == i, i) for i in back]
    got: dict[int, set] = {i: set() for i in back}
    for r in track_many(seeds, s).select("case_id", "event_id").collect():
        got[r.case_id].add(r.event_id)
    assert got == back
    for a in sorted(back[40])[:4]:
        assert 40 in levels(track_forward(Seed.events(F.col("event_id") == a), s))
    no_net = NodeFilter(drop=F.col("kind") == "n")
    during = set(levels(track_back(Seed.events(F.col("event_id") == 40), s, nodes=no_net)))
    after = set(levels(track_back(Seed.events(F.col("event_id") == 40), s, nodes=no_net, filter_mode="after")))
    assert during <= after <= back[40]
    assert during == set(brute(rows, 40, allowed=lambda r: "n" not in r[1] + r[2]))
    few = EdgeFilter(keep=F.col("event_id") % 2 == 0)
    assert set(levels(track_back(Seed.events(F.col("event_id") == 40), s, edges=few))) == set(brute(rows, 40, allowed=lambda r: r[0] % 2 == 0))


def test_missing_attributes_are_false(spark):
    from tracelake.lang.analyze import sql_of
    from tracelake.lang.tree import Compare, Not

    rows = [(1, "n1", "p1", 0, 1), (2, "f1", "p1", 0, 1), (3, "p1", "f2", 5, 6)]
    keep = F.expr(sql_of(Not(Compare("path", "~", "/f1")), "entity", ""))
    assert set(levels(track_back(Seed.events(F.col("event_id") == 3), store(spark, rows), nodes=NodeFilter(keep=keep)))) == {1, 3}


def test_recursive_statement_and_paths(spark):
    rows = random_rows(5, 40)
    s = store(spark, rows)
    assert {r[0] for r in run_track_sql(s, 20, 3).collect()} == set(brute(rows, 20, most=3))
    assert {r["last"] for r in track_paths(s, 20, 3).collect()} == set(brute(rows, 20, most=3))


def test_set_laws(spark):
    rows = random_rows(1, 60)
    s = store(spark, rows)
    a = TraceGraph(s.entities, s.events.where("event_id < 40"))
    b = TraceGraph(s.entities, s.events.where("event_id BETWEEN 20 AND 50"))
    ids = lambda g: {r.event_id for r in g.events.collect()}
    assert ids(a.minus(b).union(a.intersect(b))) == ids(a)
    assert ids(a.union(b)) == ids(a) | ids(b)
    assert a.size().first()["edges"] == 40
    assert a.show("dot").startswith("digraph")


def test_schemas_agree():
    assert set(schema.EDGE_COLUMNS) <= set(schema.EVENT_COLUMNS)


def test_recursive_statement_counts_no_paths(spark):
    """40 parallel events a hop: 64,000 paths of three hops, more than a million of four."""
    from tracelake.track.baselines import run_track_sql

    rows = [(h * 40 + k, f"n{h + 1}", f"n{h}", 100 - 10 * h, 101 - 10 * h) for h in range(5) for k in range(40)] + [(999, "n0", "x", 200, 201)]
    for hops in (1, 4, 5):
        got = [r.event_id for r in run_track_sql(store(spark, rows), 999, hops).collect()]
        assert sorted(got) == [*range(hops * 40), 999]


def test_recursive_statement_meets_only_the_edges_of_its_nodes(spark):
    """A step joins nodes and edges by the node: no edges are paired with each bound, and rows of the last hop find none."""
    from tracelake.track.baselines import run_track_sql, walk_sql

    rows = [(k, f"n{k}", "n0", 100 - k, 101 - k) for k in range(1, 30)] + [(100 * h + k, f"m{h}", f"n{k}", 50, 51) for h in (1, 2) for k in range(1, 30)]
    rows += [(900, "n0", "x", 200, 201), (901, "far", "m1", 1, 2), (902, "off", "m3", 1, 2)]
    s = store(spark, rows)
    for hops in (1, 2, 3, 4):
        got = [r.event_id for r in run_track_sql(s, 900, hops).collect()]
        assert len(got) == len(set(got)) and set(got) == set(brute(rows, 900, most=hops))
    s.edges().createOrReplaceTempView("trace_events")
    plan = spark.sql(walk_sql(900, 3))._jdf.queryExecution().optimizedPlan().toString().splitlines()
    edges_met = [line for line in plan if "Join" in line and "start_us" in line]
    assert len(edges_met) == 2 and all("dst_id" in line for line in edges_met)
    last, filters = sum("UnionLoopRef" in line for line in plan), sum("Filter" in line and "< 3)" in line for line in plan)
    assert filters >= last > 0


@pytest.mark.parametrize(("events", "rows_"), [(3, 1000), (200, 2), (0, 1000)])
def test_a_queue_that_outgrows_the_driver_goes_on_in_rounds(spark, monkeypatch, events, rows_):
    from tracelake.track import engines

    monkeypatch.setattr(engines, "QUEUE_EVENTS", events)
    monkeypatch.setattr(engines, "QUEUE_ROWS", rows_)
    rows = random_rows(7, 60)
    s = store(spark, rows)
    for most in (None, 3):
        assert levels(track_back(Seed.events(F.col("event_id") == 30), s, limits=Limits(max_hops=most), engine="queue")) == brute(rows, 30, most=most)
