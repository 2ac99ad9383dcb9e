"""Search: the order of steps never changes the result; scores keep their order."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from tests.test_track import random_rows, store
from tracelake.lang import parse
from tracelake.search import Weights, prune_score, schedule, search
from tracelake.search.run import logsearch_text, motif_join

_TEXT = 'FIND IN STORE("h") ENTITIES a, b, c, d STEPS a -> b {link} b -> c THEN WITHIN 100s c -> d;'


def _brute(rows, kind, within):
    out = set()
    for x in rows:
        for y in rows:
            gap = y[3] - x[3]
            if x[2] == y[1] and (0 <= gap < within if kind == "then" else abs(gap) < within):
                out |= {(x[0], y[0], z[0]) for z in rows if z[1] == y[2] and 0 <= z[3] - y[3] < 100_000_000}
    return out


@pytest.mark.parametrize("kind", ["then", "also"])
def test_all_ways_give_the_same(spark, kind):
    rows = [(i, a, b, s * 1_000_000, e * 1_000_000) for i, a, b, s, e in random_rows(2, 50)]
    s = store(spark, rows)
    find = parse(_TEXT.format(link=f"{kind.upper()} WITHIN 60s"))[0]
    want = _brute(rows, kind, 60_000_000)
    ways = [search(find, s).bindings, search(find, s, mode="text").bindings, search(find, s, mode="stats").bindings, search(find, s, eager=False).bindings, search(find, s, weights=Weights(file_penalty=0)).bindings, motif_join(find, s)]
    for w in ways:
        assert {(r.e0, r.e1, r.e2) for r in w.collect()} == want


def test_or_unites_and_empty_steps_stop(spark):
    rows = random_rows(4, 30)
    s = store(spark, rows)
    r = search(parse('FIND IN STORE("h") ENTITIES a (name = "nobody"), b, c STEPS a -> b THEN b -> c OR b -> c;')[0], s)
    assert r.rows[0] == 0 and 1 not in r.rows
    assert {x.e2 for x in r.bindings.collect()} == {x[0] for x in rows}


def test_within_is_monotone_and_then_is_within_also(spark):
    rows = [(i, a, b, s * 1_000_000, e * 1_000_000) for i, a, b, s, e in random_rows(9, 60)]
    s = store(spark, rows)
    text = 'FIND IN STORE("h") ENTITIES a, b, c STEPS a -> b {} b -> c;'
    get = lambda link: {(r.e0, r.e1) for r in search(parse(text.format(link))[0], s, eager=False).bindings.collect()}
    assert get("THEN WITHIN 10s") <= get("THEN WITHIN 60s") <= get("THEN") <= get("ALSO")
    assert get("THEN WITHIN 60s") <= get("ALSO WITHIN 60s")


def test_search_in_a_result(spark):
    from tracelake.graph import TraceGraph

    rows = random_rows(6, 60)
    s = store(spark, rows)
    g = TraceGraph(s.entities, s.events.where(F.col("event_id") < 30))
    find = parse('FIND IN g ENTITIES a, b, c STEPS a -> b THEN b -> c;')[0]
    inside = {(r.e0, r.e1) for r in search(find, g).bindings.collect()}
    assert inside == {(r.e0, r.e1) for r in search(find, s).bindings.collect() if r.e0 < 30 and r.e1 < 30}


def test_scores():
    f = parse('FIND IN STORE("h") ENTITIES u: process (name = "upload"), a: file (name = "*.arc"), s: network STEPS a -read-> u THEN WITHIN 2min u -sendto-> s;')[0]
    assert [prune_score(f, x) for x in f.steps] == [4.5, 4.0]
    assert schedule(f, [0, 1]) == [0, 1]
    assert prune_score(f, f.steps[0], Weights(file_penalty=0)) == 5.0
    with pytest.raises(ValueError):
        logsearch_text(parse('TRACE BACKWARD FROM "x" IN STORE("h");')[0])
