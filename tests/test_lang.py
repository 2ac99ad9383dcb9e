"""The language: round trips, mistakes with their place, meaning."""

from __future__ import annotations

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from tracelake.lang import LangError, analyze, parse, text_of
from tracelake.lang.tree import Binding, Both, Combine, Compare, Either, Find, Link, Not, SeedText, Source, Step, Trace

_names = st.sampled_from(["a", "b", "poi1", "x_2"])
_leaf = st.one_of(
    st.builds(Compare, st.sampled_from(["name", "path", "cmdline"]), st.sampled_from(["=", "!=", "~", "!~"]), st.text('ab*"\\ /', max_size=5)),
    st.builds(Compare, st.sampled_from(["pid", "srcport"]), st.sampled_from([">", ">=", "<", "<=", "="]), st.integers(0, 9999)),
    st.builds(Compare, st.just("host"), st.just("in"), st.lists(st.text("ab", max_size=3), min_size=1, max_size=3).map(tuple)),
)
_condition = st.recursive(
    _leaf,
    lambda c: st.one_of(st.builds(Not, c), st.builds(Both, st.lists(c, min_size=2, max_size=3).map(tuple)), st.builds(Either, st.lists(c, min_size=2, max_size=3).map(tuple))),
    max_leaves=6,
)
_source = st.one_of(st.builds(Source, st.lists(st.text("ho1", min_size=1, max_size=4), min_size=1, max_size=2).map(tuple)), st.builds(lambda v: Source(variable=v), _names))
_us = st.one_of(st.none(), st.sampled_from([1000, 2_000_000, 120_000_000, 3_600_000_000]))
_graph = st.recursive(_names, lambda g: st.tuples(st.sampled_from(["UNION", "INTERSECT", "MINUS"]), g, g), max_leaves=4)


@st.composite
def _finds(draw):
    n = draw(st.integers(1, 3))
    steps = tuple(Step(draw(_names), draw(_names), tuple(draw(st.lists(st.sampled_from(["read", "write"]), max_size=2, unique=True)))) for _ in range(n))
    links = []
    for _ in range(n - 1):
        kind = draw(st.sampled_from(["then", "also", "or"]))
        links.append(Link(kind, None if kind == "or" else draw(_us)))
    bindings = tuple(Binding(x, draw(st.sampled_from([None, "process", "file"])), draw(st.one_of(st.none(), _condition))) for x in ("a", "b"))
    return Find(draw(_source), bindings, steps, tuple(links), draw(st.one_of(st.none(), _names)))


_traces = st.builds(
    Trace, st.sampled_from(["back", "forward"]), st.one_of(st.builds(SeedText, st.just("variable"), _names), st.builds(SeedText, st.just("text"), st.text('a"', max_size=3)), st.builds(SeedText, st.just("entity"), _condition)),
    _source, st.one_of(st.none(), _condition), st.one_of(st.none(), _condition), max_hops=st.one_of(st.none(), st.integers(1, 9)), max_span_us=_us, budget_us=_us, target=st.one_of(st.none(), _names),
)


@settings(max_examples=200, deadline=None)
@given(st.one_of(_finds(), _traces, st.builds(Combine, _graph, _names)))
def test_text_and_back(statement):
    assert parse(text_of(statement)) == [statement]


@pytest.mark.parametrize(
    "text, line",
    [("FIND IN x", 1), ("SHOW a\nAS pictures;", 1), ("TRACE SIDEWAYS FROM a IN b;", 1), ("a := \n\n COMBINE (a UNION;", 3), ("SHOW $;", 1), ("FIND IN x ENTITIES a STEPS a -read-> b OR WITHIN 2s a -> b;", 1)],
)
def test_mistakes_have_a_place(text, line):
    with pytest.raises(LangError) as e:
        parse(text)
    assert e.value.line == line


@pytest.mark.parametrize(
    "text",
    [
        "SHOW nothing;", "FIND IN STORE(\"h\") ENTITIES a, a STEPS a -> a;", "FIND IN STORE(\"h\") ENTITIES a STEPS a -> b;", "FIND IN STORE(\"h\") ENTITIES a, b, c STEPS a -> b;",
        "FIND IN STORE(\"h\") ENTITIES a: file (pid = 3), b STEPS a -> b;", "FIND IN STORE(\"h\") ENTITIES a (pid = \"x\"), b STEPS a -> b;", "FIND IN STORE(\"h\") ENTITIES a (colour = 3), b STEPS a -> b;",
        "FIND IN STORE(\"h\") ENTITIES a, b STEPS a -fly-> b;", "TRACE BACKWARD FROM x IN STORE(\"h\");", "FIND IN STORE(\"h\") ENTITIES a (type = \"cloud\"), b STEPS a -> b;",
    ],
)
def test_meaning_is_checked(text):
    with pytest.raises(LangError):
        analyze(parse(text))


def test_product_is_flagged():
    assert analyze(parse('FIND IN STORE("h") ENTITIES a, b, c, d STEPS a -> b ALSO c -> d;'))


def test_binding_strength():
    assert parse("x := COMBINE a MINUS b INTERSECT c UNION d;")[0].expression == ("UNION", ("MINUS", "a", ("INTERSECT", "b", "c")), "d")


def test_calls_make_the_same_statements():
    from tracelake.lang.builder import find, trace

    text = 'x := FIND IN STORE("h") ENTITIES f: file (name = "*.arc"), p: process, s STEPS f -read|readv-> p THEN WITHIN 2min p -sendto-> s OR p -> s;'
    made = find("h").entity("f", "file", 'name = "*.arc"').entity("p", "process").entity("s").step("f", "read|readv", "p").then("p", "sendto", "s", within=(2, "min")).either("p", "", "s").build("x")
    assert parse(text) == [made]
    text = 'TRACE BACKWARD FROM ENTITY (pid = 3) IN g DROP NODES (path ~ "/lib") MAX HOPS 3 MAX SPAN 1h;'
    assert parse(text) == [trace("back", ("entity", "pid = 3"), inside="g", drop_nodes='path ~ "/lib"', max_hops=3, span=(1, "h"))]
