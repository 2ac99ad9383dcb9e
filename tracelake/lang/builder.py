"""The language from Python: the same statements, made by calls."""

from __future__ import annotations

from tracelake.lang.parser import parse
from tracelake.lang.tree import UNITS, Binding, Find, Link, SeedText, Source, Step, Trace


def _condition(text: str | None):
    return None if text is None else parse(f"TRACE BACKWARD FROM ENTITY ({text}) IN STORE(\"h\");")[0].seed.value


def _us(number: float, unit: str) -> int:
    return int(number * UNITS[unit])


class FindBuilder:
    """``find("host1").entity("p", "process", 'pid = 3').step("f", "read", "p").then("p", "sendto", "s", within=(2, "min")).build()``"""

    def __init__(self, *hosts: str, inside: str | None = None) -> None:
        self._source = Source(variable=inside) if inside else Source(tuple(hosts))
        self._bindings, self._steps, self._links = [], [], []

    def entity(self, name: str, kind: str | None = None, where: str | None = None) -> FindBuilder:
        self._bindings.append(Binding(name, kind, _condition(where)))
        return self

    def step(self, source: str, ops: str, sink: str) -> FindBuilder:
        self._steps.append(Step(source, sink, tuple(ops.split("|")) if ops else ()))
        return self

    def _linked(self, kind: str, source: str, ops: str, sink: str, within) -> FindBuilder:
        self._links.append(Link(kind, None if within is None else _us(*within)))
        return self.step(source, ops, sink)

    def then(self, source: str, ops: str, sink: str, within=None) -> FindBuilder:
        return self._linked("then", source, ops, sink, within)

    def also(self, source: str, ops: str, sink: str, within=None) -> FindBuilder:
        return self._linked("also", source, ops, sink, within)

    def either(self, source: str, ops: str, sink: str) -> FindBuilder:
        return self._linked("or", source, ops, sink, None)

    def build(self, target: str | None = None) -> Find:
        return Find(self._source, tuple(self._bindings), tuple(self._steps), tuple(self._links), target)


def find(*hosts: str, inside: str | None = None) -> FindBuilder:
    return FindBuilder(*hosts, inside=inside)


def trace(direction: str, seed: tuple[str, str], *hosts: str, inside: str | None = None, target: str | None = None, span=None, **clauses) -> Trace:
    """``trace("back", ("entity", 'pid = 3'), "host1", drop_nodes='path ~ "/lib"', max_hops=3, span=(1, "h"))``"""
    kind, value = seed
    found = {k: _condition(v) if k.split("_")[0] in ("keep", "drop") else v for k, v in clauses.items()}
    source = Source(variable=inside) if inside else Source(tuple(hosts))
    start = SeedText(kind, _condition(value) if kind in ("entity", "event") else value)
    return Trace(direction, start, source, target=target, max_span_us=None if span is None else _us(*span), **found)
