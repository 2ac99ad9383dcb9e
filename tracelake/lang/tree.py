"""Statements as values, and their text."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class Compare:
    attribute: str
    op: str  # = != ~ !~ > >= < <= in
    value: object  # str, int, or a tuple of them


@dataclass(frozen=True)
class Not:
    of: object


@dataclass(frozen=True)
class Both:
    parts: tuple


@dataclass(frozen=True)
class Either:
    parts: tuple


@dataclass(frozen=True)
class Binding:
    name: str
    kind: str | None = None
    condition: object = None


@dataclass(frozen=True)
class Step:
    source: str
    sink: str
    ops: tuple = ()


@dataclass(frozen=True)
class Link:
    kind: str  # then, also, or
    within_us: int | None = None


@dataclass(frozen=True)
class Source:
    hosts: tuple = ()
    variable: str | None = None


@dataclass(frozen=True)
class Find:
    source: Source
    bindings: tuple
    steps: tuple
    links: tuple
    target: str | None = None


@dataclass(frozen=True)
class SeedText:
    kind: str  # variable, entity, event, text
    value: object


@dataclass(frozen=True)
class Trace:
    direction: str
    seed: SeedText
    source: Source
    keep_nodes: object = None
    drop_nodes: object = None
    keep_edges: object = None
    drop_edges: object = None
    max_hops: int | None = None
    max_span_us: int | None = None
    budget_us: int | None = None
    target: str | None = None


@dataclass(frozen=True)
class Combine:
    expression: object  # a name or (operator, left, right)
    target: str | None = None


@dataclass(frozen=True)
class Show:
    expression: object
    form: str = "edges"
    at: int = field(default=0, compare=False)


UNITS = {"ms": 1000, "s": 1_000_000, "min": 60_000_000, "h": 3_600_000_000, "d": 86_400_000_000}


def duration(us: int) -> str:
    unit = next(u for u in ("d", "h", "min", "s", "ms") if us % UNITS[u] == 0)
    return f"{us // UNITS[unit]}{unit}"


def _literal(value) -> str:
    if isinstance(value, tuple):
        return "(" + ", ".join(map(_literal, value)) + ")"
    if isinstance(value, str):
        return '"' + value.replace("\\", "\\\\").replace('"', '\\"') + '"'
    return str(value)


def condition_text(c) -> str:
    if isinstance(c, Compare):
        return f"{c.attribute} {c.op} {_literal(c.value)}"
    if isinstance(c, Not):
        return f"NOT ({condition_text(c.of)})"
    word = " AND " if isinstance(c, Both) else " OR "
    return "(" + word.join(condition_text(p) for p in c.parts) + ")"


def graph_text(e) -> str:
    return e if isinstance(e, str) else f"({graph_text(e[1])} {e[0]} {graph_text(e[2])})"


def _source(s: Source) -> str:
    return s.variable or "STORE(" + ", ".join(_literal(h) for h in s.hosts) + ")"


def text_of(statement) -> str:
    """A statement's text; parsing it gives the statement again."""
    target = f"{statement.target} := " if getattr(statement, "target", None) else ""
    if isinstance(statement, Find):
        names = []
        for b in statement.bindings:
            names.append(b.name + (f": {b.kind}" if b.kind else "") + (f" ({condition_text(b.condition)})" if b.condition else ""))
        steps = []
        for k, s in enumerate(statement.steps):
            if k:
                link = statement.links[k - 1]
                steps.append(link.kind.upper() + (f" WITHIN {duration(link.within_us)}" if link.within_us else ""))
            steps.append(f"{s.source} -{'|'.join(s.ops)}-> {s.sink}")
        return f"{target}FIND IN {_source(statement.source)} ENTITIES {', '.join(names)} STEPS {' '.join(steps)};"
    if isinstance(statement, Trace):
        seed = statement.seed
        start = {"variable": lambda: seed.value, "text": lambda: _literal(seed.value)}.get(seed.kind, lambda: f"{seed.kind.upper()} ({condition_text(seed.value)})")()
        clauses = []
        for what in ("nodes", "edges"):
            for word in ("keep", "drop"):
                if (c := getattr(statement, f"{word}_{what}")) is not None:
                    clauses.append(f" {word.upper()} {what.upper()} ({condition_text(c)})")
        limits = [("MAX HOPS", statement.max_hops and str(statement.max_hops)), ("MAX SPAN", statement.max_span_us and duration(statement.max_span_us)), ("BUDGET", statement.budget_us and duration(statement.budget_us))]
        clauses += [f" {word} {value}" for word, value in limits if value]
        way = {"back": "BACKWARD", "forward": "FORWARD"}[statement.direction]
        return f"{target}TRACE {way} FROM {start} IN {_source(statement.source)}{''.join(clauses)};"
    if isinstance(statement, Combine):
        return f"{target}COMBINE {graph_text(statement.expression)};"
    return f"SHOW {graph_text(statement.expression)} AS {statement.form.upper()};"
