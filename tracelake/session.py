"""An investigation: a catalog of named graphs, statements run in turn, a record that can be replayed."""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracelake import plans
from tracelake.graph import TraceGraph
from tracelake.lang import analyze, parse, text_of
from tracelake.lang.analyze import sql_of
from tracelake.lang.tree import Combine, Find, SeedText, Show, Trace
from tracelake.search import search
from tracelake.search.schedule import groups, prune_score, schedule
from tracelake.track import EdgeFilter, Limits, NodeFilter, Seed, track_many


@dataclass
class Catalog:
    """Named graphs. A new binding replaces an old one once it is materialised."""

    resident: bool = True
    graphs: dict[str, TraceGraph] = field(default_factory=dict)

    def bind(self, name: str, graph: TraceGraph) -> TraceGraph:
        kept = graph.resident() if self.resident else graph.stored()
        old = self.graphs.get(name)
        self.graphs[name] = kept
        if old is not None:
            old.events.unpersist()
        kept.events.createOrReplaceTempView(f"g_{name}")
        return kept

    def drop(self, name: str) -> None:
        self.graphs.pop(name).events.unpersist()

    def __getitem__(self, name: str) -> TraceGraph:
        return self.graphs[name]

    def footprint(self) -> dict[str, float]:
        """Bytes of each graph as Spark estimates them."""
        return {n: plans.estimate(g.events)["bytes"] for n, g in self.graphs.items()}


def condition(c, on: str):
    return None if c is None else F.expr(sql_of(c, on, ""))


class Session:
    """Runs texts of the language over a store."""

    def __init__(self, store, resident: bool = True, engine: str = "auto", mode: str = "score") -> None:
        self.store, self.catalog, self.engine, self.mode = store, Catalog(resident), engine, mode
        self.record: list[dict] = []

    def run(self, text: str) -> list:
        """Runs all statements of a text; gives what each made or showed."""
        statements = parse(text)
        warnings = analyze(statements, set(self.catalog.graphs), text)
        out = []
        for s in statements:
            began = time.monotonic()
            out.append(self._one(s))
            self.record.append({"text": text_of(s), "seconds": time.monotonic() - began, "warnings": warnings})
        return out

    def replay(self) -> list:
        """Runs the record again from the beginning."""
        texts, self.record = [r["text"] for r in self.record], []
        self.catalog = Catalog(self.catalog.resident)
        return [x for t in texts for x in self.run(t)]

    def explain(self, text: str) -> str:
        """Data queries of each search with scores and order; for a trace, its form and filters."""
        lines = []
        for s in parse(text):
            lines.append(text_of(s))
            if isinstance(s, Find):
                for group in groups(s):
                    for nth, k in enumerate(schedule(s, group, self.mode)):
                        step = s.steps[k]
                        lines.append(f"  {nth + 1}. step {k + 1}: {step.source} -{'|'.join(step.ops)}-> {step.sink}, score {prune_score(s, step):g}")
            elif isinstance(s, Trace):
                lines.append(f"  {s.direction}, engine {self.engine}, filters while tracing")
        return "\n".join(lines)

    def _source(self, source):
        return self.catalog[source.variable] if source.variable else self.store.host(*source.hosts)

    def _graph(self, e) -> TraceGraph:
        if isinstance(e, str):
            return self.catalog[e]
        a, b = self._graph(e[1]), self._graph(e[2])
        return {"UNION": a.union, "INTERSECT": a.intersect, "MINUS": a.minus}[e[0]](b)

    def _one(self, s):
        if isinstance(s, Show):
            return self._graph(s.expression).show(s.form)
        if isinstance(s, Find):
            made = search(s, self._source(s.source), self.mode, eager=None).graph
        elif isinstance(s, Trace):
            made = self.trace(s)
        else:
            assert isinstance(s, Combine)
            made = self._graph(s.expression)
        return self.catalog.bind(s.target, made) if s.target else made

    def run_batch(self, programs: dict[int, str]) -> dict[str, DataFrame]:
        """Runs programs of tracing and combining, one for each case, together: per variable (case_id, event_id).

        Statements that differ in their seed only are one pass over the store for all cases.
        """
        alike: dict[tuple, list] = {}
        texts = {case: parse(text) for case, text in programs.items()}
        for case, statements in texts.items():
            analyze(statements, set(), programs[case])
            alike.setdefault(tuple(text_of(replace(s, seed=SeedText("text", "")) if isinstance(s, Trace) else s) for s in statements), []).append(case)
        out: dict[str, DataFrame] = {}
        for cases in alike.values():
            own: dict[str, DataFrame] = {}
            for nth, s in enumerate(texts[cases[0]]):
                if isinstance(s, Combine):
                    made = self._pairs(s.expression, own)
                elif isinstance(s, Trace) and not s.source.variable and s.seed.kind != "variable":
                    seeds = [replace(self._seed(texts[c][nth]), case_id=c) for c in cases]
                    made = plans.pin(self._many(seeds, s).select("case_id", "event_id").distinct(), "batch")
                else:
                    raise ValueError(f"only traces of the store and combinations run in a batch: {text_of(s)}")
                own[s.target] = made
            for name, made in own.items():
                out[name] = made if name not in out else out[name].unionByName(made)
        return out

    def _pairs(self, e, own: dict[str, DataFrame]) -> DataFrame:
        if isinstance(e, str):
            return own[e]
        a, b = self._pairs(e[1], own), self._pairs(e[2], own)
        return {"UNION": lambda: a.unionByName(b).distinct(), "INTERSECT": lambda: a.intersect(b), "MINUS": lambda: a.subtract(b)}[e[0]]()

    def _many(self, seeds: list[Seed], s: Trace) -> DataFrame:
        """The traces of all seeds as a statement says."""
        nodes = NodeFilter(condition(s.keep_nodes, "entity"), condition(s.drop_nodes, "entity"))
        edges = EdgeFilter(condition(s.keep_edges, "event"), condition(s.drop_edges, "event"))
        limits = Limits(s.max_hops, s.max_span_us, None if s.budget_us is None else s.budget_us / 1e6)
        engine = "bound" if limits.budget_s is not None else self.engine
        return track_many(seeds, self._source(s.source), s.direction, nodes=nodes, edges=edges, limits=limits, engine=engine)

    def trace(self, s: Trace) -> TraceGraph:
        source = self._source(s.source)
        return TraceGraph(source.entities, self._many([self._seed(s)], s).drop("case_id"))

    def _seed(self, s: Trace) -> Seed:
        return {
            "variable": lambda: Seed.graph(self.catalog[s.seed.value]), "text": lambda: Seed.text(s.seed.value),
            "entity": lambda: Seed.entities(condition(s.seed.value, "entity")), "event": lambda: Seed.events(condition(s.seed.value, "event")),
        }[s.seed.kind]()
