"""Runs a pattern: data queries, feedback of what was found, assembly; and the single statements to compare with."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracelake import functions as X
from tracelake import plans
from tracelake.graph import TraceGraph
from tracelake.lang.analyze import sql_of
from tracelake.lang.tree import Find
from tracelake.search import schedule as S

#: Up to so many found ids restrict another step as a literal list, up to the second number by a broadcast.
LITERAL_IDS = 1000
BROADCAST_IDS = 200_000
#: Where it is left to the engine, steps over up to so many bytes of events are one plan: writing each costs more than it saves.
ONE_PLAN_BYTES = 256 * 2**20
_STEP = ("event_id", "src_id", "dst_id", "start_us", "end_us")


@dataclass
class SearchResult:
    """bindings: one row per match, e<k> (event of step k) and v_<name> (entity); order and rows tell how it ran."""

    bindings: DataFrame
    graph: TraceGraph
    order: list[int]
    rows: dict[int, int]


def entity_ids(find: Find, name: str, source) -> DataFrame | None:
    """Entities that a binding allows; None if it allows all."""
    b = next(b for b in find.bindings if b.name == name)
    if b.kind is None and b.condition is None:
        return None
    out = source.entities
    if b.kind:
        out = out.where(F.col("kind") == b.kind)
    if b.condition is not None:
        out = out.where(F.expr(sql_of(b.condition, "entity", "")))
    return out.select(F.col("entity_id").alias("ok_id"))


def step_query(find: Find, k: int, source) -> DataFrame:
    """Events of one step under its own conditions."""
    step = find.steps[k]
    out = source.events
    if step.ops:
        out = out.where(F.col("op").isin(*step.ops))
    for end, name in (("src_id", step.source), ("dst_id", step.sink)):
        ids = entity_ids(find, name, source)
        if ids is not None:
            out = out.join(ids, F.col(end) == F.col("ok_id"), "left_semi")
    if step.source == step.sink:
        out = out.where(F.col("src_id") == F.col("dst_id"))
    return out.select(*_STEP)


def restrict(rows: DataFrame, end: str, found: DataFrame) -> DataFrame:
    """Rows whose end was found by another step: a literal list, a broadcast, or a shuffle, by the number of ids."""
    ids = found.distinct()
    few = [r[0] for r in ids.limit(LITERAL_IDS + 1).collect()]
    if len(few) <= LITERAL_IDS:
        return rows.where(F.col(end).isin(*few)) if few else rows.where(F.lit(False))
    ids = ids.toDF("found_id")
    if ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS:
        ids = F.broadcast(ids)
    return rows.join(ids, F.col(end) == F.col("found_id"), "left_semi")


def restrict_time(rows: DataFrame, found: DataFrame, link, forward: bool) -> DataFrame:
    """Rows whose start can meet a time bound with some row found."""
    low, high = found.agg(F.min("start_us"), F.max("start_us")).first()
    if low is None:
        return rows.where(F.lit(False))
    ordered = link.kind == "then"
    if link.within_us is None:
        if not ordered:
            return rows
        return rows.where(F.col("start_us") >= low) if forward else rows.where(F.col("start_us") <= high)
    before = 0 if ordered and forward else link.within_us
    after = 0 if ordered and not forward else link.within_us
    return rows.where(F.col("start_us").between(low - before, high + after))


def _assemble(find: Find, order: list[int], found: dict[int, DataFrame]) -> DataFrame:
    """Joins the steps on shared entities under the time relations."""
    out, seen = None, []
    for k in order:
        step = find.steps[k]
        own = found[k].select(F.col("event_id").alias(f"e{k}"), F.col("start_us").alias(f"s{k}"), F.col("src_id").alias(f"a{k}"), F.col("dst_id").alias(f"b{k}"))
        if out is None:
            out = own
        else:
            on = None
            for j in seen:
                for x, n in ((f"a{j}", find.steps[j].source), (f"b{j}", find.steps[j].sink)):
                    for y, m in ((f"a{k}", step.source), (f"b{k}", step.sink)):
                        if n == m:
                            on = (F.col(x) == F.col(y)) if on is None else on & (F.col(x) == F.col(y))
            for j in seen:
                if abs(j - k) == 1 and (link := find.links[min(j, k)]) and link.kind != "or":
                    first, second = F.col(f"s{min(j, k)}"), F.col(f"s{max(j, k)}")
                    rule = None
                    if link.within_us is not None:
                        rule = X.within(first, second, link.within_us, link.kind == "then")
                    elif link.kind == "then":
                        rule = second >= first
                    if rule is not None:
                        on = rule if on is None else on & rule
            out = out.crossJoin(own) if on is None else out.join(own, on)
        seen.append(k)
    names: dict[str, str] = {}
    for k in seen:
        names.setdefault(find.steps[k].source, f"a{k}")
        names.setdefault(find.steps[k].sink, f"b{k}")
    return out.select(*[f"e{k}" for k in sorted(seen)], *[F.col(c).alias(f"v_{n}") for n, c in sorted(names.items())])


def search(
    find: Find, source, mode: str = "score", eager: bool | None = True, weights: S.Weights = S.Weights(), limit: int | None = None, too_broad: int | None = None,
) -> SearchResult:
    """All matches of a pattern in a store or a graph.

    Eager: steps run one by one in scheduled order; what a step found restricts
    the connected ones; a step without rows ends its conjunction. Otherwise the
    whole pattern is one plan and restricting is left to the optimiser. None takes
    the first for events of more than ``ONE_PLAN_BYTES``, else the second. With
    ``too_broad`` a first step of more rows makes its conjunction lazy.
    """
    parts, ran, rows = [], [], {}
    if eager is None:
        eager = plans.input_bytes(source.events) > ONE_PLAN_BYTES
    for group in S.groups(find):
        counts = None
        if mode == "stats":
            counts = {k: step_query(find, k, source).count() for k in group}
        order = S.schedule(find, group, mode, weights, counts)
        found: dict[int, DataFrame] = {}
        go = eager
        for k in order:
            own = step_query(find, k, source)
            if go:
                for j in found:
                    for end, n in (("src_id", find.steps[k].source), ("dst_id", find.steps[k].sink)):
                        for other, m in (("src_id", find.steps[j].source), ("dst_id", find.steps[j].sink)):
                            if n == m:
                                own = restrict(own, end, found[j].select(other))
                    if abs(j - k) == 1:
                        own = restrict_time(own, found[j], find.links[min(j, k)], k > j)
                own = plans.pin(own, f"step{k}")
                rows[k] = own.count()
                if too_broad is not None and not found and rows[k] > too_broad:
                    go = False
            found[k] = own
            ran.append(k)
            if go and rows[k] == 0:
                found |= {j: step_query(find, j, source).where(F.lit(False)) for j in order if j not in found}
                break
        parts.append(_assemble(find, order, found))
    bindings = parts[0]
    for p in parts[1:]:
        bindings = bindings.unionByName(p, allowMissingColumns=True)
    if limit is not None:
        bindings = bindings.orderBy(*sorted(c for c in bindings.columns if c[0] == "e")).limit(limit)
    ids = bindings.select(F.explode(F.array(*[c for c in bindings.columns if c[0] == "e"])).alias("hit")).where("hit is not null").distinct()
    events = source.events.join(ids, F.col("event_id") == F.col("hit"), "left_semi")
    return SearchResult(bindings, TraceGraph(source.entities, events), ran, rows)


def monolithic_sql(find: Find, events: str = "ev", entities: str = "ent") -> str:
    """The whole pattern as one statement, joins and conditions in the order of the text; for Spark and DuckDB."""
    out = []
    all_names = sorted({x for s in find.steps for x in (s.source, s.sink)})
    every = [f"e{k}" for k in range(len(find.steps))]
    for group in S.groups(find):
        names = [b for b in find.bindings if any(b.name in (find.steps[k].source, find.steps[k].sink) for k in group)]
        tables = [f"{entities} v_{b.name}" for b in names] + [f"{events} e{k}" for k in group]
        where = []
        for b in names:
            if b.kind:
                where.append(f"v_{b.name}.kind = '{b.kind}'")
            if b.condition is not None:
                where.append(sql_of(b.condition, "entity", f"v_{b.name}"))
        for k in group:
            step = find.steps[k]
            where += [f"e{k}.src_id = v_{step.source}.entity_id", f"e{k}.dst_id = v_{step.sink}.entity_id"]
            if step.ops:
                where.append(f"e{k}.op IN ({', '.join(repr(o) for o in step.ops)})")
            if k + 1 in group:
                link = find.links[k]
                gap = f"e{k + 1}.start_us - e{k}.start_us"
                if link.kind == "then":
                    where.append(f"{gap} >= 0")
                if link.within_us is not None:
                    where.append(f"{gap} < {link.within_us}" if link.kind == "then" else f"abs({gap}) < {link.within_us}")
        own = {b.name for b in names}
        columns = [f"e{k}.event_id AS e{k}" if k in group else f"CAST(NULL AS BIGINT) AS e{k}" for k in range(len(every))]
        columns += [f"v_{n}.entity_id AS v_{n}" if n in own else f"CAST(NULL AS VARCHAR(200)) AS v_{n}" for n in all_names]
        out.append(f"SELECT {', '.join(columns)} FROM {' CROSS JOIN '.join(tables)} WHERE {' AND '.join(where)}")
    return " UNION ALL ".join(out)


def joined_sql(find: Find, events: str = "ev", entities: str = "ent") -> str:
    """The same result with each step cut to its operations first, then joined step by step on shared entities and times."""
    parts = []
    all_names = sorted({x for s in find.steps for x in (s.source, s.sink)})
    for group in S.groups(find):
        tables, place = [], {}
        for k in group:
            step = find.steps[k]
            rules = [f"op IN ({', '.join(repr(o) for o in step.ops)})"] if step.ops else []
            rules += ["src_id = dst_id"] if step.source == step.sink else []
            own = f"(SELECT event_id, src_id, dst_id, start_us FROM {events}{' WHERE ' * bool(rules)}{' AND '.join(rules)}) e{k}"
            on = [f"e{k}.{end} = {place[n]}" for end, n in (("src_id", step.source), ("dst_id", step.sink)) if n in place]
            if k - 1 in group:
                link, gap = find.links[k - 1], f"e{k}.start_us - e{k - 1}.start_us"
                if link.kind == "then":
                    on.append(f"{gap} >= 0")
                if link.within_us is not None:
                    on.append(f"{gap if link.kind == 'then' else f'abs({gap})'} < {link.within_us}")
            tables.append(own if not tables else f"JOIN {own} ON {' AND '.join(on) or 'true'}")
            place.setdefault(step.source, f"e{k}.src_id")
            place.setdefault(step.sink, f"e{k}.dst_id")
        for b in find.bindings:
            if b.name in place:
                rules = [f"v_{b.name}.entity_id = {place[b.name]}"] + ([f"v_{b.name}.kind = '{b.kind}'"] if b.kind else [])
                rules += [sql_of(b.condition, "entity", f"v_{b.name}")] if b.condition is not None else []
                tables.append(f"JOIN {entities} v_{b.name} ON {' AND '.join(rules)}")
        columns = [f"e{k}.event_id AS e{k}" if k in group else f"CAST(NULL AS BIGINT) AS e{k}" for k in range(len(find.steps))]
        columns += [f"{place[n]} AS v_{n}" if n in place else f"CAST(NULL AS VARCHAR) AS v_{n}" for n in all_names]
        parts.append(f"SELECT {', '.join(columns)} FROM {' '.join(tables)}")
    return " UNION ALL ".join(parts)


def run_monolithic(find: Find, source) -> DataFrame:
    source.events.createOrReplaceTempView("mono_events")
    source.entities.createOrReplaceTempView("mono_entities")
    return source.events.sparkSession.sql(monolithic_sql(find, "mono_events", "mono_entities"))


def motif_join(find: Find, source) -> DataFrame:
    """Joins of steps in the order of the text, all conditions on entities last."""
    found = {}
    for k, step in enumerate(find.steps):
        own = source.events.where(F.col("op").isin(*step.ops)) if step.ops else source.events
        found[k] = own.select(*_STEP)
    out = _assemble(find, list(range(len(find.steps))), found)
    for b in find.bindings:
        ids = entity_ids(find, b.name, source)
        if ids is not None:
            out = out.join(ids, F.col(f"v_{b.name}") == F.col("ok_id"), "left_semi")
    return out


def graph_text(find: Find) -> str:
    """The pattern in the manner of graph query languages."""
    paths = [f"(v_{s.source})-[e{k}{':' + '|'.join(s.ops) if s.ops else ''}]->(v_{s.sink})" for k, s in enumerate(find.steps)]
    where = [f"v_{b.name}.kind = '{b.kind}'" for b in find.bindings if b.kind]
    where += [sql_of(b.condition, "entity", f"v_{b.name}") for b in find.bindings if b.condition is not None]
    for k, link in enumerate(find.links):
        where.append(f"e{k + 1}.start_us - e{k}.start_us < {link.within_us}" if link.within_us else f"e{k}.start_us <= e{k + 1}.start_us")
    return f"MATCH {', '.join(paths)} WHERE {' AND '.join(where)} RETURN *"


def logsearch_text(statement) -> str:
    """A search as a pipeline of a log-search language, which has no recursion: a trace raises."""
    if not isinstance(statement, Find):
        raise ValueError("a log-search language can't express tracking")
    own = {b.name: b for b in statement.bindings}
    out = []
    for k, s in enumerate(statement.steps):
        terms = [f"op IN ({', '.join(s.ops)})"] if s.ops else []
        for end, name in (("src", s.source), ("dst", s.sink)):
            b = own[name]
            terms += [f"{end}_kind = {b.kind}"] if b.kind else []
            terms += [sql_of(b.condition, "entity", end)] if b.condition is not None else []
        out.append(f"search {' '.join(terms)} | rename event_id AS e{k}")
    body = out[0]
    for k, part in enumerate(out[1:]):
        link = statement.links[k]
        body += f" | join type=inner [ {part} ]" + (f" | where start{k + 1} - start{k} < {link.within_us}" if link.within_us else "")
    return body
