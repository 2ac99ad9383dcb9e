"""Thirty planted cases in five families, on top of the events of the given tables.

Truth rows are a case's own events; weave rows tie its processes to background
files, so that plain tracing runs into everything else. Other weave rows are of
a kind that no program names: an updater writes shared libraries that the case's
processes load. All numbers follow from
the case number; nothing is random. The programs are written by hand for each
family, as an investigator would: they show what the language can do and are no
automatic detection.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from tracelake.functions import file_key
from tracelake.model import schema, views
from tracelake.model.store import TraceStore

FAMILIES = {"MS": range(1, 9), "EX": range(9, 19), "MW": range(19, 24), "RT": range(24, 27), "EN": range(27, 31)}
OUTSIDE = "198.51.100.7"
_MINUTE = 60_000_000
_JAN = 1_704_067_200_000_000  # 2024-01-01 in microseconds


def family(case: int) -> str:
    return next(f for f, cases in FAMILIES.items() if case in cases)


@dataclass(frozen=True)
class Row:
    case_id: int
    step: int
    stage: int
    truth: bool
    op: str
    host: str
    source: str
    sink: str
    background: int  # number of the background file at one end, -1 for none
    start_us: int


def _p(host: int, exe: str, pid: int) -> str:
    return f"p:host{host}:{exe}:{pid}"


def _f(host: int, path: str) -> str:
    return f"f:host{host}:{path}"


def _n(src: str, sport: int, dst: str, dport: int) -> str:
    return f"n:tcp:{src}:{sport}:{dst}:{dport}"


def _edge(source: str, sink: str) -> tuple[str, str]:
    """Operation and host of the flow between two planted entities."""
    op = {"fp": "read", "pf": "write", "np": "recvfrom", "pn": "sendto", "pp": "clone"}[source[0] + sink[0]]
    return op, (sink if sink[0] == "p" and source[0] != "p" else source).split(":")[1]


def template(case: int) -> list[tuple[int, str, str]]:
    """(stage, source, sink) of a case's own events in the order of time."""
    base, kind = case * 1000, family(case)
    inner = lambda h, port: f"10.{case}.{h}.10"  # noqa: E731, ARG005
    p = lambda h, exe, pid: _p(h, exe, base + pid)
    into = _n(OUTSIDE, 40000 + case, inner(1, 80), 80)
    out = _n(inner(1, 0), 52003, OUTSIDE, 443)
    if kind == "MS":
        probe, login, copy = (_n(inner(1, 0), 52000 + k, inner(2, 0), 22) for k in range(3))
        web, sh, scan, rlogin, copyc, upload = p(1, "webd", 101), p(1, "sh", 102), p(1, "scan", 103), p(1, "rlogin", 104), p(1, "copyc", 105), p(1, "upload", 106)
        rlogind, sh2, pack, copyd = p(2, "rlogind", 201), p(2, "sh", 202), p(2, "pack", 203), p(2, "copyd", 204)
        there, here = _f(2, f"/tmp/{case}/bundle.arc"), _f(1, f"/tmp/{case}/bundle.arc")
        secrets = [_f(2, "/etc/accounts"), _f(2, "/etc/secrets"), *[_f(2, f"/etc/{case}/secret{k}") for k in range(case % 7 if case != 2 else 0)]]
        rows = [(1, into, web), (1, web, sh), (2, sh, scan), (2, scan, probe), (2, sh, rlogin), (2, rlogin, login), (2, login, rlogind), (3, rlogind, sh2), (3, sh2, pack)]
        rows += [(3, s, pack) for s in secrets] + [(3, pack, there), (4, sh, copyc), (4, there, copyd), (4, copyd, copy), (4, copy, copyc), (4, copyc, here), (4, sh, upload), (4, here, upload), (4, upload, out)]
        return rows
    if kind == "EX":
        fetch = p(1, "fetch", 101)
        rows, at = [(1, into, fetch)], fetch
        for k in range((6 + case % 5) // 2):
            script, run = _f(1, f"/home/{case}/part{k}"), p(1, "interp", 110 + k)
            rows += [(2, at, script), (2, script, run)]
            at = run
        return [*rows, (3, at, _f(1, f"/home/{case}/target"))]
    if kind == "MW":
        sample, main = _f(1, f"/home/{case}/sample.bin"), p(1, "sample", 101)
        kids = [p(1, "worker", 110 + k) for k in range(3)]
        rows = [(1, sample, main), *[(2, main, k) for k in kids]]
        rows += [(3, k, _f(1, f"/home/{case}/damaged{n}_{m}")) for n, k in enumerate(kids) for m in range(2 + (case % 7 if n == 0 else 0))]
        return [*rows, (3, kids[0], out)]
    if kind == "RT":
        wire, wire2 = _n(inner(1, 0), 52010, inner(2, 0), 22), _n(inner(2, 0), 52011, inner(3, 0), 22)
        browser, loader, root = p(1, "browser", 101), p(1, "loader", 102), p(1, "rootsh", 103)
        drop = _f(1, f"/tmp/{case}/drop")
        r2, a2, f2, g2 = p(2, "rlogind", 201), p(2, "agent", 202), _f(2, f"/tmp/{case}/agent"), p(2, "agentx", 203)
        r3, c3 = p(3, "rlogind", 301), p(3, "collect", 302)
        away = _n(inner(3, 0), 52012, OUTSIDE, 443)
        rows = [(1, into, browser), (1, browser, drop), (1, drop, loader), (2, loader, root), (2, root, wire), (2, wire, r2), (2, r2, a2), (2, a2, f2), (2, f2, g2), (3, g2, wire2), (3, wire2, r3), (3, r3, c3)]
        return rows + [(3, _f(3, f"/etc/{case}/secret{k}"), c3) for k in range(5 + case % 3)] + [(4, c3, away)]
    doc, editor, sh, fetch = _f(1, f"/mail/{case}/note.doc"), p(1, "editor", 101), p(1, "sh", 102), p(1, "fetch", 103)
    stored = _f(1, f"/auto/{case}/start")
    rows = [(1, doc, editor), (1, editor, sh), (2, sh, fetch), (2, into, fetch), (2, fetch, stored)]
    at, wire = p(1, "autostart", 104), _n(inner(1, 0), 52020, inner(2, 0), 22)
    rows += [(3, stored, at), (3, at, wire), (3, wire, p(2, "rlogind", 201))]
    at = p(2, "rlogind", 201)
    for k in range(2 + case % 5 // 2):
        nxt = _f(2, f"/tmp/{case}/stage{k}")
        rows += [(4, at, nxt), (4, nxt, p(2, "stage", 210 + k))]
        at = p(2, "stage", 210 + k)
    return rows


def anchor(case: int) -> int:
    return _JAN + (1 + case % 26) * 86_400_000_000 + case * 3_600_000_000


def rows(case: int) -> list[Row]:
    """A case's truth and weave rows."""
    out, seen = [], {}
    t0 = anchor(case)
    for s, (stage, a, b) in enumerate(template(case), 1):
        op, host = _edge(a, b)
        at = t0 + s * _MINUTE
        out.append(Row(case, s, stage, True, op, host, a, b, -1, at))
        for x in (a, b):
            if x[0] == "p" and x not in seen:
                seen[x] = at
    step = 100
    for x, at in seen.items():
        host = x.split(":")[1]
        for j in range(7):
            k = (7 * case + j) % 100
            if j < 5:
                out.append(Row(case, step, 0, False, "read", host, "", x, k, at - 30_000_000 - (j + 1) * _MINUTE))
            else:
                out.append(Row(case, step, 0, False, "write", host, x, "", k, at + 30_000_000 + (j + 1) * _MINUTE))
            step += 1
    step = 500
    for nth, (x, at) in enumerate(seen.items()):
        if nth % 2 == 0:
            host = x.split(":")[1]
            library, updater = f"f:{host}:/usr/lib/{case}/shared{nth}", f"p:{host}:updater:{9_000_000 + case}"
            out.append(Row(case, step, 0, False, "write", host, updater, library, -1, at - 10 * _MINUTE))
            out.append(Row(case, step + 1, 0, False, "read", host, library, x, -1, at - 5_000_000))
            step += 2
    return out


def event_id(case: int, step: int) -> int:
    return 10_000_000_000 + case * 1000 + step


def poi(case: int) -> int:
    """Step of the event from which the case is investigated: mid-chain for EN, the first for MW, else the last."""
    n = len(template(case))
    return {"EN": 6, "MW": 1}.get(family(case), n)


def _entity(key: str) -> tuple:
    parts = key.split(":")
    if key[0] == "p":
        return key, "process", parts[1], parts[2], f"/opt/{parts[2]}", parts[2], f"/opt/{parts[2]}", f"{parts[2]} --case", int(parts[3]), None, None, None, None, None
    if key[0] == "f":
        return key, "file", parts[1], parts[2].rsplit("/", 1)[1], parts[2], None, None, None, None, None, None, None, None, None
    return key, "network", None, key[2:], None, None, None, None, None, parts[2], parts[4], "tcp", int(parts[3]), int(parts[5])


_ENTITY = "entity_id string, kind string, host string, name string, path string, exe_name string, exe_path string, cmdline string, pid bigint, src_ip string, dst_ip string, protocol string, src_port int, dst_port int"


def plant(spark: SparkSession, sf_dir: str, which=range(1, 31)) -> TraceStore:
    """The events of the given tables with the planted cases; events have case_id, stage and is_truth besides."""
    base = views.events(spark, sf_dir)
    every = [r for c in which for r in rows(c)]
    planted = spark.createDataFrame(
        [(event_id(r.case_id, r.step), r.case_id, r.stage, r.truth, r.op, r.host, r.source or None, r.sink or None, r.background, r.start_us) for r in every],
        "event_id bigint, case_id bigint, stage int, is_truth boolean, op string, host string, source string, sink string, k bigint, start_us bigint",
    )
    files = views._files(spark, sf_dir).select("k", "path", "file_name")
    planted = planted.join(files, "k", "left").withColumn("file_id", F.when(F.col("k") >= 0, file_key(F.col("host"), F.col("path"))))
    src, dst = F.coalesce("source", "file_id"), F.coalesce("sink", "file_id")
    subject = F.when(F.col("op").isin(*schema.INWARD), dst).otherwise(src)
    end = F.col("start_us") + 20_000_000
    own = planted.select(
        "event_id", "host", F.when(F.col("op").isin("read", "write"), "file").when(F.col("op").isin("recvfrom", "sendto"), "network").otherwise("process").alias("category"), "op",
        subject.alias("subject_id"), F.when(F.col("op").isin(*schema.INWARD), src).otherwise(dst).alias("object_id"), src.alias("src_id"), dst.alias("dst_id"), "start_us",
        end.alias("end_us"), F.lit(20_000_000).cast("bigint").alias("duration_us"), (F.lit(1000) + F.col("stage") * 100).cast("bigint").alias("amount"),
        F.to_date(F.timestamp_micros("start_us")).alias("day"), F.col("case_id").alias("plant_case"), "stage", "is_truth",
    )
    events = base.events.withColumns({"plant_case": F.lit(None).cast("bigint"), "stage": F.lit(None).cast("int"), "is_truth": F.lit(False)}).unionByName(own)
    keys = sorted({k for r in every for k in (r.source, r.sink) if k})
    entities = views._with_all(spark.createDataFrame([_entity(k) for k in keys], _ENTITY), schema.ENTITY_COLUMNS)
    woven = planted.where("k >= 0").select(F.col("file_id").alias("entity_id"), F.lit("file").alias("kind"), "host", F.col("file_name").alias("name"), "path").distinct()
    woven = views._with_all(woven, schema.ENTITY_COLUMNS).join(base.entities.select("entity_id"), "entity_id", "left_anti").select(*schema.ENTITY_COLUMNS)
    return TraceStore(base.entities.unionByName(entities).unionByName(woven), events)


def planted_sql(which=range(1, 31)) -> str:
    """CTEs ``planted`` and ``pev`` (all events with the planted ones) for DuckDB, on top of the events' CTEs."""
    q = lambda s: f"'{s}'" if s else "NULL"
    values = ", ".join(
        f"({event_id(r.case_id, r.step)}, {r.case_id}, {r.stage}, {str(r.truth).lower()}, '{r.op}', '{r.host}', {q(r.source)}, {q(r.sink)}, {r.background}, {r.start_us})" for c in which for r in rows(c)
    )
    return f"""
    t_plant(event_id, case_id, stage, is_truth, op, host, source, sink, k, start_us) AS (VALUES {values}),
    planted AS (SELECT p.event_id, case_id, stage, is_truth, op, p.host, coalesce(source, 'f:' || p.host || ':' || f.path) AS src_id, coalesce(sink, 'f:' || p.host || ':' || f.path) AS dst_id,
                       start_us, start_us + 20000000 AS end_us, f.path AS wpath FROM t_plant p LEFT JOIN t_files f ON f.k = p.k),
    pev AS (SELECT event_id, host, op, src_id, dst_id, start_us, end_us, false AS is_truth, CAST(NULL AS BIGINT) AS plant_case FROM ev
            UNION ALL SELECT event_id, host, op, src_id, dst_id, start_us, end_us, is_truth, case_id FROM planted)"""


def entities_sql(which=range(1, 31)) -> str:
    """CTE ``pent``: the entities of the given tables and the planted ones, with the attributes that searches name."""
    keys = sorted({k for c in which for r in rows(c) for k in (r.source, r.sink) if k})
    q = lambda x: "NULL" if x is None else str(x) if isinstance(x, int) else f"'{x}'"
    values = ", ".join(f"({', '.join(q(_entity(k)[i]) for i in (0, 1, 3, 8, 9))})" for k in keys)
    return f"""
    t_pent(entity_id, kind, name, pid, src_ip) AS (VALUES {values}),
    pent AS MATERIALIZED (
        SELECT entity_id, kind, name, CAST(pid AS BIGINT) AS pid, src_ip FROM ent UNION SELECT entity_id, kind, name, CAST(pid AS BIGINT), src_ip FROM t_pent
        UNION SELECT 'f:' || p.host || ':' || f.path, 'file', f.file_name, NULL, NULL FROM t_plant p JOIN t_files f ON f.k = p.k)"""


def program(case: int) -> str:
    """The investigation of a case in the language; its result is bound to ``story``."""
    start = f"EVENT (id = {event_id(case, poi(case))})"
    hosts = 'STORE("host1", "host2", "host3")'
    drop = 'DROP NODES (path ~ "/brand")'
    kind = family(case)
    if kind == "MW":
        return f"story := TRACE FORWARD FROM {start} IN {hosts} {drop};"
    if kind == "EN":
        return f"past := TRACE BACKWARD FROM {start} IN {hosts} {drop}; after := TRACE FORWARD FROM {start} IN {hosts} {drop}; story := COMBINE past UNION after;"
    return f"story := TRACE BACKWARD FROM {start} IN {hosts} {drop};"


def search_text(case: int) -> str:
    """The search of a case: its telling pair of steps."""
    hosts = 'STORE("host1", "host2", "host3")'
    low, high = case * 1000, case * 1000 + 999
    own = f"pid >= {low}, pid <= {high}"
    return {
        "MS": f'FIND IN {hosts} ENTITIES u: process (name = "upload", {own}), a: file (name = "*.arc"), s: network STEPS a -read-> u THEN WITHIN 2min u -sendto-> s;',
        "EX": f'FIND IN {hosts} ENTITIES s: network (srcip = "{OUTSIDE}"), u: process ({own}), a: file STEPS s -recvfrom-> u THEN WITHIN 5min u -write-> a;',
        "MW": f'FIND IN {hosts} ENTITIES a: file (name = "sample.bin"), u: process ({own}), v: process STEPS a -read-> u THEN WITHIN 5min u -clone-> v;',
        "RT": f'FIND IN {hosts} ENTITIES s: network, b: process (name = "browser", {own}), f: file, l: process STEPS s -recvfrom-> b THEN WITHIN 5min b -write-> f THEN WITHIN 5min f -read-> l;',
        "EN": f'FIND IN {hosts} ENTITIES d: file (name = "*.doc"), e: process ({own}), h: process STEPS d -read-> e THEN WITHIN 5min e -clone-> h;',
    }[family(case)]
