"""The experiment workloads on the given tables, each with its SQL counterpart where there is one."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracelake import plans
from tracelake.graph import TraceGraph
from tracelake.lang import parse
from tracelake.lang.analyze import sql_of
from tracelake.lang.tree import Compare, Not
from tracelake.model import oracle, views
from tracelake.model.store import TraceStore, ingested, quality
from tracelake.search import search
from tracelake.search.run import joined_sql, motif_join, run_monolithic
from tracelake.session import condition
from tracelake.track import EdgeFilter, Limits, NodeFilter, Seed, track_back, track_forward, track_many
from tracelake.track.baselines import run_track_sql, track_paths, track_script

QUERIES: dict = {}
ORACLE_SQL: dict = {}


def register(name: str, sql: str | None = None):
    def wrap(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return wrap


def _events(spark, sf_dir) -> TraceStore:
    """The given events as a store that is ingested once and opened by every query."""
    return ingested(spark, "events", sf_dir, lambda: views.events(spark, sf_dir))


def _edges_only(df: DataFrame) -> TraceStore:
    """A store around bare edges, with entities that only have an id and a kind."""
    ends = df.select(F.explode(F.array("src_id", "dst_id")).alias("entity_id")).distinct()
    kind = F.when(F.col("entity_id").startswith("p:"), "process").when(F.col("entity_id").startswith("f:"), "file").otherwise("network")
    return TraceStore(ends.withColumn("kind", kind).withColumn("name", F.col("entity_id")), df)


def poi(scale: SparkSession | None, sf_dir: str, share: float) -> str:
    """Condition for the point of interest at a share of the events by id; the same in both engines."""
    return f"event_id = (SELECT CAST(floor(max(event_id) * {share}) AS BIGINT) FROM events)"


def _poi_id(spark: SparkSession, sf_dir: str, share: float) -> int:
    return spark.read.parquet(f"{sf_dir}/events.parquet").agg(F.floor(F.max("event_id") * share)).first()[0]


def _seed(spark, sf_dir, share: float, case: int = 0) -> Seed:
    return Seed.events(F.col("event_id") == _poi_id(spark, sf_dir, share), case)


MIDDLE, LAST, EARLY = 0.5, 1.0, 0.1
_IDS = "SELECT DISTINCT event_id FROM r"


def _trace_sql(share: float, direction: str = "back", usable: str | None = None, hops: int | None = None, body: str = _IDS, *more: str) -> str:
    extra = [oracle.ENTITIES, *more] + ([f"use_ AS ({usable})"] if usable else [])
    return oracle.with_events(body, *extra, oracle.closure(poi(None, "", share), direction, usable="use_" if usable else "ev", hops=hops), recursive=True)


def _ids(graph: TraceGraph) -> DataFrame:
    return graph.events.select("event_id").distinct()


# ---- model and ingest -------------------------------------------------------


@register("model_entities", oracle.with_events("SELECT entity_id, kind, host, name, path, cmdline, pid, src_ip, dst_ip, src_port, dst_port FROM ent", oracle.ENTITIES))
def model_entities(spark, sf_dir):
    return _events(spark, sf_dir).entities.select("entity_id", "kind", "host", "name", "path", "cmdline", "pid", "src_ip", "dst_ip", "src_port", "dst_port")


@register("model_events_oriented", oracle.with_events("SELECT event_id, host, category, op, src_id, dst_id, start_us, end_us, amount FROM ev"))
def model_events_oriented(spark, sf_dir):
    return _events(spark, sf_dir).events.select("event_id", "host", "category", "op", "src_id", "dst_id", "start_us", "end_us", "amount")


@register("model_six_counts", oracle.with_events("SELECT 'entity_' || kind AS part, count(*) AS n FROM ent GROUP BY 1 UNION ALL SELECT 'event_' || category, count(*) FROM ev GROUP BY 1", oracle.ENTITIES))
def model_six_counts(spark, sf_dir):
    s = _events(spark, sf_dir)
    parts = s.entities.groupBy(F.concat(F.lit("entity_"), "kind").alias("part")).agg(F.count(F.lit(1)).alias("n"))
    return parts.unionByName(s.events.groupBy(F.concat(F.lit("event_"), "category").alias("part")).agg(F.count(F.lit(1)).alias("n")))


@register("model_supply_edges", f"WITH {oracle.SUPPLY} SELECT op, count(*) AS n, count(DISTINCT src_id) AS sources, count(DISTINCT dst_id) AS sinks, min(start_us) AS first_us, max(end_us) AS last_us, CAST(sum(amount) AS BIGINT) AS amount FROM ev GROUP BY op")
def model_supply_edges(spark, sf_dir):
    e = views.supply(spark, sf_dir)
    return e.groupBy("op").agg(
        F.count(F.lit(1)).alias("n"), F.count_distinct("src_id").alias("sources"), F.count_distinct("dst_id").alias("sinks"),
        F.min("start_us").alias("first_us"), F.max("end_us").alias("last_us"), F.sum("amount").alias("amount"),
    )


@register("model_daily_summary", oracle.with_events("SELECT src_id, dst_id, op, start_us // 86400000000 AS day_no, count(*) AS n, min(start_us) AS first_us, max(end_us) AS last_us, CAST(sum(amount) AS BIGINT) AS amount FROM ev GROUP BY ALL"))
def model_daily_summary(spark, sf_dir):
    return _events(spark, sf_dir).daily_summary().withColumn("day_no", F.unix_date("day").cast("bigint")).drop("day")


@register("model_quality", oracle.with_events("SELECT 'orphan_ends' AS \"check\", (SELECT count(*) FROM (SELECT src_id AS e FROM ev UNION ALL SELECT dst_id FROM ev) WHERE e NOT IN (SELECT entity_id FROM ent)) AS n UNION ALL SELECT 'end_before_start', (SELECT count(*) FROM ev WHERE end_us < start_us) UNION ALL SELECT 'unknown_op', 0 UNION ALL SELECT 'repeated_ids', (SELECT count(*) FROM (SELECT event_id FROM ev GROUP BY 1 HAVING count(*) > 1))", oracle.ENTITIES))
def model_quality(spark, sf_dir):
    return quality(_events(spark, sf_dir))


@register("ingest_web_entities", "SELECT page_id, split_part(url, '://', 1) AS scheme, split_part(split_part(url, '://', 2), '/', 1) AS dst_host, '/' || regexp_extract(url, '^[a-z]+://[^/]+/([^?#]*)', 1) AS path, nullif(regexp_extract(url, '[?&]page=([^&#]*)', 1), '') AS page, split_part(regexp_extract(url, '^[a-z]+://[^/]+/([^?#]*)', 1), '/', 1) AS language FROM pages")
def ingest_web_entities(spark, sf_dir):
    return views.web(spark, sf_dir)


@register("ingest_variant_props", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, json_extract(props, '$.missing') IS NULL AS no_more FROM events")
def ingest_variant_props(spark, sf_dir):
    e = views.table(spark, sf_dir, "events").withColumn("v", F.try_parse_json("props"))
    return e.select("event_id", F.try_variant_get("v", "$.k", "bigint").alias("k"), F.try_variant_get("v", "$.missing", "string").isNull().alias("no_more"))


# ---- search -----------------------------------------------------------------

FINDS = {
    "search_single": 'FIND IN STORE("host1","host2","host3") ENTITIES f: file, p: process (exename = "furniture") STEPS f -read-> p;',
    "search_exfil_1h": 'FIND IN STORE("host1","host2","host3") ENTITIES f: file, p: process, s: network STEPS f -read-> p THEN WITHIN 1h p -sendto-> s;',
    "search_exfil_symmetric": 'FIND IN STORE("host1","host2","host3") ENTITIES f: file, p: process, s: network STEPS f -read-> p ALSO WITHIN 1h p -sendto-> s;',
    "search_three_step": 'FIND IN STORE("host1","host2","host3") ENTITIES s: network, p: process, f: file, q: process STEPS s -recvfrom-> p THEN WITHIN 24h p -write-> f THEN WITHIN 24h f -read-> q;',
    "search_or": 'FIND IN STORE("host1","host2","host3") ENTITIES p: process (pid = 17), f: file, s: network STEPS p -write-> f OR p -sendto-> s;',
    "search_unbounded": 'FIND IN STORE("host1","host2","host3") ENTITIES f: file, p: process (pid = 42), q: process STEPS f -read-> p ALSO p -clone-> q;',
    "search_wildcard": 'FIND IN STORE("host1","host2","host3") ENTITIES p: process, f: file (name = "*.promo") STEPS p -write-> f;',
    "search_not": 'FIND IN STORE("host1","host2","host3") ENTITIES p: process, f: file (NOT path ~ "/brand1") STEPS p -write-> f;',
    "search_numeric": 'FIND IN STORE("host1","host2","host3") ENTITIES s: network (dstport = 443, srcport >= 40090), p: process (pid < 60) STEPS s -recvfrom-> p;',
    "search_null_semantics": 'FIND IN STORE("host1","host2","host3") ENTITIES x (NOT path ~ "/brand", pid != 3), p: process (pid <= 30) STEPS x -> p;',
    "search_poi_file_proc_file": 'FIND IN STORE("host1","host2","host3") ENTITIES f: file (name ~ "widget"), p: process, g: file STEPS f -read-> p THEN WITHIN 6h p -write-> g;',
}


def finding(name: str):
    return parse(FINDS[name])[0]


def _find(name: str, spark, sf_dir, **options) -> DataFrame:
    return search(finding(name), _events(spark, sf_dir), **options).bindings


for _name in FINDS:
    QUERIES[_name] = partial(_find, _name)
    ORACLE_SQL[_name] = oracle.with_stored(joined_sql(finding(_name)))

for _key, _options in {
    "search_lazy": {"eager": False}, "search_text_order": {"mode": "text"}, "search_stats_order": {"mode": "stats"}, "search_too_broad": {"too_broad": 10},
}.items():
    QUERIES[_key] = partial(_find, "search_exfil_1h", **_options)
    ORACLE_SQL[_key] = ORACLE_SQL["search_exfil_1h"]


@register("search_single_statement", ORACLE_SQL["search_exfil_1h"])
def search_single_statement(spark, sf_dir):
    return run_monolithic(finding("search_exfil_1h"), _events(spark, sf_dir))


@register("search_motif", ORACLE_SQL["search_exfil_1h"])
def search_motif(spark, sf_dir):
    return motif_join(finding("search_exfil_1h"), _events(spark, sf_dir))


@register("search_scheduled_vs_single", "SELECT 'only_scheduled' AS side, CAST(0 AS BIGINT) AS n UNION ALL SELECT 'only_single', 0")
def search_scheduled_vs_single(spark, sf_dir):
    s = _events(spark, sf_dir)
    a = search(finding("search_exfil_1h"), s).bindings.select("e0", "e1")
    b = run_monolithic(finding("search_exfil_1h"), s).select("e0", "e1")
    count = lambda df, side: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(side).alias("side"), "n")
    return count(a.exceptAll(b), "only_scheduled").unionByName(count(b.exceptAll(a), "only_single"))


_INSIDE = 'FIND IN STORE("host1","host2","host3") ENTITIES i: network (dstip ~ "203.0.113."), w: process STEPS i -recvfrom-> w;'


@register("search_in_variable", _trace_sql(MIDDLE, body="SELECT DISTINCT ev.event_id FROM ev JOIN r USING (event_id) JOIN ent i ON i.entity_id = src_id WHERE op = 'recvfrom' AND coalesce(i.dst_ip LIKE '%203.0.113.%', false)"))
def search_in_variable(spark, sf_dir):
    g = track_back(_seed(spark, sf_dir, MIDDLE), _events(spark, sf_dir)).resident()
    return _ids(search(parse(_INSIDE)[0], g).graph)


@register("search_first_matches", ORACLE_SQL["search_single"] + " ORDER BY e0 LIMIT 5")
def search_first_matches(spark, sf_dir):
    return _find("search_single", spark, sf_dir, limit=5)


@register("search_supply_pattern", f"WITH {oracle.SUPPLY} SELECT a.event_id AS e0, b.event_id AS e1, c.event_id AS e2 FROM ev a JOIN ev b ON a.dst_id = b.src_id AND b.start_us - a.start_us BETWEEN 0 AND 2591999999999 JOIN ev c ON b.dst_id = c.src_id AND c.start_us - b.start_us BETWEEN 0 AND 2591999999999 WHERE a.op = 'write' AND b.op = 'read' AND c.op = 'sendto'")
def search_supply_pattern(spark, sf_dir):
    text = 'FIND IN STORE("x") ENTITIES v: process, p: file, o: process, n: network STEPS v -write-> p THEN WITHIN 30d p -read-> o THEN WITHIN 30d o -sendto-> n;'
    return search(parse(text)[0], _edges_only(views.supply(spark, sf_dir)), eager=False).bindings.select("e0", "e1", "e2")


# ---- tracking ---------------------------------------------------------------


def _back(spark, sf_dir, share=MIDDLE, **options) -> DataFrame:
    return _ids(track_back(_seed(spark, sf_dir, share), _events(spark, sf_dir), **options))


def _back_files(spark, sf_dir, **options) -> DataFrame:
    no_net = NodeFilter(drop=condition(Compare("type", "=", "network"), "entity"))
    return track_back(_seed(spark, sf_dir, MIDDLE), _events(spark, sf_dir), nodes=no_net, limits=Limits(max_hops=4), **options).events.select("event_id", "level")


QUERIES["track_back_all"] = _back
ORACLE_SQL["track_back_all"] = _trace_sql(MIDDLE)
for _engine in ("bound", "level", "local"):
    QUERIES[f"track_{_engine}"] = partial(_back_files, engine=_engine)
    ORACLE_SQL[f"track_{_engine}"] = _trace_sql(MIDDLE, usable="SELECT * FROM ev WHERE category <> 'network'", hops=4, body="SELECT event_id, CAST(min(hop) AS INTEGER) AS level FROM r GROUP BY 1")
QUERIES["track_queue"] = partial(_back, share=EARLY, engine="queue")
ORACLE_SQL["track_queue"] = _trace_sql(EARLY)


@register("track_forward_all", _trace_sql(MIDDLE, "forward"))
def track_forward_all(spark, sf_dir):
    return _ids(track_forward(_seed(spark, sf_dir, MIDDLE), _events(spark, sf_dir)))


_NO_NET = "SELECT * FROM ev WHERE category <> 'network'"


@register("track_back_exclude", _trace_sql(MIDDLE, usable=_NO_NET))
def track_back_exclude(spark, sf_dir):
    return _back(spark, sf_dir, nodes=NodeFilter(drop=condition(Compare("type", "=", "network"), "entity")))


_NOT_BRAND1 = Not(Compare("path", "~", "/brand1"))


@register("track_back_include_not", _trace_sql(MIDDLE, usable=f"SELECT * FROM ev WHERE src_id NOT IN (SELECT entity_id FROM ent WHERE NOT {sql_of(_NOT_BRAND1, 'entity', 'ent')}) AND dst_id NOT IN (SELECT entity_id FROM ent WHERE NOT {sql_of(_NOT_BRAND1, 'entity', 'ent')})"))
def track_back_include_not(spark, sf_dir):
    return _back(spark, sf_dir, nodes=NodeFilter(keep=condition(_NOT_BRAND1, "entity")))


_EDGES_KEPT = "SELECT * FROM ev WHERE op IN ('read', 'write', 'clone')"


@register("track_edges_filter", _trace_sql(MIDDLE, usable=_EDGES_KEPT))
def track_edges_filter(spark, sf_dir):
    return _back(spark, sf_dir, edges=EdgeFilter(keep=condition(Compare("optype", "in", ("read", "write", "clone")), "event")))


@register("track_after_filter", _trace_sql(MIDDLE, body=f"SELECT DISTINCT event_id FROM r WHERE event_id IN (SELECT event_id FROM ev WHERE category <> 'network') UNION SELECT event_id FROM ev WHERE {poi(None, '', MIDDLE)}"))
def track_after_filter(spark, sf_dir):
    return _back(spark, sf_dir, nodes=NodeFilter(drop=condition(Compare("type", "=", "network"), "entity")), filter_mode="after")


@register("track_hops_3", _trace_sql(LAST, hops=3, body="SELECT event_id, CAST(min(hop) AS INTEGER) AS level FROM r GROUP BY 1"))
def track_hops_3(spark, sf_dir):
    g = track_back(_seed(spark, sf_dir, LAST), _events(spark, sf_dir), limits=Limits(max_hops=3))
    return g.events.select("event_id", "level")


@register("track_span_7d", _trace_sql(LAST, usable=f"SELECT * FROM ev WHERE start_us >= (SELECT start_us - 604800000000 FROM ev WHERE {poi(None, '', LAST)})"))
def track_span_7d(spark, sf_dir):
    return _back(spark, sf_dir, share=LAST, limits=Limits(max_span_us=7 * 86_400_000_000))


def _entity_closure(where: str, usable: str = "ev") -> str:
    return f"r(event_id, n, b) AS (SELECT CAST(NULL AS BIGINT), entity_id, 4611686018427387904 FROM ent WHERE {where} UNION SELECT x.event_id, x.src_id, x.end_us FROM r JOIN {usable} x ON x.dst_id = r.n AND x.start_us < r.b)"


@register("track_cmdline_seed", oracle.with_events("SELECT DISTINCT event_id FROM r WHERE event_id IS NOT NULL", oracle.ENTITIES, _entity_closure("coalesce(cmdline LIKE '%--acct 7', false)", "(SELECT * FROM ev WHERE category <> 'network')"), recursive=True))
def track_cmdline_seed(spark, sf_dir):
    seed = Seed.entities(F.coalesce(F.col("cmdline").like("%--acct 7"), F.lit(False)))
    return _ids(track_back(seed, _events(spark, sf_dir), nodes=NodeFilter(drop=condition(Compare("type", "=", "network"), "entity"))))


@register("track_back_name_seed", oracle.with_events("SELECT DISTINCT event_id FROM r WHERE event_id IS NOT NULL", oracle.ENTITIES, _entity_closure("name LIKE '%red_widget%' AND host = 'host2'", "(SELECT * FROM ev WHERE host = 'host2' AND category <> 'network')"), recursive=True))
def track_back_name_seed(spark, sf_dir):
    return _ids(track_back(Seed.text("red_widget"), _events(spark, sf_dir).host("host2"), nodes=NodeFilter(drop=condition(Compare("type", "=", "network"), "entity"))))


_TENTHS = [k / 10 for k in range(1, 11)]


@register("track_multi_poi", oracle.with_events(
    "SELECT DISTINCT case_id, event_id FROM r", "use_ AS (SELECT * FROM ev WHERE category <> 'network')",
    "poi_ AS (SELECT k AS case_id, ev.* FROM range(1, 11) t(k) JOIN ev ON event_id = (SELECT CAST(floor(max(event_id) * k / 10.0) AS BIGINT) FROM events))",
    "r(case_id, event_id, n, b) AS (SELECT case_id, event_id, src_id, end_us FROM poi_ UNION SELECT r.case_id, x.event_id, x.src_id, x.end_us FROM r JOIN use_ x ON x.dst_id = r.n AND x.start_us < r.b)", recursive=True,
))
def track_multi_poi(spark, sf_dir):
    seeds = [_seed(spark, sf_dir, share, k + 1) for k, share in enumerate(_TENTHS)]
    return track_many(seeds, _events(spark, sf_dir), nodes=NodeFilter(drop=condition(Compare("type", "=", "network"), "entity"))).select("case_id", "event_id")


@register("track_cross_host", _trace_sql(MIDDLE, body="SELECT host, count(DISTINCT event_id) AS n FROM r JOIN ev USING (event_id) GROUP BY host"))
def track_cross_host(spark, sf_dir):
    return track_back(_seed(spark, sf_dir, MIDDLE), _events(spark, sf_dir)).events.groupBy("host").agg(F.count(F.lit(1)).alias("n"))


@register("track_recursive_sql", _trace_sql(MIDDLE, hops=3))
def track_recursive_sql(spark, sf_dir):
    return run_track_sql(_events(spark, sf_dir), _poi_id(spark, sf_dir, MIDDLE), 3)


@register("track_script", _trace_sql(EARLY, hops=4, body="SELECT event_id, CAST(min(hop) AS INTEGER) AS level FROM r GROUP BY 1"))
def track_script_query(spark, sf_dir):
    return track_script(_events(spark, sf_dir), _poi_id(spark, sf_dir, EARLY), 4)


@register("track_paths_3", oracle.with_events(
    "SELECT len(path) AS steps, count(*) AS paths, count(DISTINCT path[len(path)]) AS events FROM r GROUP BY 1",
    f"r(path, n, b) AS (SELECT [event_id], src_id, end_us FROM ev WHERE {poi(None, '', MIDDLE)} UNION ALL SELECT list_append(r.path, x.event_id), x.src_id, x.end_us FROM r JOIN ev x ON x.dst_id = r.n AND x.start_us < r.b AND NOT list_contains(r.path, x.event_id) WHERE len(r.path) <= 3)", recursive=True,
))
def track_paths_3(spark, sf_dir):
    paths = track_paths(_events(spark, sf_dir), _poi_id(spark, sf_dir, MIDDLE), 3)
    return paths.groupBy(F.size("path").cast("bigint").alias("steps")).agg(F.count(F.lit(1)).alias("paths"), F.count_distinct("last").alias("events"))


_HOT = "(SELECT dst_id FROM ev WHERE op = 'sendto' GROUP BY 1 ORDER BY count(*) DESC, dst_id LIMIT 1)"


@register("track_supply", f"WITH RECURSIVE {oracle.SUPPLY}, r(event_id, n, b, hop) AS (SELECT CAST(NULL AS BIGINT), dst_id, 4611686018427387904, 0 FROM {_HOT} UNION SELECT x.event_id, x.src_id, x.end_us, r.hop + 1 FROM r JOIN ev x ON x.dst_id = r.n AND x.start_us < r.b WHERE r.hop < 3) SELECT DISTINCT event_id FROM r WHERE event_id IS NOT NULL")
def track_supply(spark, sf_dir):
    edges = views.supply(spark, sf_dir)
    hot = edges.where("op = 'sendto'").groupBy("dst_id").count().orderBy(F.desc("count"), "dst_id").first()["dst_id"]
    return _ids(track_back(Seed.entities(F.col("entity_id") == hot), _edges_only(edges), limits=Limits(max_hops=3)))


@register("track_chain", f"WITH RECURSIVE {oracle.chain(20)}, r(event_id, n, b) AS (SELECT event_id, src_id, end_us FROM ev WHERE event_id = (SELECT max(conv_id * 1000 + turn * 10 + 1) FROM t_turns WHERE conv_id = 20) UNION SELECT x.event_id, x.src_id, x.end_us FROM r JOIN ev x ON x.dst_id = r.n AND x.start_us <= r.b) SELECT DISTINCT event_id FROM r".replace("x.start_us <= r.b", "x.start_us < r.b"))
def track_chain(spark, sf_dir):
    edges = views.chain(spark, sf_dir, 20)
    last = edges.where("op = 'write' AND event_id BETWEEN 20000 AND 20999").agg(F.max("event_id")).first()[0]
    return _ids(track_back(Seed.events(F.col("event_id") == last), _edges_only(edges)))


@register("track_entry_points", _trace_sql(MIDDLE, body="SELECT DISTINCT src_id AS node FROM ev JOIN r USING (event_id) WHERE src_id NOT IN (SELECT dst_id FROM ev JOIN r USING (event_id))"))
def track_entry_points(spark, sf_dir):
    return track_back(_seed(spark, sf_dir, MIDDLE), _events(spark, sf_dir)).entry_points()


@register("track_sequence", _trace_sql(EARLY, body="SELECT event_id, row_number() OVER (ORDER BY start_us, event_id) AS nth FROM (SELECT DISTINCT ev.event_id, start_us FROM ev JOIN r USING (event_id))"))
def track_sequence(spark, sf_dir):
    g = track_back(_seed(spark, sf_dir, EARLY), _events(spark, sf_dir))
    return g.sequence().select("event_id", F.col("nth").cast("bigint").alias("nth"))


@register("track_between", oracle.with_events(
    "SELECT DISTINCT event_id FROM f",
    oracle.closure(poi(None, "", LAST), usable="(SELECT * FROM ev WHERE category <> 'network')"), "sub AS (SELECT * FROM ev WHERE event_id IN (SELECT event_id FROM r) AND category <> 'network')",
    oracle.closure("event_id = (SELECT min(event_id) FROM sub)", "forward", "sub", "sub", name="f"), recursive=True,
))
def track_between(spark, sf_dir):
    s = _events(spark, sf_dir)
    no_net = NodeFilter(drop=condition(Compare("type", "=", "network"), "entity"))
    back = track_back(_seed(spark, sf_dir, LAST), s, nodes=no_net).resident()
    first = back.events.where("category <> 'network'").agg(F.min("event_id")).first()[0]
    return _ids(track_forward(Seed.events(F.col("event_id") == first), back, nodes=no_net))


# ---- graphs -----------------------------------------------------------------

_SETS = [
    "use_ AS (SELECT * FROM ev WHERE category <> 'network')", oracle.closure(poi(None, "", LAST), usable="use_", name="a"), oracle.closure(poi(None, "", 0.9), usable="use_", name="b"),
    oracle.closure(poi(None, "", EARLY), "forward", usable="use_", name="c"),
]
_SIDES = [f"SELECT event_id FROM {x}" for x in "abc"]


def _three(spark, sf_dir):
    s = _events(spark, sf_dir)
    no_net = NodeFilter(drop=condition(Compare("type", "=", "network"), "entity"))
    a = track_back(_seed(spark, sf_dir, LAST), s, nodes=no_net)
    b = track_back(_seed(spark, sf_dir, 0.9), s, nodes=no_net)
    return a, b, track_forward(_seed(spark, sf_dir, EARLY), s, nodes=no_net)


def _graph(op: str, spark, sf_dir):
    a, b, c = _three(spark, sf_dir)
    made = {"union": lambda: a.union(b), "intersect": lambda: a.intersect(b), "minus": lambda: a.minus(b), "expr": lambda: a.minus(b).union(a.intersect(c))}[op]()
    return _ids(made)


for _op, _sql in {
    "union": f"{_SIDES[0]} UNION {_SIDES[1]}", "intersect": f"{_SIDES[0]} INTERSECT {_SIDES[1]}", "minus": f"{_SIDES[0]} EXCEPT {_SIDES[1]}",
    "expr": f"({_SIDES[0]} EXCEPT {_SIDES[1]}) UNION ({_SIDES[0]} INTERSECT {_SIDES[2]})",
}.items():
    QUERIES[f"graph_{_op}"] = partial(_graph, _op)
    ORACLE_SQL[f"graph_{_op}"] = oracle.with_events(_sql, *_SETS, recursive=True)


@register("graph_refine", _trace_sql(MIDDLE, body="SELECT DISTINCT ev.event_id FROM ev JOIN r USING (event_id) JOIN ent s ON s.entity_id = src_id JOIN ent d ON d.entity_id = dst_id WHERE op IN ('read', 'write') AND NOT coalesce(s.path LIKE '%/brand1%', false) AND NOT coalesce(d.path LIKE '%/brand1%', false)"))
def graph_refine(spark, sf_dir):
    g = track_back(_seed(spark, sf_dir, MIDDLE), _events(spark, sf_dir)).resident()
    return _ids(g.refine(condition(_NOT_BRAND1, "entity"), condition(Compare("optype", "in", ("read", "write")), "event")))


@register("graph_size", _trace_sql(MIDDLE, body="SELECT (SELECT count(DISTINCT n) FROM (SELECT src_id AS n FROM ev JOIN r USING (event_id) UNION SELECT dst_id FROM ev JOIN r USING (event_id))) AS nodes, (SELECT count(DISTINCT event_id) FROM r) AS edges"))
def graph_size(spark, sf_dir):
    return track_back(_seed(spark, sf_dir, MIDDLE), _events(spark, sf_dir)).size()


@register("graph_degrees", _trace_sql(MIDDLE, body="SELECT node, CAST(sum(i) AS BIGINT) AS n_in, CAST(sum(o) AS BIGINT) AS n_out FROM (SELECT src_id AS node, 0 AS i, 1 AS o FROM ev WHERE event_id IN (SELECT event_id FROM r) UNION ALL SELECT dst_id, 1, 0 FROM ev WHERE event_id IN (SELECT event_id FROM r)) GROUP BY 1"))
def graph_degrees(spark, sf_dir):
    return track_back(_seed(spark, sf_dir, MIDDLE), _events(spark, sf_dir)).degrees()


@register("graph_copies", "SELECT f AS src_doc, doc_id AS dst_doc FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS f FROM documents) WHERE doc_id > f")
def graph_copies(spark, sf_dir):
    return views.leak(spark, sf_dir)
