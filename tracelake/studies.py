"""The research questions on planted cases: effectiveness, memory, cost, words, study table."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracelake import cases, measure, plans
from tracelake import functions as X
from tracelake.compare import impact_sweep, impact_traces, plain_traces, rareness_traces
from tracelake.lang import parse
from tracelake.lang.analyze import sql_of
from tracelake.lang.tree import Compare
from tracelake.model import oracle, views
from tracelake.model.store import ingested
from tracelake.search.run import graph_text, joined_sql, logsearch_text, monolithic_sql
from tracelake.session import Session
from tracelake.track import EdgeFilter, NodeFilter, Seed, track_back, track_many
from tracelake.track.run import admitted
from tracelake.track.baselines import track_sql
from tracelake.workloads import _seed, register

ALL = list(range(1, 31))
_POIS = [(c, cases.event_id(c, cases.poi(c))) for c in ALL]


def _store(spark, sf_dir, which=range(1, 31)):
    return ingested(spark, f"cases {list(which)}", sf_dir, lambda: cases.plant(spark, sf_dir, which))


def _truth(store) -> DataFrame:
    return store.events.where("is_truth").select(F.col("plant_case").alias("case_id"), "event_id")


def _seeds() -> list[Seed]:
    return [Seed.events(F.col("event_id") == e, c) for c, e in _POIS]


def constrained(store) -> DataFrame:
    """What the programs of all cases bind to ``story``: case_id, event_id. Programs of one shape run together."""
    return Session(store).run_batch({c: cases.program(c) for c in ALL})["story"]


def _results(store, entries: int = 3) -> DataFrame:
    graphs = plain_traces(_seeds(), store)
    graphs = plans.pin(graphs.select("case_id", "event_id", "src_id", "dst_id", "start_us", "end_us", "amount"), "plain")
    parts = {
        "constrained": constrained(store), "plain": graphs.select("case_id", "event_id"), "rareness": rareness_traces(_POIS, store, limit=500),
        "impact": impact_traces(_POIS, store, entries, graphs=graphs),
    }
    out = None
    for name, df in parts.items():
        own = df.select(F.lit(name).alias("method"), "case_id", "event_id")
        out = own if out is None else out.unionByName(own)
    return plans.pin(out, "results")


_CASE_TRACE = """
    t_poi(case_id, event_id, way) AS (VALUES {pois}),
    use_ AS ({usable}),
    r(case_id, event_id, way, n, b) AS (
        SELECT p.case_id, p.event_id, way, CASE way WHEN 'back' THEN src_id ELSE dst_id END, CASE way WHEN 'back' THEN end_us ELSE -start_us END FROM t_poi p JOIN pev USING (event_id)
        UNION
        SELECT r.case_id, x.event_id, r.way, CASE r.way WHEN 'back' THEN x.src_id ELSE x.dst_id END, CASE r.way WHEN 'back' THEN x.end_us ELSE -x.start_us END
        FROM r JOIN use_ x ON (r.way = 'back' AND x.dst_id = r.n AND x.start_us < r.b) OR (r.way = 'forward' AND x.src_id = r.n AND -x.end_us < r.b)),
    res AS (SELECT DISTINCT case_id, event_id FROM r)"""
_NO_BRAND_SQL = "SELECT * FROM pev WHERE NOT coalesce(src_id LIKE 'f:%/brand%', false) AND NOT coalesce(dst_id LIKE 'f:%/brand%', false)"
_WAYS = ", ".join(f"({c}, {e}, '{w}')" for c, e in _POIS for w in ("back", "forward") if (w == "back") != (cases.family(c) == "MW") or cases.family(c) == "EN")
_MEASURES = """
    SELECT CAST(t.case_id AS BIGINT) AS case_id, coalesce(edges, 0) AS edges, coalesce(tp, 0) AS tp, round((relevant - coalesce(tp, 0)) / relevant, 6) AS miss_ratio,
           round(coalesce((edges - tp) / edges, 0), 6) AS noise_ratio, round(coalesce(tp, 0) / (coalesce(tp, 0) + (coalesce(edges, 0) + relevant - 2 * coalesce(tp, 0)) / 2), 6) AS f1
    FROM (SELECT case_id, count(*) AS relevant FROM planted WHERE is_truth GROUP BY 1) t
    LEFT JOIN (SELECT res.case_id, count(*) AS edges, CAST(sum(CASE WHEN is_truth AND plant_case = res.case_id THEN 1 ELSE 0 END) AS BIGINT) AS tp FROM res JOIN pev USING (event_id) GROUP BY 1) g USING (case_id)"""


@register("rq1_constrained", oracle.with_events(_MEASURES, cases.planted_sql(), _CASE_TRACE.format(pois=_WAYS, usable=_NO_BRAND_SQL), recursive=True))
def rq1_constrained(spark, sf_dir):
    store = _store(spark, sf_dir)
    out = constrained(store).withColumn("method", F.lit("constrained"))
    return measure.accuracy(out, _truth(store)).select("case_id", "edges", "tp", "miss_ratio", "noise_ratio", "f1")


@register("cases_track", oracle.with_events("SELECT CAST(case_id AS BIGINT) AS case_id, event_id FROM res", cases.planted_sql(), _CASE_TRACE.format(pois=_WAYS, usable=_NO_BRAND_SQL), recursive=True))
def cases_track(spark, sf_dir):
    """Events that the program of each case finds, run from its text."""
    return constrained(_store(spark, sf_dir))


@register("rq1_accuracy")
def rq1_accuracy(spark, sf_dir):
    """Accuracy and reduction of the four methods, by case."""
    store = _store(spark, sf_dir)
    return measure.accuracy(_results(store), _truth(store), store.events.count())


@register("rq1_reduction")
def rq1_reduction(spark, sf_dir):
    """Means of the measures by method and family, and over all cases."""
    kind = None
    for name, own in cases.FAMILIES.items():
        kind = F.when(F.col("case_id").isin(*own), name) if kind is None else kind.when(F.col("case_id").isin(*own), name)
    return measure.summarise(rq1_accuracy(spark, sf_dir), kind, "reduction", "f1", "miss_ratio", "noise_ratio", "edges")


@register("rq1_entry_sweep")
def rq1_entry_sweep(spark, sf_dir):
    """Impact propagation with more and more entries."""
    store = _store(spark, sf_dir)
    graphs = plans.pin(plain_traces(_seeds(), store).select("case_id", "event_id", "src_id", "dst_id", "start_us", "end_us", "amount"), "plain")
    counts = [1, 2, 3, 5, 10]
    out = impact_sweep(_POIS, store, counts, graphs=graphs).withColumn("method", F.format_string("entries_%02d", "entries"))
    methods = spark.createDataFrame([(f"entries_{n:02d}",) for n in counts], "method string")
    per = measure.accuracy(out, F.broadcast(_truth(store)), methods=methods)  # the truth is some 20 events a case
    return per.groupBy("method").agg(*[F.round(F.avg(m), 6).alias(m) for m in ("f1", "miss_ratio", "noise_ratio", "edges")])


@register("rq1_rareness_sweep")
def rq1_rareness_sweep(spark, sf_dir):
    """Prioritised tracing with growing limits; without one it is plain tracing."""
    store = _store(spark, sf_dir)
    out = None
    for limit in (10, 50, 200, 1000, None):
        own = rareness_traces(_POIS, store, limit).withColumn("method", F.lit(f"limit_{limit or 'none'}"))
        out = own if out is None else out.unionByName(own)
    per = measure.accuracy(plans.pin(out, "sweep"), _truth(store))
    return per.groupBy("method").agg(*[F.round(F.avg(m), 6).alias(m) for m in ("f1", "miss_ratio", "noise_ratio", "edges")])


@register("rq1_labels", """
    SELECT lang, count(*) AS n, CAST(sum(toxic) AS BIGINT) AS relevant, round(sum(toxic) / count(*), 6) AS share FROM documents JOIN labels USING (doc_id) GROUP BY lang""")
def rq1_labels(spark, sf_dir):
    """Partial truth: labelled documents as relevant files, by language."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "lang")
    return docs.join(spark.read.parquet(f"{sf_dir}/labels.parquet"), "doc_id").groupBy("lang").agg(
        F.count(F.lit(1)).alias("n"), F.sum("toxic").cast("bigint").alias("relevant"), F.round(F.sum("toxic") / F.count(F.lit(1)), 6).alias("share")
    )


STORY = """
    hits  := FIND IN STORE("host1") ENTITIES u: process (name = "upload", pid >= 2000, pid < 3000), a: file (name = "*.arc"), s: network STEPS a -read-> u THEN WITHIN 2min u -sendto-> s;
    back1 := TRACE BACKWARD FROM hits IN STORE("host1") DROP NODES (path ~ "/brand");
    back3 := TRACE BACKWARD FROM ENTITY (exename = "upload", pid >= 2000, pid < 3000) IN STORE("host1") KEEP NODES (NOT path ~ "/brand");
    entry := FIND IN back3 ENTITIES i: network (srcip = "198.51.100.7"), w: process STEPS i -recvfrom-> w;
    full  := COMBINE back1 UNION back3;
    story := TRACE FORWARD FROM entry IN full DROP NODES (name ~ "scan");
"""


@register("case_study", oracle.with_events("SELECT event_id FROM planted WHERE case_id = 2 AND is_truth AND event_id - 10000002000 IN (1, 2, 13, 17, 18, 19, 20)", cases.planted_sql([2])))
def case_study(spark, sf_dir):
    """Six statements on the planted leakage; the events of its last graph."""
    session = Session(_store(spark, sf_dir, [2]))
    session.run(STORY)
    return session.catalog["story"].events.select("event_id").distinct()


_CHAIN_SQL = f"""
    use_ AS MATERIALIZED ({_NO_BRAND_SQL}),
    t_poi(case_id, event_id) AS (VALUES {", ".join(map(str, _POIS))}),
    b(case_id, event_id, n, t) AS (
        SELECT case_id, event_id, src_id, end_us FROM t_poi JOIN pev USING (event_id)
        UNION SELECT b.case_id, x.event_id, x.src_id, x.end_us FROM b JOIN use_ x ON x.dst_id = b.n AND x.start_us < b.t),
    back AS (SELECT DISTINCT case_id, event_id FROM b),
    entry AS (SELECT case_id, event_id, dst_id, start_us FROM back JOIN pev USING (event_id) WHERE op = 'recvfrom' AND src_id LIKE 'n:tcp:{cases.OUTSIDE}:%'),
    f(case_id, event_id, n, t) AS (
        SELECT case_id, event_id, dst_id, start_us FROM entry
        UNION SELECT f.case_id, x.event_id, x.dst_id, x.start_us FROM f JOIN use_ x ON x.src_id = f.n AND x.end_us > f.t),
    ahead AS (SELECT DISTINCT case_id, event_id FROM f),
    steps AS (
        SELECT 'backward' AS step, case_id, event_id FROM back UNION ALL SELECT 'entry', case_id, event_id FROM entry UNION ALL SELECT 'forward', case_id, event_id FROM ahead
        UNION ALL SELECT 'intersection', case_id, event_id FROM back JOIN ahead USING (case_id, event_id))"""


def memory_chain(store, setting: str) -> DataFrame:
    """Backward trace of each case, search for entries inside it, forward trace from these, intersection: step, case_id, event_id.

    ``resident`` keeps each result in memory, ``stored`` writes it out; ``anew`` asks the store again for what a later step needs.
    """
    drop = NodeFilter(drop=F.expr(sql_of(Compare("path", "~", "/brand"), "entity", "")))
    keep = {"resident": lambda df: df.persist(StorageLevel.MEMORY_AND_DISK), "stored": lambda df: plans.pin(df, "chain"), "anew": lambda df: df}[setting]
    outside = store.entities.where(F.coalesce(F.col("src_ip") == cases.OUTSIDE, F.lit(False))).select(F.col("entity_id").alias("o_id"))

    def back():
        return track_many(_seeds(), store, "back", nodes=drop)

    def entries(rows):
        own = rows.where("op = 'recvfrom'").join(outside, F.col("src_id") == F.col("o_id"), "left_semi")
        return own.select("case_id", "event_id").distinct()

    first = keep(back())
    entry = keep(entries(first))
    found = [(r.case_id, r.event_id) for r in entry.collect()]  # a few for each case
    seeds = [Seed.events(F.col("event_id").isin([e for c, e in found if c == case]), case) for case in sorted({c for c, _ in found})]
    ahead = keep(track_many(seeds, store, "forward", nodes=drop)) if seeds else first.where(F.lit(False))
    again = first if setting != "anew" else back()
    pairs = lambda df: df.select("case_id", "event_id")
    parts = {"backward": pairs(first), "entry": entry, "forward": pairs(ahead), "intersection": pairs(again).intersect(pairs(ahead))}
    out = None
    for name, df in parts.items():
        own = df.distinct().select(F.lit(name).alias("step"), "case_id", "event_id")
        out = own if out is None else out.unionByName(own)
    return out


_SETTINGS = ("resident", "stored", "anew")


@register("rq2_memory", oracle.with_events(
    f"SELECT setting, step, CAST(case_id AS BIGINT) AS case_id, count(*) AS events FROM steps CROSS JOIN (VALUES {', '.join(f'({s!r})' for s in _SETTINGS)}) v(setting) GROUP BY 1, 2, 3",
    cases.planted_sql(), _CHAIN_SQL, recursive=True,
))
def rq2_memory(spark, sf_dir):
    """Events of each step of the four-step chain by case, with results kept in memory, stored, and asked for anew."""
    store = _store(spark, sf_dir)
    out = None
    for setting in _SETTINGS:
        own = memory_chain(store, setting).groupBy("step", "case_id").agg(F.count(F.lit(1)).alias("events")).select(F.lit(setting).alias("setting"), "step", "case_id", "events")
        out = own if out is None else out.unionByName(own)
    return out


@register("rq3_steps", oracle.with_events("SELECT hop AS level, count(*) AS events FROM (SELECT event_id, min(hop) AS hop FROM r GROUP BY 1) WHERE hop > 0 GROUP BY 1", oracle.ENTITIES, "use_ AS (SELECT * FROM ev WHERE category <> 'network')", oracle.closure("event_id = (SELECT CAST(floor(max(event_id) * 0.5) AS BIGINT) FROM events)", usable="use_", hops=40), recursive=True).replace("hop AS level", "CAST(hop AS INTEGER) AS level"))
def rq3_steps(spark, sf_dir):
    """Candidates per level of a stepwise trace."""
    from tracelake.model import views

    g = track_back(_seed(spark, sf_dir, 0.5), views.events(spark, sf_dir), nodes=NodeFilter(drop=F.col("kind") == "network"))
    return g.events.where("level > 0").groupBy("level").agg(F.count(F.lit(1)).alias("events"))


#: Rounds of the recursive statement whose cost is compared; without a limit it would not end on cycles.
COST_HOPS = 4
_COST_SQL = f"""
    use_ AS MATERIALIZED ({_NO_BRAND_SQL}),
    t_poi(case_id, event_id) AS (VALUES {", ".join(map(str, _POIS))}),
    w(case_id, event_id, n, b, hop) AS (
        SELECT case_id, event_id, src_id, end_us, 0 FROM t_poi JOIN pev USING (event_id)
        UNION ALL SELECT w.case_id, x.event_id, x.src_id, x.end_us, w.hop + 1 FROM w JOIN use_ x ON x.dst_id = w.n AND x.start_us < w.b WHERE w.hop < {COST_HOPS})"""


@register("rq3_cost", oracle.with_events(
    "SELECT CAST(case_id AS BIGINT) AS case_id, CAST(hop AS INTEGER) AS hop, count(*) AS paths, count(DISTINCT event_id) AS events, count(DISTINCT n) AS nodes FROM w GROUP BY 1, 2",
    cases.planted_sql(), _COST_SQL, recursive=True,
))
def rq3_cost(spark, sf_dir):
    """Per case and hop: rows that one recursive statement makes (paths), and events and nodes that a stepwise trace asks for."""
    store = _store(spark, sf_dir)
    drop = NodeFilter(drop=F.expr(sql_of(Compare("path", "~", "/brand"), "entity", "")))
    usable = plans.pin(admitted(store, drop, EdgeFilter()).select("event_id", "src_id", "dst_id", "start_us", "end_us"), "usable")
    given = store.events.where(F.col("event_id").isin([e for _, e in _POIS])).select(F.col("event_id").alias("g_id"), "src_id", "end_us")
    pois = spark.createDataFrame(_POIS, "case_id bigint, event_id bigint")
    # Equal paths of a case are one row with their number, so the count of paths needs no paths.
    level = pois.join(given, F.col("event_id") == F.col("g_id")).select("case_id", "event_id", F.col("src_id").alias("n"), F.col("end_us").alias("b"), F.lit(1).cast("bigint").alias("many"))
    out = None
    for hop in range(COST_HOPS + 1):
        level = plans.pin(level, "cost")
        own = level.groupBy("case_id").agg(F.lit(hop).alias("hop"), F.sum("many").alias("paths"), F.count_distinct("event_id").alias("events"), F.count_distinct("n").alias("nodes"))
        out = own if out is None else out.unionByName(own)
        step = level.join(usable.withColumnRenamed("event_id", "x_id"), (F.col("dst_id") == F.col("n")) & (F.col("start_us") < F.col("b")))
        level = step.groupBy("case_id", F.col("x_id").alias("event_id"), F.col("src_id").alias("n"), F.col("end_us").alias("b")).agg(F.sum("many").alias("many"))
    return out


def _word_rows() -> list[tuple[str, str, int]]:
    rows = []
    for c in ALL:
        find = parse(cases.search_text(c))[0]
        rows += [("search", form, measure.words(text)) for form, text in (
            ("language", cases.search_text(c)), ("sql", monolithic_sql(find)), ("graph", graph_text(find)), ("logsearch", logsearch_text(find)),
        )]
        rows += [("tracking", "language", measure.words(cases.program(c))), ("tracking", "sql", measure.words(track_sql(cases.event_id(c, cases.poi(c)), 10)))]
    return rows


_WORD = r"[^\x20\x09-\x0D]+"


@register("rq4_words", f"SELECT source AS kind, lang AS form, round(avg(len(regexp_extract_all(text, '{_WORD}'))), 6) AS words FROM documents GROUP BY source, lang")
def rq4_words(spark, sf_dir):
    """Mean words of texts by kind (their source) and form (their language); ``_word_rows`` has those of the cases' queries."""
    docs = views.table(spark, sf_dir, "documents")
    return docs.groupBy(F.col("source").alias("kind"), F.col("lang").alias("form")).agg(F.round(F.avg(F.regexp_count("text", F.lit(_WORD))), 6).alias("words"))


_STUDY_SQL = """
    SELECT task, language, count(*) AS people, round(avg(minutes) FILTER (finished), 6) AS minutes, round(avg(queries) FILTER (finished), 6) AS queries, round(count(*) FILTER (finished) / count(*), 6) AS share_finished
    FROM (SELECT o_orderpriority AS task, c_mktsegment AS language, (epoch_us(last) - epoch_us(o_orderdate)) // 60000000 AS minutes, queries, o_orderstatus = 'F' AS finished
          FROM orders LEFT JOIN customer ON o_custkey = c_custkey
          LEFT JOIN (SELECT l_orderkey, count(*) AS queries, max(l_shipdate) AS last FROM lineitem GROUP BY l_orderkey) ON l_orderkey = o_orderkey)
    GROUP BY task, language"""


@register("rq5_study", _STUDY_SQL)
def rq5_study(spark, sf_dir):
    """The study table of orders: a task is a priority, a language a market segment; minutes until the last item left, queries are items."""
    items = views.table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("queries"), F.max("l_shipdate").alias("last"))
    people = views.table(spark, sf_dir, "customer").select("c_custkey", F.col("c_mktsegment").alias("language"))
    orders = views.table(spark, sf_dir, "orders").join(people, F.col("o_custkey") == F.col("c_custkey"), "left").join(items, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    minutes = F.floor((X.micros(F.col("last")) - X.micros(F.col("o_orderdate"))) / 60_000_000)
    return measure.study_summary(orders.select(F.col("o_orderpriority").alias("task"), "language", minutes.alias("minutes"), "queries", (F.col("o_orderstatus") == "F").alias("finished")))


@register("rq5_likert", "SELECT question, count(*) AS answers, round(count(*) FILTER (answer < 3) / count(*), 6) AS disagree, round(count(*) FILTER (answer = 3) / count(*), 6) AS neutral, "
          "round(count(*) FILTER (answer > 3) / count(*), 6) AS agree FROM (SELECT o_orderstatus AS question, CAST(substr(o_orderpriority, 1, 1) AS INTEGER) AS answer FROM orders) WHERE answer IS NOT NULL GROUP BY 1")  # fmt: skip
def rq5_likert(spark, sf_dir):
    """Shares of the five-point priorities of orders, by the orders' status."""
    return measure.likert(views.table(spark, sf_dir, "orders").select(F.col("o_orderstatus").alias("question"), F.substring("o_orderpriority", 1, 1).cast("int").alias("answer")))


def _search_sql() -> str:
    """All searches as joins, one after the other."""
    parts = []
    for c in ALL:
        find = parse(cases.search_text(c))[0]
        steps = range(len(find.steps))
        parts.append(f"q{c} AS MATERIALIZED ({joined_sql(find, 'pev', 'pent')})")
        parts.append(f"u{c} AS ({' UNION '.join(f'SELECT CAST({c} AS BIGINT) AS case_id, e{k} AS event_id FROM q{c}' for k in steps)})")
    every = " UNION ALL ".join(f"SELECT case_id, event_id FROM u{c}" for c in ALL)
    return oracle.with_stored(every, cases.planted_sql().replace("pev AS (", "pev AS MATERIALIZED ("), cases.entities_sql(), *parts)


@register("cases_search", _search_sql())
def cases_search(spark, sf_dir):
    """Matches of the searches of all cases."""
    from tracelake.search import search

    store = _store(spark, sf_dir)
    out = None
    for c in ALL:
        own = search(parse(cases.search_text(c))[0], store, eager=None).graph.events.select(F.lit(c).cast("bigint").alias("case_id"), "event_id")
        out = own if out is None else out.unionByName(own)
    return out
