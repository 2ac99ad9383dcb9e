"""Ways of tracking to compare with: one recursive statement, enumeration of paths, a script."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracelake import plans
from tracelake.track import engines

_ROWS = "spark.sql.cteRecursionRowLimit"


def track_sql(event_id: int, max_hops: int, view: str = "trace_events") -> str:
    """A single recursive statement for the backward trace of one event. Repeats an event once for every path."""
    return f"""
        WITH RECURSIVE walk(event_id, src_id, end_us, hop) AS (
            SELECT event_id, src_id, end_us, 0 FROM {view} WHERE event_id = {event_id}
            UNION ALL
            SELECT e.event_id, e.src_id, e.end_us, w.hop + 1
            FROM walk w JOIN {view} e ON e.dst_id = w.src_id AND e.start_us < w.end_us
            WHERE w.hop < {max_hops}
        )
        SELECT DISTINCT event_id FROM walk
    """


def walk_sql(event_id: int, max_hops: int, view: str = "trace_events") -> str:
    """The same trace as a recursive statement over nodes and bounds.

    A step makes one row for each node that a row reaches, with the latest end of the edges
    between the two, so parallel events don't multiply the paths; equal rows are made one, and
    the last hop's events are found once for each node. The lateral part begins with the row's own
    node and bound: were they outer conditions on the edges, Spark would pair all edges with each
    bound before it looks at nodes. Rows of the last hop are left out before the lateral part,
    which would find their edges for nothing.
    """
    return f"""
        WITH RECURSIVE walk(node, bound, hop) AS (
            SELECT src_id, end_us, 1 FROM {view} WHERE event_id = {event_id}
            UNION ALL
            SELECT DISTINCT x.src_id, x.bound, w.hop + 1
            FROM (SELECT node, bound, hop FROM walk WHERE hop < {max_hops}) w, LATERAL (
                SELECT e.src_id, max(e.end_us) AS bound
                FROM (SELECT w.node AS node, w.bound AS bound) o JOIN {view} e ON e.dst_id = o.node AND e.start_us < o.bound
                GROUP BY e.src_id
            ) x
        )
        SELECT event_id FROM {view} WHERE event_id = {event_id}
        UNION
        SELECT e.event_id FROM (SELECT node, max(bound) AS bound FROM walk WHERE hop <= {max_hops} GROUP BY node) w JOIN {view} e ON e.dst_id = w.node AND e.start_us < w.bound
    """


def run_track_sql(source, event_id: int, max_hops: int) -> DataFrame:
    """Runs :func:`walk_sql`, written out with Spark's limit on the rows of a recursion lifted: hops bound it."""
    spark = source.events.sparkSession
    source.edges().createOrReplaceTempView("trace_events")
    before = spark.conf.get(_ROWS, None)
    spark.conf.set(_ROWS, "-1")
    try:
        return plans.pin(spark.sql(walk_sql(event_id, max_hops)), "walk")
    finally:
        spark.conf.unset(_ROWS) if before is None else spark.conf.set(_ROWS, before)


def track_paths(source, event_id: int, max_hops: int, keep=None) -> DataFrame:
    """Backward paths of up to ``max_hops`` steps without a repeated event: path (array), last; filtered only when complete."""
    edges = engines.directed(source.edges(), "back")
    poi = edges.where(F.col("event_id") == event_id)
    paths = poi.select(F.array("event_id").alias("path"), F.col("next").alias("at"), F.col("t_out").alias("bound"))
    out = paths
    for _ in range(max_hops):
        step = paths.join(edges, (F.col("key") == F.col("at")) & (F.col("t_in") < F.col("bound")) & ~F.array_contains("path", F.col("event_id")))
        paths = step.select(F.array_append("path", F.col("event_id")).alias("path"), F.col("next").alias("at"), F.col("t_out").alias("bound"))
        out = out.unionByName(paths)
    out = out.select("path", F.element_at("path", -1).alias("last"))
    return out if keep is None else out.where(keep)


def script(event_id: int, found: str, view: str = "trace_events", max_rounds: int = 100) -> str:
    """The rounds as one SQL script: each adds to the table ``found`` the events that depend on the last round's."""
    return f"""
        BEGIN
            DECLARE hop INT DEFAULT 0;
            DECLARE grown BIGINT DEFAULT 1;
            CREATE TABLE {found} USING parquet AS SELECT event_id, src_id, end_us, 0 AS level FROM {view} WHERE event_id = {event_id};
            WHILE grown > 0 AND hop < {max_rounds} DO
                INSERT INTO {found}
                SELECT e.event_id, e.src_id, e.end_us, hop + 1
                FROM {view} e
                JOIN (SELECT src_id, max(end_us) AS bound FROM {found} WHERE level = hop GROUP BY src_id) f ON e.dst_id = f.src_id AND e.start_us < f.bound
                LEFT ANTI JOIN {found} seen ON seen.event_id = e.event_id;
                SET hop = hop + 1;
                SET grown = (SELECT count(*) FROM {found} WHERE level = hop);
            END WHILE;
        END
    """


def track_script(source, event_id: int, max_rounds: int = 100) -> DataFrame:
    """Runs the script; the table lies in the warehouse and holds event_id and level."""
    spark = source.events.sparkSession
    found = f"trace_{uuid.uuid4().hex}"
    source.edges().createOrReplaceTempView("trace_events")
    spark.sql(script(event_id, found, max_rounds=max_rounds))
    return spark.table(found).select("event_id", "level")
