"""The views of the given tables as DuckDB SQL, for comparison."""

from __future__ import annotations

EVENTS = """
    t_third AS (SELECT (max(user_id) + 1) // 3 AS third FROM events),
    t_users AS (
        SELECT c_custkey AS user_id, lower(c_mktsegment) AS exe, n_name AS owner, r_name AS owner_group,
               'host' || (c_custkey % 3 + 1) AS host, 'p:host' || (c_custkey % 3 + 1) || ':' || lower(c_mktsegment) || ':' || c_custkey AS pid_key
        FROM customer LEFT JOIN nation ON c_nationkey = n_nationkey LEFT JOIN region ON n_regionkey = r_regionkey),
    t_files AS (
        SELECT p_partkey AS k, replace(p_name, ' ', '_') || '.' || lower(p_type) AS file_name,
               '/' || replace(lower(p_brand), '#', '') || '/' || p_partkey || '/' || replace(p_name, ' ', '_') || '.' || lower(p_type) AS path
        FROM part WHERE p_partkey < 100),
    t_raw AS (
        SELECT event_id, user_id, 'host' || (user_id % 3 + 1) AS host, event_type,
               CAST(json_extract(props, '$.k') AS BIGINT) AS k, epoch_us(ts) AS start_us,
               epoch_us(ts) + CAST(round(value * 1e6) AS BIGINT) AS end_us, CAST(round(value * 100) AS BIGINT) AS amount
        FROM events),
    t_ends AS (
        SELECT r.*, CASE event_type WHEN 'view' THEN 'read' WHEN 'purchase' THEN 'write' WHEN 'click' THEN 'recvfrom' WHEN 'error' THEN 'sendto' ELSE 'clone' END AS op,
               s.pid_key AS subject_id,
               CASE WHEN event_type IN ('view', 'purchase') THEN 'f:' || r.host || ':' || f.path
                    WHEN event_type IN ('click', 'error') AND r.k < 30 THEN 'n:tcp:10.0.0.1:' || (30000 + r.k) || ':10.0.0.2:22'
                    WHEN event_type IN ('click', 'error') THEN 'n:tcp:10.0.' || (r.user_id % 3 + 1) || '.1:' || (40000 + r.k) || ':203.0.113.' || r.k || ':443'
                    ELSE o.pid_key END AS object_id
        FROM t_raw r CROSS JOIN t_third
        JOIN t_users s ON s.user_id = r.user_id
        LEFT JOIN t_users o ON o.user_id = 3 * (r.k % third) + r.user_id % 3
        LEFT JOIN t_files f ON f.k = r.k),
    ev AS (
        SELECT event_id, host, CASE WHEN op IN ('read', 'write') THEN 'file' WHEN op IN ('recvfrom', 'sendto') THEN 'network' ELSE 'process' END AS category, op,
               subject_id, object_id, CASE WHEN op IN ('read', 'recvfrom') THEN object_id ELSE subject_id END AS src_id,
               CASE WHEN op IN ('read', 'recvfrom') THEN subject_id ELSE object_id END AS dst_id, start_us, end_us, amount
        FROM t_ends)"""

ENTITIES = """
    ent AS (
        SELECT DISTINCT u.pid_key AS entity_id, 'process' AS kind, u.host, u.exe AS name, '/bin/' || u.exe AS path, u.exe AS exe_name, '/bin/' || u.exe AS exe_path,
               u.exe || ' --acct ' || u.user_id AS cmdline, CAST(NULL AS VARCHAR) AS src_ip, CAST(NULL AS VARCHAR) AS dst_ip, u.user_id AS pid,
               CAST(NULL AS INTEGER) AS src_port, CAST(NULL AS INTEGER) AS dst_port, u.owner, u.owner_group
        FROM t_users u WHERE u.pid_key IN (SELECT subject_id FROM ev UNION SELECT object_id FROM ev)
        UNION ALL
        SELECT DISTINCT object_id, 'file', e.host, f.file_name, f.path, NULL, NULL, NULL, NULL, NULL, NULL, NULL, NULL, NULL, NULL
        FROM ev e JOIN t_files f ON e.object_id = 'f:' || e.host || ':' || f.path WHERE category = 'file'
        UNION ALL
        SELECT DISTINCT object_id, 'network', NULL, substr(object_id, 3), NULL, NULL, NULL, NULL, split_part(object_id, ':', 3), split_part(object_id, ':', 5), NULL,
               CAST(split_part(object_id, ':', 4) AS INTEGER), CAST(split_part(object_id, ':', 6) AS INTEGER), NULL, NULL
        FROM ev WHERE category = 'network')"""

SUPPLY = """
    t_items AS (
        SELECT 1000000000000 + l_orderkey * 1000 + l_linenumber * 100 AS base,
               CASE WHEN l_linestatus = 'F' THEN 'write' WHEN l_returnflag = 'R' THEN 'sendto' ELSE 'read' END AS op,
               'p:supplier:' || l_suppkey AS vendor, 'f:part:' || l_partkey AS part, 'p:order:' || l_orderkey AS ord, 'n:nation:' || n_name AS wire,
               epoch_us(l_shipdate) AS start_us, epoch_us(l_shipdate) + CAST(round(l_quantity * 1e6) AS BIGINT) AS end_us, CAST(round(l_extendedprice * 100) AS BIGINT) AS amount
        FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey),
    t_flow AS (
        SELECT base, op, CASE op WHEN 'write' THEN vendor WHEN 'sendto' THEN ord ELSE part END AS src_id,
               CASE op WHEN 'write' THEN part WHEN 'sendto' THEN wire ELSE ord END AS dst_id, start_us, end_us, amount FROM t_items),
    ev AS (
        SELECT o_orderkey AS event_id, 'clone' AS op, 'p:customer:' || o_custkey AS src_id, 'p:order:' || o_orderkey AS dst_id,
               epoch_us(o_orderdate) AS start_us, epoch_us(o_orderdate) AS end_us, CAST(round(o_totalprice * 100) AS BIGINT) AS amount FROM orders
        UNION ALL
        SELECT base + row_number() OVER (PARTITION BY base ORDER BY op, src_id, dst_id, start_us, end_us, amount) - 1, op, src_id, dst_id, start_us, end_us, amount FROM t_flow)"""


def chain(long_links: int = 0) -> str:
    extra = f"""
        UNION ALL
        SELECT h.conv_id * 1000 + 3, 'read', 'f:host1:/conv/' || c || '/' || t, 'p:host1:' || role || ':' || (h.conv_id * 100), h.conv_id * 1000000000 - 500000, h.conv_id * 1000000000 - 500000
        FROM t_turns h JOIN (SELECT conv_id AS c, max(turn) AS t FROM t_turns WHERE conv_id < {long_links} GROUP BY 1) ON h.conv_id = c + 1 WHERE h.turn = 0"""
    return f"""
    t_turns AS (SELECT DISTINCT conv_id, turn, role FROM conversations),
    ev AS (
        SELECT conv_id * 1000 + turn * 10 + 1 AS event_id, 'write' AS op, 'p:host1:' || role || ':' || (conv_id * 100 + turn) AS src_id, 'f:host1:/conv/' || conv_id || '/' || turn AS dst_id,
               conv_id * 1000000000 + turn * 1000000 AS start_us, conv_id * 1000000000 + turn * 1000000 AS end_us FROM t_turns
        UNION ALL
        SELECT conv_id * 1000 + turn * 10 + 2, 'read', 'f:host1:/conv/' || conv_id || '/' || (turn - 1), 'p:host1:' || role || ':' || (conv_id * 100 + turn),
               conv_id * 1000000000 + turn * 1000000 - 500000, conv_id * 1000000000 + turn * 1000000 - 500000 FROM t_turns WHERE turn > 0
        {extra if long_links else ""})"""


def with_events(body: str, *more: str, recursive: bool = False) -> str:
    return f"WITH {'RECURSIVE ' * recursive}{', '.join([EVENTS, *more])} {body}"


def with_stored(body: str, *more: str, recursive: bool = False) -> str:
    """:func:`with_events` and entities, each worked out once."""
    stored = [part.replace("\n    ev AS (", "\n    ev AS MATERIALIZED (").replace("\n    ent AS (", "\n    ent AS MATERIALIZED (") for part in (EVENTS, ENTITIES)]
    return f"WITH {'RECURSIVE ' * recursive}{', '.join([*stored, *more])} {body}"


def closure(poi: str, direction: str = "back", events: str = "ev", usable: str = "ev", hops: int | None = None, name: str = "r") -> str:
    """CTE ``name`` with event_id (and hop, if limited) of the trace of the events that meet ``poi``."""
    keep = ("event_id", "src_id", "end_us") if direction == "back" else ("event_id", "dst_id", "start_us")
    rule = "x.dst_id = r.n AND x.start_us < r.b" if direction == "back" else "x.src_id = r.n AND x.end_us > r.b"
    hop = (", 0 AS hop", ", r.hop + 1", f" WHERE r.hop < {hops}") if hops is not None else ("", "", "")
    return f"""
    {name}(event_id, n, b{', hop' if hops is not None else ''}) AS (
        SELECT {', '.join(keep)}{hop[0]} FROM {events} WHERE {poi}
        UNION
        SELECT x.{', x.'.join(keep)}{hop[1]} FROM {name} r JOIN {usable} x ON {rule}{hop[2]})"""
