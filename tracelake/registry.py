"""Names of all queries of the engine and their SQL counterparts."""

from __future__ import annotations

from tracelake import catalogue, streamed, studies, workloads

assert catalogue and streamed and studies  # they register their queries with the workloads
QUERIES: dict = {**workloads.QUERIES}
ORACLE_SQL: dict = {**workloads.ORACLE_SQL}
