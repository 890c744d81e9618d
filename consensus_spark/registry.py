"""Every registered query of the engine, with its DuckDB twin where SQL can state it."""

from __future__ import annotations

from consensus_spark.plans import (
    schedule_queries,
    speedup_queries,
    surrounding_queries,
    training_queries,
    workload_queries,
)

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
for _module in (schedule_queries, training_queries, speedup_queries, workload_queries, surrounding_queries):
    QUERIES |= _module.QUERIES
    ORACLE_SQL |= _module.ORACLE_SQL
