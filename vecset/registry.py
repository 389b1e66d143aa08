"""Queries and their DuckDB oracles, by key, gathered from the query modules."""

from __future__ import annotations

from .queries import baseline_queries, cluster_queries, derived_queries, distance_queries, graph_queries, relational_queries, study_queries, workload_queries

QUERIES: dict = {}
ORACLES: dict = {}
for _m in (distance_queries, cluster_queries, graph_queries, baseline_queries, workload_queries, relational_queries, derived_queries, study_queries):
    QUERIES |= _m.QUERIES
    ORACLES |= _m.ORACLES
