"""Registered queries with their SQL: one module per part of the engine."""

from __future__ import annotations

from . import baseline_queries, cost_queries, join_queries, relational_queries, skew_queries

_PARTS = (skew_queries, join_queries, cost_queries, baseline_queries, relational_queries)

QUERIES = {name: q for part in _PARTS for name, q in part.QUERIES.items()}
ORACLES = {name: sql for part in _PARTS for name, sql in part.ORACLES.items()}
