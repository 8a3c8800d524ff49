"""All queries on the given tables, by name, and their SQL."""

from __future__ import annotations

from flowrings.queries import graph_queries, ledger_queries, risk_queries, search_queries

_PARTS = (ledger_queries, graph_queries, search_queries, risk_queries)
QUERIES = {name: run for part in _PARTS for name, run in part.QUERIES.items()}
ORACLES = {name: sql for part in _PARTS for name, sql in part.ORACLES.items()}
FLAGSHIP = "risk_ftl_relay"
