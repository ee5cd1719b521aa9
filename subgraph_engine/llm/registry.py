"""All queries and SQL of this subpackage."""

from __future__ import annotations

from subgraph_engine.llm import queries_native, queries_python

MODULES = [queries_native, queries_python]
QUERIES = {name: f for m in MODULES for name, f in m.QUERIES.items()}
ORACLE_SQL = {name: sql for m in MODULES for name, sql in m.ORACLE_SQL.items()}
