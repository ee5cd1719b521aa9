"""Every query that has SQL against DuckDB on the smallest tables."""

import pytest

import __spark_entry__ as entry_module
from subgraph_engine import queries
from subgraph_engine.operators import queries as operator_queries
from subgraph_engine.streaming import queries as stream_queries

PARTS = [queries, operator_queries, stream_queries]
CASES = [(name, f, part.ORACLE_SQL[name]) for part in PARTS for name, f in part.QUERIES.items() if name in part.ORACLE_SQL]
REST = [(name, f) for part in PARTS for name, f in part.QUERIES.items() if name not in part.ORACLE_SQL]


@pytest.mark.parametrize(("query", "sql"), [pytest.param(f, sql, id=name) for name, f, sql in CASES])
def test_same_as_sql(same_as_sql, query, sql):
    same_as_sql(query, sql)


@pytest.mark.parametrize("query", [pytest.param(f, id=name) for name, f in REST])
def test_runs(spark, sf_dir, query):
    assert query(spark, sf_dir).count() > 0


def test_entry_names_and_sql():
    assert set(entry_module.oracle_sql()) <= set(entry_module.queries())
    assert {"wcc_basket", "pr_basket", "cdlp_copurchase", "bfs_basket"} <= set(entry_module.queries())
