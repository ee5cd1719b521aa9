"""What large tables need, shown on small ones."""

import pytest

from subgraph_engine import graphs, messaging, prepare, queries
from subgraph_engine.coordinator import Coordinator
from subgraph_engine.model import JobRequest
from subgraph_engine.operators import queries as operator_queries
from subgraph_engine.storage import written_table


@pytest.fixture(scope="module")
def basket(spark, sf_dir):
    g = graphs.basket(spark, sf_dir)
    return g, written_table(spark, prepare.partition_by_degree(spark, g, 8), "placement")


@pytest.mark.parametrize("build", [
    prepare.placed_arcs, prepare.mirrors, prepare.adjacency_sets, prepare.adjacency_bitmaps, messaging.routes,
    lambda g, pl: messaging.outbox(pl.withColumnRenamed("pid", "value"), messaging.routes(g, pl)),
])
def test_placements_are_not_broadcast(basket, build):
    """A placement's file has about a byte a row; by that size Spark broadcast ten million rows through the driver."""
    plan = build(*basket)._jdf.queryExecution().executedPlan().toString()
    assert "Join" in plan and "Broadcast" not in plan


@pytest.mark.parametrize("engine", ["partition", "store", "per_vertex_kv"])
def test_jobs_broadcast_only_what_is_marked(spark, sf_dir, engine):
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    seen = []

    def until(counted):
        seen.append(spark.conf.get("spark.sql.autoBroadcastJoinThreshold"))
        return True

    Coordinator(spark, graphs.geo(spark, sf_dir), engine).run(JobRequest("wcc"), until)
    assert seen == ["-1"]
    assert spark.conf.get("spark.sql.autoBroadcastJoinThreshold") == before
    assert spark.conf.get("spark.sql.adaptive.autoBroadcastJoinThreshold", None) is None


def test_neighbours_of_many_blocks(spark, same_as_sql, monkeypatch):
    """Tiles of two blocks met only where their keys, a long and an int, were dealt alike."""
    monkeypatch.setattr(graphs, "KNN_BLOCK", 30)
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        same_as_sql(queries.QUERIES["g_knn_edges"], queries.ORACLE_SQL["g_knn_edges"])
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")


@pytest.mark.parametrize("name", ["bfs_multi", "cdlp_directed_knn", "pr_personal", "base_block_cdlp"])
def test_queries_on_neighbours_of_many_blocks(spark, same_as_sql, monkeypatch, name):
    """What is computed on the graph of neighbours, where that graph is made of many tiles."""
    monkeypatch.setattr(graphs, "KNN_BLOCK", 30)
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        same_as_sql(queries.QUERIES[name], queries.ORACLE_SQL[name])
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")


@pytest.mark.parametrize(("name", "part", "table"), [
    ("mask_example", queries, "lineitem"), ("cost_saving", queries, "lineitem"), ("mode_rule", queries, "lineitem"), ("cost_cloud", queries, "orders"), ("g_kron_degrees", operator_queries, "pages"),
])
def test_tables_are_read(spark, sf_dir, name, part, table):
    """These were of made-up rows, whatever the tables held."""
    assert any(f.endswith(f"{table}.parquet") for f in part.QUERIES[name](spark, sf_dir).inputFiles())


def test_timelines_read_lineitem(spark, sf_dir, duck):
    """Their work was made up, whatever the table held."""
    want = duck.sql("SELECT count(*)::DOUBLE, sum(l_quantity) FROM lineitem").fetchall()[0]
    work = queries._work(spark, sf_dir)
    assert (sum(w.load for w in work), sum(w.compute for w in work)) == want
    assert (len(work), all(w.message > 0 for w in work)) == (15, True)
