"""The compared systems as strategies, and ablations of one optimization at a time."""

from __future__ import annotations

from typing import Any

from pyspark.sql import DataFrame, SparkSession

from subgraph_engine import messaging
from subgraph_engine.coordinator import run_job
from subgraph_engine.measures import memory_model, timed
from subgraph_engine.model import GraphSpec, JobResult
from subgraph_engine.prepare import partition_by_degree
from subgraph_engine.storage import written_table

#: strategy -> engine and request fields
STRATEGIES: dict[str, tuple[str, dict[str, Any]]] = {
    "per_vertex_kv": ("per_vertex_kv", {"threads": 1}),
    "shared_memory": ("shared_memory", {"threads": 1}),
    "compiled_block": ("block", {"local_sweeps": "fixpoint"}),
    "vertex_centric": ("vertex_centric", {}),
    "edge_centric": ("edge_centric", {}),
    "ours": ("partition", {}),
}


def run_baseline(spark: SparkSession, strategy: str, g: GraphSpec, algorithm: str, **how: Any) -> JobResult:
    engine, own = STRATEGIES[strategy]
    options = {k: v for k, v in own.items() if k != "local_sweeps" or algorithm in ("wcc", "bfs", "sssp")}
    return run_job(spark, g, algorithm, engine, **{**options, **how})


def ablate_key_aggregation(spark: SparkSession, g: GraphSpec, p: int) -> DataFrame:
    """wid, keys_before, keys_after: a key per vertex against a key per pair of partitions."""
    placement = written_table(spark, partition_by_degree(spark, g, p), "ablate")
    before = messaging.key_accesses(g, placement, "vertex").selectExpr("wid", "accesses as keys_before")
    after = messaging.key_accesses(g, placement, "partition").selectExpr("wid", "accesses as keys_after")
    return before.join(after, "wid")


def ablate_colocation(spark: SparkSession, g: GraphSpec, p: int, threads: tuple[int, ...] = (1, 2, 3, 6)) -> DataFrame:
    """threads, functions, bytes, messages: what is held and sent as functions take more partitions."""
    from pyspark.sql import functions as F

    placement = written_table(spark, partition_by_degree(spark, g, p), "ablate")
    out = None
    for t in threads:
        workers = messaging.worker_table(spark, messaging.colocate(p, t))
        memory = memory_model(g, placement, workers).agg(F.count(F.lit(1)).alias("functions"), F.sum("bytes").alias("bytes"))
        sent = messaging.function_routes(g, placement, workers).agg(F.count(F.lit(1)).alias("messages"))
        row = memory.crossJoin(sent).withColumn("threads", F.lit(t))  # one row each
        out = row if out is None else out.unionByName(row)
    return out.select("threads", "functions", "bytes", "messages")


def ablate_activation(spark: SparkSession, g: GraphSpec, algorithm: str, thresholds=(None, 0, 1, 2, 4), **how: Any) -> list[dict[str, Any]]:
    """One row per threshold: seconds, supersteps, arcs scanned, active vertices."""
    rows = []
    for activate_from in thresholds:
        result, seconds = timed(lambda: run_job(spark, g, algorithm, activate_from=activate_from, **how))
        rows.append(
            {
                "activate_from": activate_from,
                "seconds": seconds,
                "supersteps": len(result.history),
                "arcs_scanned": sum(h["arcs_scanned"] for h in result.history),
                "active": sum(h["active"] for h in result.history),
            }
        )
    return rows
