"""Every workload gives its table on the smallest sizes."""

import os

import pytest

from subgraph_engine import workloads

COLUMNS = {
    "runtime": {"graph", "algorithm", "strategy", "prep_s", "run_s", "messages", "bytes"},
    "worker_caps": {"max_worker", "mode", "run_s", "functions", "core_s", "saving"},
    "partition_counts": {"p", "algorithm", "min_s", "avg_s", "max_s", "core_s", "cut_ratio", "messages", "keys"},
    "cloud_cost": {"algorithm", "config", "run_s", "vcpu", "cents", "messages"},
    "scale_out": {"graph", "p", "run_s", "keys", "bound", "messages"},
    "key_aggregation": {"graph", "algorithm", "baseline_s", "optimized_s", "speedup", "keys_before", "keys_after"},
    "colocation": {"threads", "run_s", "memory_bytes", "messages"},
    "activation": {"activate_from", "run_s", "arcs_scanned", "active"},
    "claims": {"metric", "paper", "ours"},
}


@pytest.mark.parametrize("name", [n for n in workloads.WORKLOADS if n != "claims"])
def test_tables(spark, sf_dir, name):
    rows = list(workloads.WORKLOADS[name](spark, os.path.dirname(sf_dir), **workloads.QUICK[name]))
    assert rows and COLUMNS[name] <= set(rows[0])
    if name == "partition_counts":
        assert rows[0]["messages"] < rows[1]["messages"] and all(r["min_s"] <= r["avg_s"] <= r["max_s"] for r in rows)
    if name == "scale_out":
        assert all(r["keys"] <= r["bound"] for r in rows)
    if name == "key_aggregation":
        assert all(r["keys_after"] < r["keys_before"] for r in rows)
    if name == "colocation":
        assert rows[1]["messages"] == 0 < rows[0]["messages"] and rows[1]["memory_bytes"] < rows[0]["memory_bytes"]
    if name == "activation":
        assert rows[1]["arcs_scanned"] < rows[0]["arcs_scanned"]


def test_every_workload_is_listed():
    assert set(workloads.WORKLOADS) == set(workloads.QUICK) == set(COLUMNS)
