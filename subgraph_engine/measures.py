"""Cost measures and checks of results."""

from __future__ import annotations

import time
from collections.abc import Callable
from typing import Any

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.functions.sqltools import varint_bytes
from subgraph_engine.messaging import unified_mirror
from subgraph_engine.model import GraphSpec
from subgraph_engine.prepare import placed_arcs

# Prices and sizes of the public function service.
USD_PER_GB_SECOND = 0.0000166667
USD_PER_MILLION_REQUESTS = 0.20
MB_PER_VCPU = 1769
UNIT_MB = 128


def timed(run: Callable[[], Any]) -> tuple[Any, float]:
    start = time.perf_counter()
    out = run()
    return out, time.perf_counter() - start


def repeat(n: int, run: Callable[[], Any]) -> dict[str, float]:
    """Least, mean and most seconds of n runs."""
    seconds = [timed(run)[1] for _ in range(n)]
    return {"min": min(seconds), "avg": sum(seconds) / n, "max": max(seconds)}


def speedup(baseline: float, optimized: float) -> float:
    return baseline / optimized


def reduction(baseline: float, optimized: float) -> float:
    """Share of the baseline that is saved; also the saving of resources or cost."""
    return 1 - optimized / baseline


saving = reduction


def vcpu_of(memory_mb: float) -> float:
    return memory_mb / MB_PER_VCPU


def equivalent_functions(memory_mb: float, unit_mb: float = UNIT_MB) -> float:
    return memory_mb / unit_mb


def faas_cost(gb_s: float, requests: int) -> float:
    return gb_s * USD_PER_GB_SECOND + requests * USD_PER_MILLION_REQUESTS / 1e6


def cost_table(spark: SparkSession, runs: DataFrame | list[tuple[str, float, float, int, int]]) -> DataFrame:
    """config, vcpu, units, gb_s, usd of (config, seconds, memory_mb, functions, requests)."""
    rows = runs if isinstance(runs, DataFrame) else spark.createDataFrame(runs, "config string, seconds double, memory_mb double, functions int, requests long")
    gb_s = F.col("seconds") * F.col("memory_mb") / 1024 * F.col("functions")
    return rows.select(
        "config",
        (F.col("memory_mb") / MB_PER_VCPU).alias("vcpu"),
        (F.col("memory_mb") / UNIT_MB).alias("units"),
        gb_s.alias("gb_s"),
        (gb_s * USD_PER_GB_SECOND + F.col("requests") * USD_PER_MILLION_REQUESTS / 1e6).alias("usd"),
    )


VALUE_BYTES = 8


def memory_model(g: GraphSpec, placement: DataFrame, workers: DataFrame) -> DataFrame:
    """wid, inner, outer, adjacency_bytes, bytes: what each function holds.

    Adjacency at its encoded size, a value for each distinct vertex of the function
    whether its own or a copy, and a message buffer of a value per outer copy.
    """
    held = unified_mirror(g, placement, workers).groupBy("wid").agg(
        F.count_if("is_inner").alias("inner"), F.count_if(~F.col("is_inner")).alias("outer")
    )
    arcs = placed_arcs(g, placement, "both")
    from pyspark.sql import Window

    gap = F.col("src") - F.coalesce(F.lag("src").over(Window.partitionBy("dst").orderBy("src")), F.lit(0))
    sizes = arcs.select("pid", varint_bytes(gap).alias("b")).join(F.broadcast(workers), "pid")
    adjacency = sizes.groupBy("wid").agg(F.sum("b").cast("long").alias("adjacency_bytes"))
    both = held.join(adjacency, "wid", "left").withColumn("adjacency_bytes", F.coalesce("adjacency_bytes", F.lit(0).cast("long")))
    total = F.col("adjacency_bytes") + VALUE_BYTES * (F.col("inner") + F.col("outer")) + 2 * VALUE_BYTES * F.col("outer")
    return both.select("wid", "inner", "outer", "adjacency_bytes", total.alias("bytes"))


def validate(result: DataFrame, reference: DataFrame, kind: str, column: str = "value", epsilon: float = 1e-4) -> DataFrame:
    """ok, mismatches: one row. Kinds: ``exact``, ``epsilon`` (relative), ``equivalence`` (same grouping).

    A vertex that only one side has is a mismatch.
    """
    a = result.select("vid", F.col(column).alias("a"))
    b = reference.select("vid", F.col(column).alias("b"))
    both = a.join(b, "vid", "full")
    if kind == "equivalence":
        # groupings agree when each label of one side meets one label of the other
        pairs = both.select("a", "b").distinct()
        bad = [pairs.groupBy(c).agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select(F.col("n")) for c in ("a", "b")]
        missing = both.filter("a is null or b is null").select(F.lit(1).cast("long").alias("n"))
        rows = bad[0].unionByName(bad[1]).unionByName(missing)
        return rows.agg((F.count(F.lit(1)) == 0).alias("ok"), F.count(F.lit(1)).alias("mismatches"))
    if kind == "epsilon":
        wrong = F.coalesce(F.abs(F.col("a") - F.col("b")) > epsilon * F.abs(F.col("b")), F.lit(True))
    else:
        wrong = ~F.col("a").eqNullSafe(F.col("b"))
    n = F.count_if(wrong)
    return both.agg((n == 0).alias("ok"), n.alias("mismatches"))
