"""The superstep loop, in both modes.

A Spark job's end is the barrier. Its counters (an observation on the write, no
second pass) say how many vertices changed and of how many vertices the state
now consists: the superstep is complete when no partition is unfinished, and goes
on while any partition has changed something.
"""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from typing import Any

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.engines import ENGINES
from subgraph_engine.engines.base import Engine, bytes_by_row, explicit_layout, marked_broadcasts
from subgraph_engine.engines.store import StoreEngine
from subgraph_engine.model import GraphSpec, JobRequest, JobResult
from subgraph_engine.modes import choose_mode, waves
from subgraph_engine.programs import lookup
from subgraph_engine.storage import scratch, shared_path


class Coordinator:
    """Runs requests on a graph."""

    def __init__(self, spark: SparkSession, graph: GraphSpec, engine: str = "partition", placement: DataFrame | None = None):
        self.spark, self.graph, self.engine, self.placement = spark, graph, engine, placement

    def run(self, request: JobRequest, until: Callable[[dict[str, Any]], bool] | None = None) -> JobResult:
        """All supersteps; ``until`` may end the job early, from a superstep's counters."""
        mode = request.mode or choose_mode(request.max_worker, request.partitions, request.threads, request.strict_partition_rule)
        options = {k: v for k, v in request.options.items() if k != "local_sweeps"}
        program = lookup(request.algorithm)(**options)
        history: list[dict[str, Any]] = []
        path = shared_path(self.spark, "job-values")
        with marked_broadcasts(self.spark), bytes_by_row(self.spark), scratch(self.spark):  # placement, arcs, routes, messages and states go with the job
            engine = ENGINES[self.engine](self.spark, self.graph, program, request, self.placement, pinned=mode == "pinned")
            try:
                values = self._supersteps(engine, request, mode, until, history)
                values.write.option("compression", "zstd").parquet(path)
            finally:
                engine.close()
        return JobResult(self.spark.read.schema(values.schema).parquet(path), history, mode, request, engine.worked)

    def _supersteps(self, engine: Engine, request: JobRequest, mode: str, until, history: list[dict[str, Any]]) -> DataFrame:
        state = engine.prepare()
        if mode == "pinned":
            step = engine.superstep
        elif isinstance(engine, StoreEngine):
            step = engine.rotation(min(request.max_worker, engine.functions), request.preload)
        else:
            step = self._rotate(engine, request)
        k = 0
        while True:
            state, counted = step(k, state)
            missing = request.partitions if counted["vertices"] != engine.n_vertices else 0
            last = engine.program.ends(k, counted) or k + 1 >= request.max_supersteps or bool(until and until(counted))
            history.append(
                {"superstep": k, "unfinished": counted.get("unfinished", missing), "keep_going": counted["changed"] > 0, "finish": last}
                | {n: int(counted.get(n) or 0) for n in ("changed", "active", "arcs_scanned", "messages", "keys", "bytes")}
            )
            if last:
                return engine.values(state)
            k += 1

    def _rotate(self, engine: Engine, request: JobRequest):
        """Supersteps in waves of at most so many partitions as workers may run."""
        plan = waves(request.partitions, request.max_worker * request.threads)
        pool = ThreadPoolExecutor(1) if request.preload else None
        ready: dict[int, DataFrame] = {}

        def load(pids: list[int]) -> None:
            arcs = engine.arcs.drop("src_pid").filter(F.col("pid").isin(*pids)).repartitionById(request.partitions, "pid").persist()
            arcs.count()
            ready[0] = arcs

        read = engine.wave_arcs

        def wave_arcs(pids: list[int] | None) -> DataFrame:
            return ready[0] if pids == plan[0] and 0 in ready else read(pids)

        def forget() -> None:
            if 0 in ready:
                ready.pop(0).unpersist()

        engine.wave_arcs = wave_arcs

        def step(k: int, state: DataFrame) -> tuple[DataFrame, dict[str, Any]]:
            path, summed, loading = shared_path(self.spark, "job-wave"), {}, None
            with explicit_layout(self.spark):
                totals = dict(engine.totals)
                for i, pids in enumerate(plan):
                    if pool and i == len(plan) - 1 and len(pids) < len(plan[0]):
                        loading = pool.submit(load, plan[0])  # workers without a partition fetch for the next superstep
                    engine.totals = totals
                    new, counted = engine._written(engine.advance(k, state, pids), path, "append")
                    if i == 0:
                        forget()  # loaded for one superstep; the next is loaded anew
                    engine._paths = [x for x in engine._paths if x != path] + [path]
                    for n, v in counted.items():
                        summed[n] = (summed.get(n) or 0) + (v or 0)
                engine.totals = {n: summed[n] for n in engine.program.totals()}
                engine.changed_share = summed["changed"] / max(1, summed["vertices"])
                if loading:
                    loading.result()
            return new, summed

        def stop() -> None:
            forget()
            if pool:
                pool.shutdown()

        engine.on_close.append(stop)
        return step


def run_job(spark: SparkSession, graph: GraphSpec, algorithm: str, engine: str = "partition", placement: DataFrame | None = None, **request: Any) -> JobResult:
    """Shorthand: a request's fields by name, all others are the program's options."""
    known = {f for f in JobRequest.__dataclass_fields__ if f not in ("algorithm", "options")}
    own = {k: v for k, v in request.items() if k in known}
    options = {k: v for k, v in request.items() if k not in known}
    return Coordinator(spark, graph, engine, placement).run(JobRequest(algorithm, options=options, **own))
