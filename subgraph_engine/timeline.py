"""Timelines of workers by list scheduling, in both modes.

Input is small: one row per superstep and partition with the seconds of its
phases. The result has one row per phase a worker was in.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Work:
    superstep: int
    pid: int
    load: float
    compute: float
    message: float
    partial: float = 0.0


Phase = tuple[int, int, int | None, str, float, float]  # worker, superstep, partition, phase, start, end


def simulate(work: list[Work], max_worker: int, mode: str, preload: bool = False) -> list[Phase]:
    """Phases of every worker: load, messages, partials, compute, write, wait.

    Pinned: a worker per partition, which loads in superstep 0 alone. Rotating:
    the next partition goes to the worker that is free first; with ``preload`` a
    worker that finds none left fetches the partition it will have in the next
    superstep, and is charged only what the barrier does not hide.
    """
    steps = sorted({w.superstep for w in work})
    by_step = {k: sorted((w for w in work if w.superstep == k), key=lambda w: w.pid) for k in steps}
    phases: list[Phase] = []
    now = 0.0
    fetched: dict[int, tuple[int, float]] = {}  # worker -> partition, when its load ends
    n = max(len(v) for v in by_step.values()) if mode == "pinned" else min(max_worker, max(len(v) for v in by_step.values()))
    for k in steps:
        free = [(now, w) for w in range(n)]
        heapq.heapify(free)
        ends = [now] * n
        queue = list(by_step[k])
        if fetched:  # workers begin with what they have fetched
            order = {pid: i for i, (pid, _) in enumerate(fetched.values())}
            queue.sort(key=lambda w: (w.pid not in order, w.pid))
        for item in queue:
            holder = next((w for w, (pid, _) in fetched.items() if pid == item.pid), None)
            if mode == "pinned":
                at, worker = now, item.pid
            elif holder is not None and any(w == holder for _, w in free):
                at = next(t for t, w in free if w == holder)
                free = [(t, w) for t, w in free if w != holder]
                heapq.heapify(free)
                worker = holder
            else:
                at, worker = heapq.heappop(free)

            def spend(phase: str, seconds: float) -> None:
                nonlocal at
                if seconds > 0:
                    phases.append((worker, k, item.pid, phase, at, at + seconds))
                    at += seconds

            if mode == "rotating" or k == steps[0]:
                ready = fetched.get(worker, (None, 0.0))
                spend("load", max(0.0, ready[1] - at) if ready[0] == item.pid else item.load)
            if k != steps[0]:
                spend("messages", item.message)
                spend("partials", item.partial if mode == "rotating" else 0.0)
            spend("compute", item.compute)
            spend("write", item.message + (item.partial if mode == "rotating" else 0.0))
            ends[worker] = at
            if mode == "rotating":
                heapq.heappush(free, (at, worker))
        barrier = max(ends)
        fetched = {}
        if preload and mode == "rotating" and k != steps[-1]:
            nxt = by_step[steps[steps.index(k) + 1]]
            idle = sorted((t, w) for w, t in enumerate(ends) if t < barrier)
            for (t, w), item in zip(idle, nxt):
                phases.append((w, k, item.pid, "preload", t, min(t + item.load, barrier)))
                fetched[w] = (item.pid, t + item.load)
        for w, t in enumerate(ends):
            begin = max([t, *(e for ww, kk, _, ph, _, e in phases if ww == w and kk == k and ph == "preload")])
            if begin < barrier:
                phases.append((w, k, None, "wait", begin, barrier))
        now = barrier
    return phases


PHASES = "wid int, superstep int, pid int, phase string, start double, end double"


def timeline(spark: SparkSession, work: list[Work], max_worker: int, mode: str, preload: bool = False) -> DataFrame:
    return spark.createDataFrame(simulate(work, max_worker, mode, preload), PHASES)


def concurrency(phases: DataFrame) -> DataFrame:
    """t, running: functions alive from each moment on; waiting ones poll, so they count."""
    life = phases.groupBy("wid").agg(F.min("start").alias("a"), F.max("end").alias("b"))
    steps = life.select(F.col("a").alias("t"), F.lit(1).alias("d")).unionByName(life.select(F.col("b").alias("t"), F.lit(-1).alias("d")))
    steps = steps.groupBy("t").agg(F.sum("d").alias("d"))
    running = F.sum("d").over(Window.orderBy("t").rowsBetween(Window.unboundedPreceding, 0))  # two rows per worker
    return steps.select("t", running.cast("long").alias("running"))


def core_seconds(phases: DataFrame, vcpu: float) -> DataFrame:
    """core_seconds: one row; from a function's first start to its last end, waiting included."""
    life = phases.groupBy("wid").agg((F.max("end") - F.min("start")).alias("s"))
    return life.agg((F.sum("s") * vcpu).alias("core_seconds"))


def gb_seconds(phases: DataFrame, memory_mb: float) -> DataFrame:
    life = phases.groupBy("wid").agg((F.max("end") - F.min("start")).alias("s"))
    return life.agg((F.sum("s") * memory_mb / 1024).alias("gb_seconds"))
