"""The experiment workloads on the given tables; each gives rows for a table.

Seconds are of runs alone; loading a graph and placing its vertices is timed apart. The
stand-in graphs are named as in ``graphs``. Sizes, rounds and repeats are arguments:
the defaults are those of the reported experiments, ``QUICK`` has smaller ones.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

from pyspark.sql import DataFrame, SparkSession

from subgraph_engine import baselines, graphs, messaging, prepare
from subgraph_engine.baselines import STRATEGIES, run_baseline
from subgraph_engine.coordinator import run_job
from subgraph_engine.measures import equivalent_functions, faas_cost, reduction, repeat, saving, speedup, timed, vcpu_of
from subgraph_engine.model import GraphSpec, JobResult, UnsupportedAlgorithm
from subgraph_engine.storage import release, written_table

Row = dict[str, Any]
ALGORITHMS = ("bfs", "pagerank", "cdlp", "wcc")
ROUNDS = 10


def load(spark: SparkSession, root: str, sf: str, name: str) -> GraphSpec:
    """A graph written once, so that its building is not timed again and again."""
    g = graphs.BUILDERS[name](spark, f"{root}/{sf}")
    return GraphSpec(g.name, g.directed, g.weighted, written_table(spark, g.vertices, "bench-v"), written_table(spark, g.edges, "bench-e"))


def place(spark: SparkSession, g: GraphSpec, p: int) -> DataFrame:
    return written_table(spark, prepare.partition_by_degree(spark, g, p), "bench-p")


def options(algorithm: str, g: GraphSpec, rounds: int = ROUNDS) -> Row:
    if algorithm == "bfs":
        return {"sources": (g.vertices.agg({"vid": "min"}).first()[0],)}
    return {"iters": rounds} if algorithm in ("pagerank", "cdlp") else {}


def _store(spark: SparkSession, g: GraphSpec, algorithm: str, rounds: int, **how: Any) -> tuple[JobResult, float]:
    return timed(lambda: run_job(spark, g, algorithm, "store", **how, **options(algorithm, g, rounds)))


def _sums(result: JobResult) -> Row:
    return {"supersteps": len(result.history)} | {n: sum(h[n] for h in result.history) for n in ("messages", "keys", "bytes")}


GRAPHS = (("sf0.001", "copurchase"), ("sf0.001", "basket"), ("sf0.01", "basket"), ("sf0.1", "basket"))


def runtime(spark: SparkSession, root: str, sizes=GRAPHS, algorithms=ALGORITHMS, rounds: int = ROUNDS) -> Iterator[Row]:
    """Run time of every strategy; the per-vertex store on the smallest graph alone."""
    for i, (sf, name) in enumerate(sizes):
        g, prep = timed(lambda: load(spark, root, sf, name))
        for algorithm in algorithms:
            for strategy in (*STRATEGIES, "store"):
                if strategy == "per_vertex_kv" and i:
                    continue
                try:
                    if strategy == "store":
                        result, seconds = _store(spark, g, algorithm, rounds)
                    else:
                        result, seconds = timed(lambda: run_baseline(spark, strategy, g, algorithm, **options(algorithm, g, rounds)))
                except UnsupportedAlgorithm:
                    continue
                yield {"graph": f"{name}@{sf}", "algorithm": algorithm, "strategy": strategy, "prep_s": round(prep, 2), "run_s": round(seconds, 2), "per_superstep_s": round(seconds / len(result.history), 2)} | _sums(result)
        release(spark, g.vertices, g.edges)


def worker_caps(spark: SparkSession, root: str, names=("supply", "copurchase"), sf: str = "sf0.001", p: int = 5, algorithms=ALGORITHMS, rounds: int = ROUNDS) -> Iterator[Row]:
    """Functions over time for worker caps 1 to p, and core-seconds against the per-vertex store on p functions.

    A rotating worker is alive from its first function to the end; its times are measured.
    """
    for name in names:
        g = load(spark, root, sf, name)
        placement = place(spark, g, p)
        for algorithm in algorithms:
            _, kv = timed(lambda: run_baseline(spark, "per_vertex_kv", g, algorithm, partitions=p, **options(algorithm, g, rounds)))
            for cap in range(1, p + 1):
                result, seconds = _store(spark, g, algorithm, rounds, placement=placement, partitions=p, max_worker=cap, preload=cap < p)
                first = {w: min(s for x, _, _, s, _ in result.worked if x == w) for w in {x[0] for x in result.worked}}
                end = max((e for *_, e in result.worked), default=0.0)
                cores = sum(end - s for s in first.values()) if first else seconds * p
                yield {"graph": f"{name}@{sf}", "algorithm": algorithm, "max_worker": cap, "mode": result.mode, "run_s": round(seconds, 2), "functions": len(first) or p, "core_s": round(cores, 2), "core_s_per_vertex_store": round(kv * p, 2), "saving": round(saving(kv * p, cores), 3)}
        release(spark, g.vertices, g.edges, placement)


def partition_counts(spark: SparkSession, root: str, sf: str = "sf0.1", counts=(12, 18, 24, 30, 36, 42, 48, 54), algorithms=ALGORITHMS, repeats: int = 3, rounds: int = ROUNDS) -> Iterator[Row]:
    """More partitions: seconds in bands, core-seconds, cut arcs, messages and keys."""
    g = load(spark, root, sf, "basket")
    for p in counts:
        placement = place(spark, g, p)
        m = messaging.message_counts(g, placement, messaging.worker_table(spark, messaging.colocate(p, 6))).first()
        for algorithm in algorithms:
            band = repeat(repeats, lambda: _store(spark, g, algorithm, rounds, placement=placement, partitions=p))
            yield {"p": p, "algorithm": algorithm} | {f"{k}_s": round(x, 2) for k, x in band.items()} | {"core_s": round(band["avg"] * p, 1), "cut_ratio": round(m.cut_arcs / m.arcs, 4), "messages": m.partition_messages, "keys": m.partition_keys, "function_messages_t6": m.function_messages}
        release(spark, placement)


def cloud_cost(spark: SparkSession, root: str, sf: str = "sf0.001", algorithms=ALGORITHMS, rounds: int = ROUNDS) -> Iterator[Row]:
    """One 768 MB function with all partitions against six of 128 MB and the per-vertex store on as many."""
    g = load(spark, root, sf, "supply")
    for algorithm in algorithms:
        cents: dict[str, float] = {}
        for name, memory, functions, threads in (("one 768 MB", 768, 1, 6), ("six 128 MB", 128, 6, 1), ("per-vertex store, six 128 MB", 128, 6, 0)):
            if threads:
                result, seconds = _store(spark, g, algorithm, rounds, partitions=6, threads=threads, max_worker=functions)
                requests = functions * len(result.history)
            else:
                result, seconds = timed(lambda: run_baseline(spark, "per_vertex_kv", g, algorithm, partitions=6, **options(algorithm, g, rounds)))
                requests = functions * len(result.history) * g.vertices.count()  # a request for every key
            cents[name] = 100 * faas_cost(seconds * memory / 1024 * functions, requests)
            yield {"algorithm": algorithm, "config": name, "run_s": round(seconds, 2), "functions": functions, "vcpu": round(vcpu_of(memory), 3), "units": equivalent_functions(memory), "cents": round(cents[name], 5), "messages": _sums(result)["messages"]}
        yield {"algorithm": algorithm, "config": "saving of one function over the per-vertex store", "saving": round(saving(cents["per-vertex store, six 128 MB"], cents["one 768 MB"]), 4)}


def scale_out(spark: SparkSession, root: str, graphs_of=(("sf0.01", "page_links", 64), ("sf0.01", "event_session", 256), ("sf0.1", "basket", 256)), threads: int = 16, algorithms=ALGORITHMS, rounds: int = ROUNDS) -> Iterator[Row]:
    """Many logical partitions: run times, and payload keys below p(p-1)."""
    for sf, name, p in graphs_of:
        g = load(spark, root, sf, name)
        placement = place(spark, g, p)
        m = messaging.message_counts(g, placement, messaging.worker_table(spark, messaging.colocate(p, threads))).first()
        for algorithm in algorithms:
            result, seconds = _store(spark, g, algorithm, rounds, placement=placement, partitions=p, threads=threads)
            yield {"graph": f"{name}@{sf}", "p": p, "threads": threads, "algorithm": algorithm, "run_s": round(seconds, 2), "keys": m.partition_keys, "bound": p * (p - 1), "keys_of_functions": m.function_keys} | _sums(result)
        release(spark, g.vertices, g.edges, placement)


def key_aggregation(spark: SparkSession, root: str, graphs_of=(("sf0.001", "supply"), ("sf0.001", "basket"), ("sf0.01", "basket")), p: int = 6, algorithms=ALGORITHMS, rounds: int = ROUNDS) -> Iterator[Row]:
    """A key per vertex against a key per pair of partitions in the same engine, one partition to a function."""
    for sf, name in graphs_of:
        g = load(spark, root, sf, name)
        placement = place(spark, g, p)
        for algorithm in algorithms:
            (apart, before), (together, after) = (_store(spark, g, algorithm, rounds, placement=placement, partitions=p, aggregate=x) for x in (False, True))
            yield {"graph": f"{name}@{sf}", "algorithm": algorithm, "baseline_s": round(before, 2), "optimized_s": round(after, 2), "speedup": round(speedup(before, after), 2), "keys_before": _sums(apart)["keys"], "keys_after": _sums(together)["keys"], "bytes_before": _sums(apart)["bytes"], "bytes_after": _sums(together)["bytes"]}
        release(spark, g.vertices, g.edges, placement)


def colocation(spark: SparkSession, root: str, graphs_of=(("sf0.001", 6), ("sf0.1", 24)), threads=(1, 2, 3, 6), algorithms=ALGORITHMS, rounds: int = ROUNDS) -> Iterator[Row]:
    """Seconds, memory and messages as functions take more partitions."""
    for sf, p in graphs_of:
        g = load(spark, root, sf, "basket")
        placement = place(spark, g, p)
        memory = {r.threads: r.bytes for r in baselines.ablate_colocation(spark, g, p, threads).collect()}
        for algorithm in algorithms:
            first = None
            for t in threads:
                result, seconds = _store(spark, g, algorithm, rounds, placement=placement, partitions=p, threads=t)
                first = first or seconds
                yield {"graph": f"basket@{sf}", "p": p, "algorithm": algorithm, "threads": t, "run_s": round(seconds, 2), "speedup": round(speedup(first, seconds), 2), "memory_bytes": memory[t], "memory_saving": round(reduction(memory[threads[0]], memory[t]), 3)} | _sums(result)
        release(spark, g.vertices, g.edges, placement)


def activation(spark: SparkSession, root: str, graphs_of=(("sf0.001", "basket", 6), ("sf0.001", "copurchase_sparse", 6), ("sf0.001", "event_chain", 6), ("sf0.1", "basket", 24)), thresholds=(None, 0, 1, 2, 4), algorithms=("bfs", "cdlp", "wcc"), rounds: int = ROUNDS) -> Iterator[Row]:
    """Seconds and arcs that are looked at, by the superstep from which only active vertices are."""
    for sf, name, p in graphs_of:
        g = load(spark, root, sf, name)
        placement = place(spark, g, p)
        for algorithm in algorithms:
            for start in thresholds:
                result, seconds = _store(spark, g, algorithm, rounds, placement=placement, partitions=p, activate_from=start)
                yield {"graph": f"{name}@{sf}", "p": p, "algorithm": algorithm, "activate_from": start, "run_s": round(seconds, 2), "supersteps": len(result.history)} | {n: sum(h[n] for h in result.history) for n in ("arcs_scanned", "active")}
        release(spark, g.vertices, g.edges, placement)


def claims(spark: SparkSession, root: str, sf: str = "sf0.001", rounds: int = ROUNDS) -> Iterator[Row]:
    """What is reported, beside our own ratio on the stand-in graph; nothing is asserted."""
    g = load(spark, root, sf, "copurchase")
    p = 5
    placement = place(spark, g, p)
    times: dict[str, tuple[float, float, JobResult]] = {}
    for algorithm in ALGORITHMS:
        kv = timed(lambda: run_baseline(spark, "per_vertex_kv", g, algorithm, partitions=p, **options(algorithm, g, rounds)))[1]
        result, ours = _store(spark, g, algorithm, rounds, placement=placement, partitions=p)
        times[algorithm] = (kv, ours, result)
    ratio = {a: round(speedup(kv, ours), 2) for a, (kv, ours, _) in times.items()}
    yield {"metric": "speedup over the per-vertex store, least", "paper": ">= 12", "ours": min(ratio.values())}
    yield {"metric": "speedup over the per-vertex store, CDLP", "paper": "127", "ours": ratio["cdlp"]}
    yield {"metric": "speedup, one 768 MB function, BFS / PageRank", "paper": "9 / > 48", "ours": f"{ratio['bfs']} / {ratio['pagerank']}"}
    one = {a: _store(spark, g, a, rounds, placement=placement, partitions=p, max_worker=1)[0] for a in ("wcc", "pagerank")}
    for a, paper in (("wcc", "96.8 %"), ("pagerank", "98.8 %")):
        spent = max(x[4] for x in one[a].worked) - min(x[3] for x in one[a].worked)
        yield {"metric": f"resources saved by one rotating function, {a}", "paper": paper, "ours": f"{100 * saving(times[a][0] * p, spent):.1f} %"}
    (apart, _), (together, _) = (_store(spark, g, "pagerank", rounds, placement=placement, partitions=p, aggregate=x) for x in (False, True))
    yield {"metric": "keys per superstep, per vertex -> per pair of partitions", "paper": "O(v) -> O(p)", "ours": f"{apart.history[0]['keys']} -> {together.history[0]['keys']}"}
    memory = {r.threads: r.bytes for r in baselines.ablate_colocation(spark, load(spark, root, sf, "basket"), 6, (1, 6)).collect()}
    yield {"metric": "memory saved by six partitions to a function", "paper": "53.2 - 55.6 %", "ours": f"{100 * reduction(memory[1], memory[6]):.1f} %"}


WORKLOADS = {
    "runtime": runtime,
    "worker_caps": worker_caps,
    "partition_counts": partition_counts,
    "cloud_cost": cloud_cost,
    "scale_out": scale_out,
    "key_aggregation": key_aggregation,
    "colocation": colocation,
    "activation": activation,
    "claims": claims,
}
#: Smaller arguments by workload, for a look at the tables.
QUICK: dict[str, Row] = {
    "runtime": {"sizes": GRAPHS[1:2], "algorithms": ("wcc",), "rounds": 2},
    "worker_caps": {"names": ("supply",), "p": 2, "algorithms": ("bfs",), "rounds": 2},
    "partition_counts": {"sf": "sf0.001", "counts": (2, 4), "algorithms": ("pagerank",), "repeats": 2, "rounds": 2},
    "cloud_cost": {"algorithms": ("bfs",), "rounds": 2},
    "scale_out": {"graphs_of": (("sf0.001", "event_session", 32),), "threads": 16, "algorithms": ("bfs",), "rounds": 2},
    "key_aggregation": {"graphs_of": (("sf0.001", "supply"),), "p": 3, "algorithms": ("pagerank",), "rounds": 2},
    "colocation": {"graphs_of": (("sf0.001", 4),), "threads": (1, 4), "algorithms": ("pagerank",), "rounds": 2},
    "activation": {"graphs_of": (("sf0.001", "copurchase_sparse", 2),), "thresholds": (None, 1), "algorithms": ("bfs",), "rounds": 2},
    "claims": {"rounds": 1},
}


def report(spark: SparkSession, root: str, names: tuple[str, ...] = tuple(WORKLOADS), quick: bool = False) -> Iterator[tuple[str, Iterator[Row]]]:
    for name in names:
        yield name, WORKLOADS[name](spark, root, **(QUICK[name] if quick else {}))
