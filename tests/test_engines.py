"""All engines, modes and optimizations give the same values; hand-made graphs."""

import pytest

from subgraph_engine import algorithms as al
from subgraph_engine import blocks, graphs, messaging, prepare
from subgraph_engine.coordinator import Coordinator, run_job
from subgraph_engine.engines.relational import PartitionEngine
from subgraph_engine.functions.components import star_components
from subgraph_engine.model import UNREACHABLE, JobRequest, UnsupportedAlgorithm
from subgraph_engine.programs import Program, lookup, register
from subgraph_engine.storage import written_table


def graph(spark, edges, vertices=(), directed=False, weighted=False):
    schema = "src long, dst long" + (", weight double" if weighted else "")
    extra = spark.createDataFrame([(v,) for v in vertices], "vid long")
    return prepare.prepare("hand", spark.createDataFrame(edges, schema), directed, weighted, extra)


@pytest.fixture(scope="module")
def bridge(spark):
    """Two triangles with a bridge, a loop, a double edge, two lone vertices, and a path."""
    edges = [(1, 2), (2, 3), (3, 1), (3, 4), (4, 5), (5, 6), (6, 4), (2, 1), (7, 7), (20, 21), (21, 22), (22, 23), (23, 24)]
    return graph(spark, edges, [30, 31])


def python_wcc(g):
    rows = g.edges.collect()
    label = {r.vid: r.vid for r in g.vertices.collect()}
    changed = True
    while changed:
        changed = False
        for r in rows:
            low = min(label[r.src], label[r.dst])
            changed |= label[r.src] != low or label[r.dst] != low
            label[r.src] = label[r.dst] = low
    return label


def python_ranks(g, iters, d=0.85):
    arcs = [(r.src, r.dst) for r in g.arcs("out").collect()]
    vs = [r.vid for r in g.vertices.collect()]
    out = {v: sum(a == v for a, _ in arcs) for v in vs}
    rank = {v: 1 / len(vs) for v in vs}
    for _ in range(iters):
        lost = sum(rank[v] for v in vs if not out[v])
        got = dict.fromkeys(vs, 0.0)
        for a, b in arcs:
            got[b] += rank[a] / out[a]
        rank = {v: (1 - d) / len(vs) + d * (got[v] + lost / len(vs)) for v in vs}
    return rank


def values(result):
    return {r.vid: r.value for r in result.values.collect()}


@pytest.mark.parametrize("how", [
    {}, {"partitions": 1}, {"partitions": 40}, {"activate_from": 0}, {"activate_from": 1}, {"activate_below": 0.5}, {"max_worker": 2}, {"max_worker": 3, "preload": True},
    {"partitions": 6, "threads": 3, "max_worker": 2}, {"engine": "block"}, {"engine": "block", "local_sweeps": "fixpoint"}, {"engine": "vertex_centric"},
    {"engine": "edge_centric"}, {"engine": "shared_memory"}, {"engine": "per_vertex_kv"}, {"engine": "block", "max_worker": 2},
    {"engine": "store"}, {"engine": "store", "threads": 2}, {"engine": "store", "threads": 4}, {"engine": "store", "partitions": 40}, {"engine": "store", "codec": "json"},
    {"engine": "store", "codec": "binary", "batch_rows": 2}, {"engine": "store", "aggregate": False}, {"engine": "store", "activate_from": 1}, {"engine": "store", "activate_from": 0, "threads": 2},
    {"engine": "store", "max_worker": 2}, {"engine": "store", "max_worker": 1, "preload": True}, {"engine": "store", "partitions": 6, "threads": 2, "max_worker": 2, "preload": True},
], ids=str)
def test_components_are_the_same_however_they_are_run(spark, bridge, how):
    result = run_job(spark, bridge, "wcc", **how)
    assert values(result) == python_wcc(bridge)
    assert [h["superstep"] for h in result.history] == list(range(len(result.history)))
    assert all(h["unfinished"] == 0 for h in result.history)
    assert [h["keep_going"] for h in result.history] == [True] * (len(result.history) - 1) + [False]
    assert result.mode == ("rotating" if how.get("max_worker", 99) * how.get("threads", 1) < how.get("partitions", 4) else "pinned")


@pytest.mark.parametrize("engine", ["partition", "block", "store", "vertex_centric", "edge_centric", "shared_memory"])
def test_ranks(spark, bridge, engine):
    got = values(run_job(spark, bridge, "pagerank", engine, iters=5))
    want = python_ranks(bridge, 5)
    assert abs(sum(got.values()) - 1) < 1e-12
    assert all(abs(got[v] - want[v]) < 1e-12 for v in want)


def test_ranks_with_sinks_and_rotation(spark):
    g = graph(spark, [(1, 2), (1, 3), (2, 3), (4, 3)], [9], directed=True)
    want = python_ranks(g, 6)
    for how in ({}, {"max_worker": 1}, {"engine": "store"}, {"engine": "store", "max_worker": 3, "preload": True}):
        got = values(run_job(spark, g, "pagerank", iters=6, **how))
        assert all(abs(got[v] - want[v]) < 1e-12 for v in want)


def test_communities_vote_in_both_directions(spark):
    g = graph(spark, [(1, 3), (3, 1), (2, 3), (5, 3)], directed=True)
    for engine in ("partition", "block", "store"):
        got = values(run_job(spark, g, "cdlp", engine, iters=1))
        assert got == {1: 3, 2: 3, 3: 1, 5: 3}  # the reciprocal arc votes twice for 1
    with pytest.raises(UnsupportedAlgorithm):
        run_job(spark, g, "cdlp", "shared_memory")


def test_activation_does_less_on_long_paths(spark):
    path = graph(spark, [(k, k + 1) for k in range(12)])
    full, lean = (run_job(spark, path, "wcc", activate_from=a) for a in (None, 0))
    assert values(full) == values(lean) == dict.fromkeys(range(13), 0)
    assert [h["changed"] for h in full.history] == [h["changed"] for h in lean.history]
    assert sum(h["arcs_scanned"] for h in lean.history) < sum(h["arcs_scanned"] for h in full.history)
    block = run_job(spark, path, "wcc", "block", local_sweeps="fixpoint")
    assert len(block.history) < len(full.history)


def test_search_and_paths(spark):
    g = graph(spark, [(0, 1, 5.0), (0, 2, 1.0), (2, 1, 1.0), (1, 3, 1.0), (9, 0, 1.0)], directed=True, weighted=True)
    depth = {r.vid: r.depth for r in al.bfs(spark, g, source=0).collect()}
    assert depth == {0: 0, 1: 1, 2: 1, 3: 2, 9: UNREACHABLE}
    assert {r.vid: r.depth for r in al.bfs(spark, g, source=0, max_depth=1, null_unreachable=True).collect()}[3] is None
    for engine in ("partition", "block", "store"):
        dist = values(run_job(spark, g, "sssp", engine, source=0))
        assert dist == {0: 0.0, 2: 1.0, 1: 2.0, 3: 3.0, 9: float("inf")}
    tree = {r.vid: r.parent for r in al.bfs_parents(g, al.bfs(spark, g, source=0)).collect()}
    assert tree == {0: None, 1: 0, 2: 0, 3: 1, 9: None}


def test_empty_and_single(spark):
    empty = graph(spark, [])
    assert run_job(spark, empty, "wcc").values.count() == run_job(spark, empty, "wcc", "store").values.count() == 0
    assert values(run_job(spark, graph(spark, [], [5]), "pagerank", iters=2)) == {5: 1.0}
    assert star_components(spark, empty.edges).count() == 0


def test_star_contraction(spark, bridge):
    got = {r.vid: r.component for r in al.wcc(spark, bridge, "star").collect()}
    assert got == python_wcc(bridge)
    ring = spark.createDataFrame([(k, (k + 1) % 50) for k in range(50)], "src long, dst long")
    assert {r.component for r in star_components(spark, ring).collect()} == {0}


def test_a_new_program_needs_worker_logic_alone(spark, bridge):
    from pyspark.sql import functions as F

    @register("largest")
    class Largest(Program):
        """The largest id of the component."""

        def __init__(self):
            self.name, self.value_type, self.direction, self.incremental = "largest", "bigint", "both", True
            self.local_fixpoint, self.arc_columns, self.static_columns = False, (), ()

        def first_value(self):
            return F.col("vid")

        def combine(self, seen, keys):
            return seen.groupBy(*keys).agg(F.max("msg").alias("got"))

        def apply(self, totals):
            return F.greatest("value", F.coalesce("got", F.col("value")))

    got = values(run_job(spark, bridge, "largest"))
    assert got[1] == 6 and got[20] == 24 and got[30] == 30
    with pytest.raises(ValueError):
        lookup("unknown")


def test_arcs_do_not_move_in_a_superstep(spark, bridge):
    """The only exchanges are of the state and its mirrors; kept arcs and routes are joined where they are."""
    from subgraph_engine.engines.base import explicit_layout
    from subgraph_engine.programs.algorithms import Components

    engine = PartitionEngine(spark, bridge, Components(), JobRequest("wcc", partitions=4))
    state = engine.prepare()
    with explicit_layout(spark):
        plan = engine.advance(0, state)._jdf.queryExecution().executedPlan().toString()
    engine.close()
    outside = [line for line in plan.split("\n") if "Exchange" in line and "InMemory" not in line]
    # cached plans are printed below InMemoryRelation; their own exchange ran once
    moving = [line for line in outside if "REPARTITION_BY" in line or "ENSURE" in line]
    assert "InMemoryTableScan" in plan
    assert not any("ENSURE_REQUIREMENTS" in line for line in moving), plan


def test_partitions_larger_than_memory_are_merged(spark, bridge):
    """Mirrors of a whole partition were held in a hash table, which cannot go to disk; kept arcs are sorted once."""
    from subgraph_engine.engines.base import explicit_layout
    from subgraph_engine.programs.algorithms import Components

    for how in ({}, {"activate_from": 0}):
        engine = PartitionEngine(spark, bridge, Components(), JobRequest("wcc", partitions=4, **how))
        state = engine.prepare()
        with explicit_layout(spark):
            plan = engine.advance(0, state)._jdf.queryExecution().executedPlan().toString()
            kept = engine.kept_arcs.sortWithinPartitions("pid", "src")._jdf.queryExecution().executedPlan().toString()
        engine.close()
        assert "ShuffledHashJoin" not in plan and "SortMergeJoin" in plan
        assert kept.count("Sort [") == 1  # the one below the kept rows


def test_messaging_bounds(spark, sf_dir):
    g = graphs.basket(spark, sf_dir)
    p = 6
    placement = written_table(spark, prepare.partition_by_degree(spark, g, p), "t")
    one, two, three = (messaging.message_counts(g, placement, messaging.worker_table(spark, messaging.colocate(p, t))).first() for t in (1, 2, 3))
    assert one.function_messages == one.partition_messages >= two.function_messages >= three.function_messages
    assert one.partition_messages <= one.cut_arcs * 2 and one.partition_keys <= p * (p - 1)
    keys = messaging.key_accesses(g, placement, "partition").collect()
    assert all(r.accesses <= 2 * (p - 1) for r in keys)
    # contiguous co-location of pairs is the same as half as many partitions
    half = written_table(spark, prepare.partition_by_degree(spark, g, p // 2), "t")
    nested = messaging.message_counts(g, half, messaging.worker_table(spark, messaging.colocate(p // 2, 1))).first()
    assert (nested.partition_messages, nested.partition_keys) == (two.function_messages, two.function_keys)


def test_placements(spark, sf_dir, bridge):
    g = graphs.basket(spark, sf_dir)
    for placement in (prepare.partition_by_degree(spark, g, 8), prepare.partition_greedy(spark, g, 8), prepare.partition_by_hash(g, 8), prepare.partition_by_count(spark, g, 8)):
        placement = written_table(spark, placement, "t")
        assert placement.count() == g.vertices.count() and placement.select("vid").distinct().count() == placement.count()
        assert placement.agg({"pid": "max"}).first()[0] <= 7
    summary = prepare.quality_summary(prepare.partition_quality(g, written_table(spark, prepare.partition_by_degree(spark, g, 8), "t"))).first()
    assert summary.imbalance < 1.1 and 0 < summary.cut_ratio <= 1
    greedy = prepare.quality_summary(prepare.partition_quality(g, written_table(spark, prepare.partition_greedy(spark, g, 8), "t"))).first()
    assert greedy.imbalance < 1.05
    many = prepare.partition_by_degree(spark, bridge, 64)
    assert many.count() == bridge.vertices.count()


def test_what_is_written_is_what_is_counted(spark, sf_dir):
    """Keys and messages in the store against the counts of the scheme, by functions and by vertices."""
    g = graphs.basket(spark, sf_dir)
    placement = written_table(spark, prepare.partition_by_degree(spark, g, 4), "t")
    kept, sizes = {}, {}
    for t in (1, 2, 4):
        how = {"placement": placement, "partitions": 4, "threads": t, "iters": 2}
        want = messaging.message_counts(g, placement, messaging.worker_table(spark, messaging.colocate(4, t))).first()
        rows = run_job(spark, g, "pagerank", "store", **how).history
        assert all((h["messages"], h["keys"]) == (want.function_messages, want.function_keys) for h in rows)
        kept[t] = rows[0]["messages"]
        sizes[t] = rows[0]["bytes"]
    assert kept[1] > kept[2] > kept[4] == 0 and sizes[1] > sizes[2] > sizes[4] == 0
    apart = run_job(spark, g, "pagerank", "store", aggregate=False, placement=placement, partitions=4, iters=1).history[0]
    writes = messaging.key_accesses(g, placement, "vertex").agg({"writes": "sum"}).first()[0]
    assert (apart["messages"], apart["keys"]) == (kept[1], writes)
    bytes_of = {c: run_job(spark, g, "wcc", "store", codec=c, placement=placement, partitions=4, max_supersteps=1).history[0]["bytes"] for c in ("json", "binary", "binary+zstd")}
    assert bytes_of["json"] > bytes_of["binary"] > bytes_of["binary+zstd"]


def test_pinned_store_holds_messages_alone(spark, bridge, monkeypatch):
    """Arrays are written by rotating workers, not by pinned ones, which write them only now and then."""
    from subgraph_engine.engines import store as engine_module

    written = {}
    real = engine_module.ParquetStore.put

    def put(self, superstep, rows, part=0):
        real(self, superstep, rows, part)
        written.setdefault(superstep, set()).update(r.kind for r in self.get("partial", superstep).limit(1).collect())

    monkeypatch.setattr(engine_module.ParquetStore, "put", put)
    run_job(spark, bridge, "wcc", "store")
    assert not any(kinds for step, kinds in written.items() if step >= 0)
    written.clear()
    run_job(spark, bridge, "wcc", "store", max_worker=2)
    assert all(kinds == {"partial"} for kinds in written.values())
    path = graph(spark, [(k, k + 1) for k in range(12)])
    monkeypatch.setattr(engine_module, "COMPACT", 3)
    written.clear()
    assert values(run_job(spark, path, "wcc", "store")) == dict.fromkeys(range(13), 0)
    assert [step for step, kinds in sorted(written.items()) if kinds] == [-1, *range(2, max(written) + 1, 3)]


def test_workers_take_what_is_left(spark, bridge):
    from subgraph_engine.engines.store import StoreEngine
    from subgraph_engine.programs.algorithms import Components

    engine = StoreEngine(spark, bridge, Components(), JobRequest("wcc", partitions=5, max_worker=2), pinned=False)
    state = engine.prepare()
    step = engine.rotation(2, preload=True)
    for k in range(2):
        step(k, state)
        assert sorted(wid for _, wid in engine.order) == list(range(5))
        assert len({worker for worker, _ in engine.order}) <= 2
    engine.close()


def test_scratch_of_a_job_is_deleted(spark, bridge):
    import os

    from subgraph_engine.storage import shared_root

    root = shared_root(spark).removeprefix("file://")
    before = set(os.listdir(root))
    for engine in ("partition", "store"):
        run_job(spark, bridge, "wcc", engine)
    assert {n.split("-")[0] + "-" + n.split("-")[1] for n in set(os.listdir(root)) - before} == {"job-values"}


def test_blocks_round_trip(spark, sf_dir, tmp_path):
    g = graphs.supply(spark, sf_dir)
    placement = written_table(spark, prepare.partition_by_degree(spark, g, 3), "t")
    built = blocks.build_blocks(g, placement)
    blocks.write_blocks(built, f"{tmp_path}/blocks")
    back = blocks.explode_blocks(spark.read.parquet(f"{tmp_path}/blocks"))
    want = prepare.placed_arcs(g, placement).select("pid", "src", "dst")
    assert back.exceptAll(want).count() == want.exceptAll(back).count() == 0
    wave = spark.read.parquet(f"{tmp_path}/blocks").filter("pid in (1)")
    plan = wave._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [" in plan and "pid" in plan.split("PartitionFilters: [")[1].split("]")[0]


def test_kronecker_graph_is_skewed(spark):
    g = graphs.kron(spark, 8, 8)
    top = prepare.degrees(g).agg({"degree": "max", "vid": "count"}).first()
    assert top[0] > 40 and g.edges.count() > 1000


def test_rows_of_bytes_are_not_read_in_batches(spark, bridge):
    """A batch of the vectorized reader had all pieces of a function, which took an executor's heap."""
    from subgraph_engine.engines.base import bytes_by_row
    from subgraph_engine.engines.store import StoreEngine
    from subgraph_engine.programs.algorithms import Components

    name = "spark.sql.parquet.enableNestedColumnVectorizedReader"
    before, seen = spark.conf.get(name), []
    Coordinator(spark, bridge, "store").run(JobRequest("wcc"), until=lambda _: seen.append(spark.conf.get(name)))
    assert set(seen) == {"false"} and spark.conf.get(name) == before
    engine = StoreEngine(spark, bridge, Components(), JobRequest("wcc", partitions=4))
    engine.prepare()
    with bytes_by_row(spark):
        plan = engine.store.get("block", -1)._jdf.queryExecution().executedPlan().toString()
    engine.close()
    assert "Batched: false" in plan


def test_functions_are_packed_in_pieces(spark, sf_dir, monkeypatch):
    """A partition's arcs and a function's array were packed, sent and unpacked whole."""
    from subgraph_engine import graphs
    from subgraph_engine.engines import store
    from subgraph_engine.engines.store import StoreEngine
    from subgraph_engine.programs.algorithms import Components

    g = graphs.basket(spark, sf_dir)
    whole = {n: run_job(spark, g, n, "store", partitions=4, threads=2, **how) for n, how in (("wcc", {"activate_from": 1}), ("pagerank", {"iters": 3}))}
    monkeypatch.setattr(store, "PIECE_ARCS", 100)
    monkeypatch.setattr(store, "PIECE_VERTICES", 50)
    engine = StoreEngine(spark, g, Components(), JobRequest("wcc", partitions=4, threads=2))
    engine.prepare()
    rows = engine.store.get("block", -1).select("x", "y", "n").collect()
    assert len({(r.x, r.y) for r in rows}) == len(rows) > 100 and max(r.n for r in rows) < 400
    assert sum(r.n for r in rows) == engine.n_arcs
    for kind in ("routes", "partial"):
        assert max(r.n for r in engine.store.get(kind, -1).select("n").collect()) < 150
    engine.close()
    for name, how in (("wcc", {"activate_from": 1}), ("pagerank", {"iters": 3})):
        cut = run_job(spark, g, name, "store", partitions=4, threads=2, **how)
        same = lambda a, b: {k: v for k, v in a.items() if k != "bytes"} == {k: v for k, v in b.items() if k != "bytes"}
        assert all(map(same, cut.history, whole[name].history)) and len(cut.history) == len(whole[name].history)
        assert values(cut) == pytest.approx(values(whole[name]))
    assert [b.num_rows for b in store._table([("messages", 0, 0, k, 1, [b"x" * (3 << 20)]) for k in range(4)]).to_batches()] == [2, 2]
