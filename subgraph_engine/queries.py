"""Queries of graphs, preparation, algorithms, modes, messaging, baselines and measures."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine import algorithms as al
from subgraph_engine import baselines, blocks, graphs, measures, messaging, modes, oracle_sql, prepare, timeline
from subgraph_engine.coordinator import run_job
from subgraph_engine.model import GraphSpec
from subgraph_engine.storage import written_table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}
P = 4
PLACES = 6


def query(name: str, sql: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return keep


# graphs

_SHORT = {
    "basket": "basket", "supply": "supply", "patron": "patron", "nation_trade": "nation", "copurchase": "copurchase",
    "copurchase_sparse": "copurchase_sparse", "accounts": "accounts", "event_chain": "chain", "event_session": "session",
    "event_flow": "flow", "user_relay": "relay", "page_links": "pages", "knn": "knn", "doc_dup": "docdup", "dialog": "dialog", "geo": "geo",
}


def _edges(name: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = graphs.BUILDERS[name](spark, sf_dir)
        return g.edges.withColumn("weight", F.round("weight", 6)) if g.weighted else g.edges

    return run


for _name, _short in _SHORT.items():
    query(f"g_{_short}_edges", oracle_sql.edges(_name))(_edges(_name))


# preparation


def _placed(spark: SparkSession, g: GraphSpec, p: int = P) -> DataFrame:
    return written_table(spark, prepare.partition_by_degree(spark, g, p), "placement")


def _with(name: str, tail: str, p: int = P) -> str:
    return f"WITH {oracle_sql.placed(name, p)} {tail}"


@query("prep_degrees", f"WITH {oracle_sql.graph('patron', 'out')}, {oracle_sql.degrees('patron')} SELECT * FROM deg")
def prep_degrees(spark, d):
    return prepare.degrees(graphs.patron(spark, d))


@query(
    "prep_undirect",
    f"SELECT least(src, dst) AS src, greatest(src, dst) AS dst, round(sum(weight), 6) AS weight FROM ({oracle_sql.EDGES['nation_trade']}) GROUP BY ALL",
)
def prep_undirect(spark, d):
    return prepare.undirected(graphs.nation_trade(spark, d)).edges.withColumn("weight", F.round("weight", 6))


@query("prep_place_degree", _with("basket", "SELECT vid, pid FROM pl", 8))
def prep_place_degree(spark, d):
    return prepare.partition_by_degree(spark, graphs.basket(spark, d), 8)


@query(
    "prep_place_count",
    f"WITH {oracle_sql.graph('basket')} SELECT vid, CAST(floor((row_number() OVER (ORDER BY vid) - 1) * 8 / CAST(count(*) OVER () AS DOUBLE)) AS INTEGER) AS pid FROM v",
)
def prep_place_count(spark, d):
    return prepare.partition_by_count(spark, graphs.basket(spark, d), 8)


@query("prep_place_hash", f"WITH {oracle_sql.graph('basket')} SELECT vid, CAST(vid % 8 AS INTEGER) AS pid FROM v")
def prep_place_hash(spark, d):
    return prepare.partition_by_hash(graphs.basket(spark, d), 8)


@query("prep_place_greedy")
def prep_place_greedy(spark, d):
    return prepare.partition_greedy(spark, graphs.basket(spark, d), 8)


@query("prep_remap", _with("basket", "SELECT vid, pid, row_number() OVER (ORDER BY pid, vid) - 1 AS rid FROM pl", 8))
def prep_remap(spark, d):
    return prepare.remap(spark, _placed(spark, graphs.basket(spark, d), 8))


@query("prep_mirrors", _with("basket", "SELECT pid, vid, true AS is_inner FROM pl UNION ALL SELECT DISTINCT pid, src, false FROM x WHERE src_pid <> pid"))
def prep_mirrors(spark, d):
    g = graphs.basket(spark, d)
    return prepare.mirrors(g, _placed(spark, g))


@query("prep_adjacency_sets", _with("basket", "SELECT vid, dst_pid FROM ro", 8))
def prep_adjacency_sets(spark, d):
    g = graphs.basket(spark, d)
    return prepare.adjacency_sets(g, _placed(spark, g, 8))


@query(
    "prep_adjacency_bitmaps",
    _with("basket", "SELECT vid, CAST(dst_pid // 32 AS INTEGER) AS word, bit_or(CAST(1 AS BIGINT) << (dst_pid % 32)) AS bits FROM ro GROUP BY ALL", 40),
)
def prep_adjacency_bitmaps(spark, d):
    g = graphs.basket(spark, d)
    return prepare.adjacency_bitmaps(g, _placed(spark, g, 40))


_QUALITY = """,
q AS (SELECT pid,
  (SELECT count(*) FROM pl WHERE pl.pid = k.pid) AS n_inner,
  (SELECT count(DISTINCT src) FROM x WHERE x.pid = k.pid AND src_pid <> x.pid) AS n_outer,
  (SELECT CAST(sum(degree) AS BIGINT) FROM pl JOIN deg USING (vid) WHERE pl.pid = k.pid) AS degree_sum,
  (SELECT count(*) FROM x WHERE x.pid = k.pid) AS arcs,
  (SELECT count(*) FROM x WHERE x.pid = k.pid AND src_pid <> x.pid) AS cut_arcs
FROM (SELECT DISTINCT pid FROM pl) k) """


@query("prep_quality", _with("basket", _QUALITY + "SELECT * FROM q", 8))
def prep_quality(spark, d):
    g = graphs.basket(spark, d)
    return prepare.partition_quality(g, _placed(spark, g, 8))


_GAPS = "SELECT src, src - coalesce(lag(src) OVER (PARTITION BY dst ORDER BY src), 0) AS gap FROM a"
_VARINT = "1 + " + " + ".join(f"CAST(gap >= {1 << 7 * k} AS INTEGER)" for k in range(1, 9))


@query(
    "prep_codec_sizes",
    f"""WITH {oracle_sql.graph('basket')}, s AS (SELECT *, {_VARINT} AS b FROM ({_GAPS})),
t AS (SELECT count(*) AS n, sum(b) AS gaps, sum(length(CAST(src AS VARCHAR)) + 1) AS txt FROM s)
SELECT 'fixed4' AS codec, n AS n_values, CAST(n * 4 AS BIGINT) AS n_bytes FROM t UNION ALL SELECT 'fixed8', n, n * 8 FROM t
UNION ALL SELECT 'text', n, CAST(txt AS BIGINT) FROM t UNION ALL SELECT 'varint_gaps', n, CAST(gaps AS BIGINT) FROM t""",
)
def prep_codec_sizes(spark, d):
    return blocks.encoded_sizes(graphs.basket(spark, d))


@query("prep_blocks", f"WITH {oracle_sql.placed('geo', P)} SELECT pid, src, dst FROM x")
def prep_blocks(spark, d):
    """Blocks written packed and taken apart again."""
    g = graphs.geo(spark, d)
    return blocks.explode_blocks(blocks.build_blocks(g, _placed(spark, g)))


# algorithms


@query("bfs_basket", oracle_sql.bfs("basket", "0"))
def bfs_basket(spark, d):
    return al.bfs(spark, graphs.basket(spark, d), source=0)


@query("bfs_directed_patron", oracle_sql.bfs("patron", "0"))
def bfs_directed_patron(spark, d):
    return al.bfs(spark, graphs.patron(spark, d), source=0)


@query("bfs_multi", oracle_sql.bfs("knn", "0, 7, 11"))
def bfs_multi(spark, d):
    return al.bfs(spark, graphs.knn(spark, d), sources=(0, 7, 11))


@query("bfs_depth2", oracle_sql.bfs("supply", "0", most=2))
def bfs_depth2(spark, d):
    return al.bfs(spark, graphs.supply(spark, d), source=0, max_depth=2)


@query("bfs_levels", oracle_sql.bfs("basket", "0", "SELECT d AS depth, count(*) AS vertices FROM w GROUP BY d"))
def bfs_levels(spark, d):
    return al.level_histogram(al.bfs(spark, graphs.basket(spark, d), source=0))


@query(
    "bfs_parents",
    oracle_sql.bfs("geo", "0", f"""SELECT v.vid, CAST(coalesce(w.d, {oracle_sql.UNREACHABLE}) AS BIGINT) AS depth,
  (SELECT min(a.src) FROM a JOIN w u ON u.id = a.src WHERE a.dst = v.vid AND u.d + 1 = w.d) AS parent
FROM v LEFT JOIN w ON w.id = v.vid"""),
)
def bfs_parents(spark, d):
    g = graphs.geo(spark, d)
    return al.bfs_parents(g, al.bfs(spark, g, source=0))


def _ranked(spark: SparkSession, g: GraphSpec, **how) -> DataFrame:
    ranks = written_table(spark, al.pagerank(spark, g, **how), "ranks")
    n = ranks.count()
    return ranks.select("vid", F.round(F.col("rank") * n, PLACES).alias("rank"))


@query("pr_basket", oracle_sql.pagerank("basket"))
def pr_basket(spark, d):
    return _ranked(spark, graphs.basket(spark, d))


@query("pr_directed_patron", oracle_sql.pagerank("patron"))
def pr_directed_patron(spark, d):
    return _ranked(spark, graphs.patron(spark, d))


@query("pr_weighted_patron", oracle_sql.pagerank("patron", weighted=True))
def pr_weighted_patron(spark, d):
    return _ranked(spark, graphs.patron(spark, d), weighted=True)


@query("pr_personal", oracle_sql.pagerank("knn", restart="3, 4"))
def pr_personal(spark, d):
    return _ranked(spark, graphs.knn(spark, d), restart=(3, 4))


@query("pr_top20", oracle_sql.pagerank("supply", tail="SELECT vid, round(r * (SELECT count(*) FROM v), 6) AS rank FROM last ORDER BY 2 DESC, 1 LIMIT 20"))
def pr_top20(spark, d):
    return al.top_ranked(_ranked(spark, graphs.supply(spark, d)), 20)


@query("pr_tolerance")
def pr_tolerance(spark, d):
    return _ranked(spark, graphs.geo(spark, d), iters=50, tol=1e-3)


@query("cdlp_copurchase", oracle_sql.cdlp("copurchase"))
def cdlp_copurchase(spark, d):
    return al.cdlp(spark, graphs.copurchase(spark, d))


@query("cdlp_directed_knn", oracle_sql.cdlp("knn"))
def cdlp_directed_knn(spark, d):
    return al.cdlp(spark, graphs.knn(spark, d))


@query("cdlp_sizes", oracle_sql.cdlp("geo", 10, "SELECT l AS label, count(*) AS members FROM last GROUP BY l"))
def cdlp_sizes(spark, d):
    return al.group_sizes(al.cdlp(spark, graphs.geo(spark, d)), "label")


@query("wcc_basket", oracle_sql.wcc("basket"))
def wcc_basket(spark, d):
    return al.wcc(spark, graphs.basket(spark, d))


@query("wcc_geo", oracle_sql.wcc("geo"))
def wcc_geo(spark, d):
    return al.wcc(spark, graphs.geo(spark, d))


for _name, _key in (("copurchase_sparse", "sparse"), ("event_session", "session"), ("event_chain", "chain"), ("doc_dup", "docdup"), ("dialog", "dialog"), ("accounts", "accounts"), ("page_links", "pages")):
    query(f"wcc_{_key}", oracle_sql.wcc(_name))(lambda spark, d, name=_name: al.wcc(spark, graphs.BUILDERS[name](spark, d), "star"))


@query("wcc_sizes", oracle_sql.wcc("copurchase_sparse", "SELECT l AS component, count(*) AS members FROM w GROUP BY l"))
def wcc_sizes(spark, d):
    return al.group_sizes(al.wcc(spark, graphs.copurchase_sparse(spark, d), "star"), "component")


@query("sssp_nation", oracle_sql.sssp("nation_trade", 0))
def sssp_nation(spark, d):
    return al.sssp(spark, graphs.nation_trade(spark, d), 0).withColumn("dist", F.round("dist", 6))


@query("sssp_flow", oracle_sql.sssp("event_flow", 0))
def sssp_flow(spark, d):
    return al.sssp(spark, graphs.event_flow(spark, d), 0).withColumn("dist", F.round("dist", 6))


# modes and the superstep loop


_REQUESTS = "SELECT DISTINCT l_linenumber AS max_worker, CAST(floor(l_quantity) AS INTEGER) AS p, CAST(l_suppkey % 3 + 1 AS INTEGER) AS threads FROM lineitem"


@query("mode_rule", f"SELECT *, CASE WHEN max_worker >= ceil(p / CAST(threads AS DOUBLE)) THEN 'pinned' ELSE 'rotating' END AS mode FROM ({_REQUESTS})")
def mode_rule(spark, d):
    """The mode of each different request that a line stands for: its number, its quantity and its supplier's remainder."""
    lines = graphs.load(spark, d, "lineitem")
    asked = lines.select(F.col("l_linenumber").alias("max_worker"), F.floor("l_quantity").cast("int").alias("p"), (F.pmod("l_suppkey", F.lit(3)) + 1).cast("int").alias("threads")).distinct()
    return asked.withColumn("mode", F.udf(modes.choose_mode, "string")("max_worker", "p", "threads"))


_GEO_WCC = oracle_sql.wcc("geo")
_BASKET_WCC = oracle_sql.wcc("basket")


def _in_store(**how) -> Query:
    """Components of orders and parts by functions that exchange payloads through the store."""
    return lambda spark, d: run_job(spark, graphs.basket(spark, d), "wcc", "store", **how).values.withColumnRenamed("value", "component")


for _name, _how in (
    ("mode_pinned_wcc", {"partitions": 5, "max_worker": 5}), ("mode_rotating_wcc", {"partitions": 5, "max_worker": 2}),
    ("mode_rotating_preload_wcc", {"partitions": 5, "max_worker": 3, "preload": True}), ("store_functions_wcc", {"partitions": 6, "threads": 3}),
    ("store_codec_json_wcc", {"codec": "json"}), ("store_codec_binary_wcc", {"codec": "binary", "batch_rows": 1000}), ("store_vertex_keys_wcc", {"aggregate": False}),
    ("store_activation_wcc", {"activate_from": 2}),
):
    query(_name, _BASKET_WCC)(_in_store(**_how))


@query("store_pagerank", oracle_sql.pagerank("basket"))
def store_pagerank(spark, d):
    return _ranked_values(spark, run_job(spark, graphs.basket(spark, d), "pagerank", "store", threads=2).values)


@query("store_cdlp", oracle_sql.cdlp("knn"))
def store_cdlp(spark, d):
    return run_job(spark, graphs.knn(spark, d), "cdlp", "store").values.withColumnRenamed("value", "label")


@query("mode_rotating_engine_wcc", _GEO_WCC)
def mode_rotating_engine_wcc(spark, d):
    """The partition engine a wave of partitions at a time."""
    return al.wcc(spark, graphs.geo(spark, d), partitions=5, max_worker=3, preload=True)


def _written_sql(t: int) -> str:
    return f"""SELECT {t} AS threads, superstep, count(*) AS messages, count(DISTINCT s * 1000 + t) AS keys
FROM (SELECT DISTINCT src_pid // {t} AS s, vid, dst_pid // {t} AS t FROM ro WHERE src_pid // {t} <> dst_pid // {t}), (VALUES (0), (1)) k(superstep) GROUP BY superstep"""


@query("store_messages_written", _with("basket", " UNION ALL ".join(map(_written_sql, (1, 2)))))
def store_messages_written(spark, d):
    """Messages and keys that were written in two rounds in which every vertex sends, by threads of a function."""
    g, rows = graphs.basket(spark, d), []
    for t in (1, 2):
        rows += [(t, h["superstep"], h["messages"], h["keys"]) for h in run_job(spark, g, "pagerank", "store", partitions=P, threads=t, iters=2).history]
    return spark.createDataFrame(rows, "threads int, superstep int, messages long, keys long")


@query("store_vertex_keys_written", _with("basket", "SELECT count(*) AS messages, count(DISTINCT vid) AS keys FROM ro"))
def store_vertex_keys_written(spark, d):
    """Without aggregation: a key for every boundary vertex."""
    h = run_job(spark, graphs.basket(spark, d), "pagerank", "store", partitions=P, aggregate=False, iters=1).history[0]
    return spark.createDataFrame([(h["messages"], h["keys"])], "messages long, keys long")


_HISTORY = "superstep int, unfinished int, keep_going boolean, finish boolean, changed long, active long, arcs_scanned long, messages long"


def _history(spark: SparkSession, rows: list[dict]) -> DataFrame:
    names = [c.split()[0] for c in _HISTORY.split(", ")]
    return spark.createDataFrame([tuple(r[n] for n in names) for r in rows], _HISTORY)


@query("coord_trace", f"SELECT superstep, changed, 0 AS unfinished, changed > 0 AS keep_going, changed = 0 AS finish FROM ({oracle_sql.wcc_trace('geo', 9)})")
def coord_trace(spark, d):
    rows = run_job(spark, graphs.geo(spark, d), "wcc").history
    return _history(spark, rows).select("superstep", "changed", "unfinished", "keep_going", "finish")


_IO = """, n AS (SELECT (SELECT count(*) FROM x) AS arcs, (SELECT count(*) FROM v) AS vs, (SELECT count(*) FROM ro) AS m)
SELECT mode, superstep, CASE WHEN mode = 'rotating' OR superstep = 0 THEN arcs ELSE 0 END AS blocks_read, CASE WHEN superstep > 0 THEN m ELSE 0 END AS messages_read,
  CASE WHEN mode = 'rotating' AND superstep > 0 THEN vs ELSE 0 END AS partials_read, m AS messages_written, CASE WHEN mode = 'rotating' THEN vs ELSE 0 END AS partials_written
FROM n, (VALUES ('pinned'), ('rotating')) a(mode), (VALUES (0), (1), (2)) b(superstep)"""


@query("mode_io_model", _with("basket", _IO))
def mode_io_model(spark, d):
    """Rows that each mode reads and writes in three rounds in which every vertex sends."""
    g = graphs.basket(spark, d)
    arcs, vertices, rows = g.arcs("both").count(), g.vertices.count(), []
    for mode, cap in (("pinned", P), ("rotating", 2)):
        result = run_job(spark, g, "pagerank", "store", partitions=P, max_worker=cap, iters=3)
        rows += modes.io_model(result.history, arcs, vertices, mode)
    return spark.createDataFrame([tuple(r.values()) for r in rows], "mode string, superstep int, blocks_read long, messages_read long, partials_read long, messages_written long, partials_written long")


# messaging and co-location


def _accesses(name: str, scheme: str, p: int, t: int = 1) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        g = graphs.BUILDERS[name](spark, d)
        workers = messaging.worker_table(spark, messaging.colocate(p, t))
        return messaging.key_accesses(g, _placed(spark, g, p), scheme, workers)

    return run


_ACCESS = """SELECT wid, coalesce(w, 0) AS writes, coalesce(r, 0) AS reads, coalesce(w, 0) + coalesce(r, 0) AS accesses
FROM ({w}) FULL JOIN ({r}) USING (wid)"""
query(
    "key_vertex_scheme",
    _with("basket", _ACCESS.format(w="SELECT src_pid AS wid, count(DISTINCT vid) AS w FROM ro GROUP BY 1", r="SELECT dst_pid AS wid, count(*) AS r FROM ro GROUP BY 1"), 8),
)(_accesses("basket", "vertex", 8))
query(
    "key_partition_scheme",
    _with("basket", _ACCESS.format(w="SELECT src_pid AS wid, count(DISTINCT dst_pid) AS w FROM ro GROUP BY 1", r="SELECT dst_pid AS wid, count(DISTINCT src_pid) AS r FROM ro GROUP BY 1"), 8),
)(_accesses("basket", "partition", 8))
_F2 = "(SELECT DISTINCT src_pid // 2 AS s, vid, dst_pid // 2 AS t FROM ro WHERE src_pid // 2 <> dst_pid // 2)"
query(
    "key_function_scheme",
    _with("basket", _ACCESS.format(w=f"SELECT CAST(s AS INTEGER) AS wid, count(DISTINCT t) AS w FROM {_F2} GROUP BY 1", r=f"SELECT CAST(t AS INTEGER) AS wid, count(DISTINCT s) AS r FROM {_F2} GROUP BY 1"), 8),
)(_accesses("basket", "function", 8, 2))


@query(
    "message_counts",
    _with("basket", f"""SELECT (SELECT count(*) FROM x) AS arcs, (SELECT count(*) FROM x WHERE src_pid <> pid) AS cut_arcs,
  (SELECT count(*) FROM ro) AS partition_messages, (SELECT count(*) FROM (SELECT DISTINCT src_pid, dst_pid FROM ro)) AS partition_keys,
  (SELECT count(*) FROM {_F2}) AS function_messages, (SELECT count(*) FROM (SELECT DISTINCT s, t FROM {_F2})) AS function_keys""", 8),
)
def message_counts(spark, d):
    g = graphs.basket(spark, d)
    return messaging.message_counts(g, _placed(spark, g, 8), messaging.worker_table(spark, messaging.colocate(8, 2)))


@query("payload_roundtrip", _with("geo", "SELECT src_pid, dst_pid, vid, vid AS value FROM ro"))
def payload_roundtrip(spark, d):
    """Messages of all boundary vertices, grouped, encoded, compressed, and back."""
    g = graphs.geo(spark, d)
    placement = _placed(spark, g)
    changed = placement.select("vid", F.col("vid").alias("value"))
    messages = messaging.outbox(changed, messaging.routes(g, placement))
    return blocks.decode_payloads(blocks.encode_payloads(messaging.partition_payloads(messages)))


@query("payload_sizes", _with("geo", "SELECT src_pid, dst_pid, count(*) AS n_items FROM ro GROUP BY ALL"))
def payload_sizes(spark, d):
    g = graphs.geo(spark, d)
    placement = _placed(spark, g)
    messages = messaging.outbox(placement.select("vid", F.col("vid").alias("value")), messaging.routes(g, placement))
    return messaging.partition_payloads(messages).groupBy("src_pid", "dst_pid").agg(F.sum(F.size("items")).alias("n_items"))


@query(
    "mask_targets",
    _with("basket", "SELECT vid, CAST(dst_pid // 3 AS INTEGER) AS wid, min(dst_pid) AS target_pid FROM ro WHERE dst_pid // 3 <> src_pid // 3 GROUP BY ALL", 40),
)
def mask_targets(spark, d):
    g = graphs.basket(spark, d)
    placement = _placed(spark, g, 40)
    workers = messaging.worker_table(spark, messaging.colocate(40, 3))
    home = placement.join(F.broadcast(workers), "pid").select("vid", "wid")
    return messaging.function_targets(prepare.adjacency_bitmaps(g, placement), messaging.worker_bitmaps(workers), home)


@query("mask_example", """WITH w(pid, wid) AS (VALUES (0, 0), (1, 1), (2, 1), (3, 0), (4, 2), (5, 2)),
s AS (SELECT DISTINCT l_partkey AS vid, CAST(l_suppkey % 6 AS INTEGER) AS dst_pid FROM lineitem)
SELECT vid, r.wid, min(dst_pid) AS target_pid FROM s JOIN w r ON r.pid = dst_pid JOIN w o ON o.pid = vid % 6 WHERE r.wid <> o.wid GROUP BY vid, r.wid""")
def mask_example(spark, d):
    """Parts are read by the partitions of their suppliers; three functions hold two of the six each."""
    lines = graphs.load(spark, d, "lineitem")
    sets = lines.select(F.col("l_partkey").alias("vid"), F.pmod("l_suppkey", F.lit(6)).cast("int").alias("dst_pid"))
    maps = sets.groupBy("vid", F.lit(0).alias("word")).agg(F.bit_or(prepare.bit("dst_pid")).alias("bits"))
    workers = messaging.worker_table(spark, [(0, 0), (1, 1), (2, 1), (3, 0), (4, 2), (5, 2)])
    home = sets.select("vid", F.pmod("vid", F.lit(6)).cast("int").alias("pid")).distinct().join(F.broadcast(workers), "pid").select("vid", "wid")  # six rows
    return messaging.function_targets(maps, messaging.worker_bitmaps(workers), home)


@query("toy5_keys", "SELECT * FROM (VALUES (0, CAST(5 AS BIGINT), CAST(2 AS BIGINT)), (1, CAST(5 AS BIGINT), CAST(2 AS BIGINT))) t(wid, keys_before, keys_after)")
def toy5_keys(spark, d):
    """Five vertices over two workers: five keys each before aggregation, two after."""
    g = graphs.toy5(spark)
    placement = g.vertices.select("vid", F.when(F.col("vid") < 2, 0).otherwise(1).alias("pid"))
    before = messaging.key_accesses(g, placement, "vertex").selectExpr("wid", "accesses as keys_before")
    return before.join(messaging.key_accesses(g, placement, "partition").selectExpr("wid", "accesses as keys_after"), "wid")


def _memory_sql(t: int) -> str:
    return f""", g AS (SELECT pid, {_VARINT} AS b FROM (SELECT pid, src - coalesce(lag(src) OVER (PARTITION BY dst ORDER BY src), 0) AS gap FROM x)),
h AS (SELECT pid // {t} AS wid, src AS vid FROM x UNION SELECT pid // {t}, vid FROM pl),
n AS (SELECT h.wid, count(*) FILTER (pl.pid // {t} = h.wid) AS inn, count(*) FILTER (pl.pid // {t} <> h.wid) AS outr FROM h JOIN pl USING (vid) GROUP BY 1),
mem AS (SELECT CAST(wid AS INTEGER) AS wid, inn AS "inner", outr AS "outer", CAST(ab AS BIGINT) AS adjacency_bytes, CAST(ab + 8 * (inn + outr) + 16 * outr AS BIGINT) AS bytes
FROM n JOIN (SELECT pid // {t} AS wid, sum(b) AS ab FROM g GROUP BY 1) USING (wid))"""


@query("colocation_memory", _with("basket", _memory_sql(2) + " SELECT * FROM mem", 8))
def colocation_memory(spark, d):
    g = graphs.basket(spark, d)
    return measures.memory_model(g, _placed(spark, g, 8), messaging.worker_table(spark, messaging.colocate(8, 2)))


@query(
    "colocation_messages",
    _with("basket", " UNION ALL ".join(f"SELECT {t} AS threads, count(*) AS messages FROM (SELECT DISTINCT src_pid // {t}, vid, dst_pid // {t} FROM ro WHERE src_pid // {t} <> dst_pid // {t})" for t in (1, 2, 4)), 8),
)
def colocation_messages(spark, d):
    g = graphs.basket(spark, d)
    placement = _placed(spark, g, 8)
    rows = None
    for t in (1, 2, 4):
        paths = messaging.function_routes(g, placement, messaging.worker_table(spark, messaging.colocate(8, t)))
        row = paths.agg(F.lit(t).alias("threads"), F.count(F.lit(1)).alias("messages"))
        rows = row if rows is None else rows.unionByName(row)
    return rows


@query(
    "colocation_local",
    _with("basket", "SELECT src_pid // 2 = dst_pid // 2 AS is_local, count(*) AS messages FROM ro GROUP BY 1", 8),
)
def colocation_local(spark, d):
    g = graphs.basket(spark, d)
    placement = _placed(spark, g, 8)
    messages = messaging.outbox(placement.select("vid", F.col("vid").alias("value")), messaging.routes(g, placement))
    sent = messaging.deliver(messages, messaging.worker_table(spark, messaging.colocate(8, 2)))
    return sent.groupBy("is_local").agg(F.count(F.lit(1)).alias("messages"))


@query("rescale_same_answer", _GEO_WCC)
def rescale_same_answer(spark, d):
    """Six partitions on two functions instead of six: nothing is placed anew."""
    return al.wcc(spark, graphs.geo(spark, d), partitions=6, threads=3, max_worker=2)


# activation


@query("activation_trace_wcc", oracle_sql.wcc_trace("geo", 9))
def activation_trace_wcc(spark, d):
    rows = run_job(spark, graphs.geo(spark, d), "wcc", activate_from=1).history
    return _history(spark, rows).select("superstep", "changed")


@query("activation_trace_bfs", oracle_sql.bfs("geo", "0", "SELECT CAST(d - 1 AS INTEGER) AS superstep, count(*) AS changed FROM w WHERE d > 0 GROUP BY 1 UNION ALL SELECT CAST(max(d) AS INTEGER), 0 FROM w"))
def activation_trace_bfs(spark, d):
    rows = run_job(spark, graphs.geo(spark, d), "bfs", sources=(0,), activate_from=0).history
    return _history(spark, rows).select("superstep", "changed")


@query("activation_same_answer_cdlp", oracle_sql.cdlp("knn", 6))
def activation_same_answer_cdlp(spark, d):
    return al.cdlp(spark, graphs.knn(spark, d), 6, activate_from=2)


@query("activation_auto_wcc", oracle_sql.wcc("geo"))
def activation_auto_wcc(spark, d):
    return al.wcc(spark, graphs.geo(spark, d), activate_below=0.2)


@query("ablation_activation")
def ablation_activation(spark, d):
    rows = baselines.ablate_activation(spark, graphs.geo(spark, d), "wcc", (None, 0, 2))
    shown = [(r["activate_from"], r["supersteps"], r["arcs_scanned"], r["active"]) for r in rows]
    return spark.createDataFrame(shown, "activate_from int, supersteps int, arcs_scanned long, active long")


# baselines


@query("base_vertex_centric_wcc", _BASKET_WCC)
def base_vertex_centric_wcc(spark, d):
    return baselines.run_baseline(spark, "vertex_centric", graphs.basket(spark, d), "wcc").values.withColumnRenamed("value", "component")


@query("base_edge_centric_pr", oracle_sql.pagerank("copurchase_sparse"))
def base_edge_centric_pr(spark, d):
    return _ranked_values(spark, baselines.run_baseline(spark, "edge_centric", graphs.copurchase_sparse(spark, d), "pagerank").values)


@query("base_per_vertex_kv_bfs", oracle_sql.bfs("basket", "0"))
def base_per_vertex_kv_bfs(spark, d):
    return baselines.run_baseline(spark, "per_vertex_kv", graphs.basket(spark, d), "bfs", sources=(0,)).values.withColumnRenamed("value", "depth")


@query("base_shared_memory_pr", oracle_sql.pagerank("copurchase_sparse"))
def base_shared_memory_pr(spark, d):
    return _ranked_values(spark, baselines.run_baseline(spark, "shared_memory", graphs.copurchase_sparse(spark, d), "pagerank").values)


@query("base_block_wcc", oracle_sql.wcc("copurchase_sparse"))
def base_block_wcc(spark, d):
    """One partition, swept to its fixpoint: as a single shared-memory engine would."""
    g = graphs.copurchase_sparse(spark, d)
    return baselines.run_baseline(spark, "compiled_block", g, "wcc", partitions=1).values.withColumnRenamed("value", "component")


@query("base_block_cdlp", oracle_sql.cdlp("knn", 6))
def base_block_cdlp(spark, d):
    return baselines.run_baseline(spark, "compiled_block", graphs.knn(spark, d), "cdlp", iters=6).values.withColumnRenamed("value", "label")


def _ranked_values(spark: SparkSession, values: DataFrame) -> DataFrame:
    values = written_table(spark, values, "ranks")
    return values.select("vid", F.round(F.col("value") * values.count(), PLACES).alias("rank"))


# cost measures and checks


_RUNS = "SELECT o_orderpriority AS config, count(*) / CAST(100 AS DOUBLE) AS seconds, CAST(128 * (count(*) % 7 + 1) AS DOUBLE) AS memory_mb, CAST(count(DISTINCT o_orderstatus) AS INTEGER) AS functions, count(*) AS requests FROM orders GROUP BY 1"


@query("cost_cloud", f"""SELECT config, memory_mb / 1769 AS vcpu, memory_mb / 128 AS units, seconds * memory_mb / 1024 * functions AS gb_s,
  seconds * memory_mb / 1024 * functions * CAST(0.0000166667 AS DOUBLE) + requests * CAST(0.2 AS DOUBLE) / 1000000 AS usd FROM ({_RUNS})""")
def cost_cloud(spark, d):
    """A request for each order, ten milliseconds each; a configuration for each priority."""
    n = F.count(F.lit(1))
    runs = graphs.load(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("config")).agg(
        (n / 100).alias("seconds"), (128 * (n % 7 + 1)).cast("double").alias("memory_mb"), F.count_distinct("o_orderstatus").cast("int").alias("functions"), n.alias("requests")
    )
    return measures.cost_table(spark, runs)


_WORK_SQL = """SELECT l_linenumber % 3 AS k, l_suppkey % 5 AS i, CAST(count(*) AS DOUBLE) AS load, sum(l_quantity) AS compute, CAST(count(DISTINCT l_partkey) AS DOUBLE) AS message
FROM lineitem GROUP BY ALL"""


def _work(spark: SparkSession, d: str) -> list[timeline.Work]:
    """Three supersteps of five partitions: a second for each line, each part and each piece on them."""
    k, i = F.pmod("l_linenumber", F.lit(3)).alias("k"), F.pmod("l_suppkey", F.lit(5)).alias("i")
    lines = graphs.load(spark, d, "lineitem").groupBy(k, i)
    rows = lines.agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("q"), F.count_distinct("l_partkey").alias("m")).collect()  # fifteen
    found = {(r.k, r.i): (float(r.n), float(r.q or 0), float(r.m)) for r in rows}
    none = (0.0, 0.0, 0.0)
    return [timeline.Work(k, i, *found.get((k, i), none), partial=0.25) for k in range(3) for i in range(5)]


@query("cost_concurrency_pinned", f"""WITH w AS ({_WORK_SQL}), s AS (SELECT k, max(CASE WHEN k = 0 THEN load + compute + message ELSE 2 * message + compute END) AS seconds FROM w GROUP BY k)
SELECT CAST(0 AS DOUBLE) AS t, count(DISTINCT i) AS running FROM w UNION ALL SELECT sum(seconds), CAST(0 AS BIGINT) FROM s""")
def cost_concurrency_pinned(spark, d):
    """Pinned functions live from the first superstep to the last barrier."""
    return timeline.concurrency(timeline.timeline(spark, _work(spark, d), 5, "pinned"))


@query("cost_timeline_rotating")
def cost_timeline_rotating(spark, d):
    return timeline.timeline(spark, _work(spark, d), 3, "rotating", preload=True)


@query("cost_saving", """WITH m AS (SELECT CAST(count(*) AS DOUBLE) AS lines, CAST(count(DISTINCT (l_orderkey, l_suppkey)) AS DOUBLE) AS pairs, CAST(count(DISTINCT l_orderkey) AS DOUBLE) AS orders FROM lineitem)
SELECT round(lines / pairs, 3) AS speedup, round(1 - pairs / lines, 3) AS reduction, round(1 - orders / lines, 3) AS memory_saving FROM m""")
def cost_saving(spark, d):
    """What is saved by a message for each order and supplier, or a copy for each order, instead of one for each line."""
    lines = graphs.load(spark, d, "lineitem")
    m = lines.agg(F.count(F.lit(1)).cast("double").alias("lines"), F.count_distinct("l_orderkey", "l_suppkey").alias("pairs"), F.count_distinct("l_orderkey").alias("orders"))
    lines, pairs, orders = (F.col(c) for c in m.columns)
    row = (measures.speedup(lines, pairs), measures.reduction(lines, pairs), measures.saving(lines, orders))
    return m.select(*(F.round(x, 3).alias(n) for x, n in zip(row, ("speedup", "reduction", "memory_saving"))))


_SWEEP = (2, 4, 8)


def _sweep_sql(p: int) -> str:
    return f"SELECT * FROM ({_with('basket', f'SELECT {p} AS p, (SELECT count(*) FROM x WHERE src_pid <> pid) AS cut_arcs, (SELECT count(*) FROM ro) AS messages, (SELECT count(*) FROM (SELECT DISTINCT src_pid, dst_pid FROM ro)) AS keys', p)})"


@query("cost_partition_sweep", " UNION ALL ".join(_sweep_sql(p) for p in _SWEEP))
def cost_partition_sweep(spark, d):
    """More partitions cut more arcs, send more messages and need more keys."""
    g = graphs.basket(spark, d)
    rows = None
    for p in _SWEEP:
        placement = _placed(spark, g, p)
        arcs = prepare.placed_arcs(g, placement).agg(F.count_if(F.col("src_pid") != F.col("pid")).alias("cut_arcs"))
        sent = messaging.routes(g, placement).agg(F.count(F.lit(1)).alias("messages"), F.count_distinct("src_pid", "dst_pid").alias("keys"))
        row = arcs.crossJoin(sent).select(F.lit(p).alias("p"), "cut_arcs", "messages", "keys")  # one row each
        rows = row if rows is None else rows.unionByName(row)
    return rows


@query("ablation_key_aggregation", _with("basket", f"""SELECT wid, a.accesses AS keys_before, b.accesses AS keys_after FROM
({_ACCESS.format(w="SELECT src_pid AS wid, count(DISTINCT vid) AS w FROM ro GROUP BY 1", r="SELECT dst_pid AS wid, count(*) AS r FROM ro GROUP BY 1")}) a JOIN
({_ACCESS.format(w="SELECT src_pid AS wid, count(DISTINCT dst_pid) AS w FROM ro GROUP BY 1", r="SELECT dst_pid AS wid, count(DISTINCT src_pid) AS r FROM ro GROUP BY 1")}) b USING (wid)""", 6))
def ablation_key_aggregation(spark, d):
    return baselines.ablate_key_aggregation(spark, graphs.basket(spark, d), 6)


def _ablated_sql(t: int) -> str:
    sent = f"(SELECT count(*) FROM (SELECT DISTINCT src_pid // {t}, vid, dst_pid // {t} FROM ro WHERE src_pid // {t} <> dst_pid // {t}))"
    return f"SELECT * FROM ({_with('basket', _memory_sql(t) + f' SELECT {t} AS threads, count(*) AS functions, CAST(sum(bytes) AS BIGINT) AS bytes, {sent} AS messages FROM mem', 6)})"


@query("ablation_colocation", " UNION ALL ".join(map(_ablated_sql, (1, 2, 3, 6))))
def ablation_colocation(spark, d):
    return baselines.ablate_colocation(spark, graphs.basket(spark, d), 6)


def _valid(name: str, sql: str = "SELECT true AS ok, CAST(0 AS BIGINT) AS mismatches"):
    return query(name, sql)


@_valid("valid_equivalence")
def valid_equivalence(spark, d):
    g = graphs.geo(spark, d)
    a = al.wcc(spark, g).withColumnRenamed("component", "value")
    b = al.wcc(spark, g, "star").select("vid", (-F.col("component")).alias("value"))  # other names, same groups
    return measures.validate(a, b, "equivalence")


@_valid("valid_epsilon")
def valid_epsilon(spark, d):
    g = graphs.geo(spark, d)
    a = run_job(spark, g, "pagerank", iters=4).values
    b = run_job(spark, g, "pagerank", "block", iters=4).values
    return measures.validate(a, b, "epsilon")


@_valid("valid_exact")
def valid_exact(spark, d):
    g = graphs.geo(spark, d)
    a = run_job(spark, g, "bfs", sources=(0,)).values
    b = run_job(spark, g, "bfs", "vertex_centric", sources=(0,)).values
    return measures.validate(a, b, "exact")
