"""Messages between partitions: who needs a vertex's value, and how it is keyed.

Three schemes of the same content. ``vertex``: one key per vertex, as without
aggregation. ``partition``: all updates of one partition for another under one
key. ``function``: the same between functions that hold several partitions each,
where a vertex is sent once to a function and addressed to one of its partitions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.functions.sqltools import lowest_bit_index
from subgraph_engine.model import GraphSpec
from subgraph_engine.prepare import WORD_BITS, adjacency_sets, bit, mirrors, per_vertex, placed_arcs


def colocate(p: int, threads: int, layout: str = "contiguous") -> list[tuple[int, int]]:
    """(pid, wid): ``threads`` partitions to a function."""
    functions = -(-p // threads)
    return [(pid, pid // threads if layout == "contiguous" else pid % functions) for pid in range(p)]


def worker_table(spark, layout: list[tuple[int, int]]) -> DataFrame:
    """pid, wid: one row per partition."""
    return spark.createDataFrame(layout, "pid int, wid int")


def worker_bitmaps(workers: DataFrame) -> DataFrame:
    """wid, word, bits: the partitions of each function, 32 to a word."""
    return workers.groupBy("wid", F.floor(F.col("pid") / WORD_BITS).cast("int").alias("word")).agg(F.bit_or(bit("pid")).alias("bits"))


def routes(g: GraphSpec, placement: DataFrame, direction: str = "both") -> DataFrame:
    """src_pid, vid, dst_pid: where a change of the vertex has to go."""
    sets = adjacency_sets(g, placement, direction)
    return sets.join(per_vertex(placement.withColumnRenamed("pid", "src_pid")), "vid").select("src_pid", "vid", "dst_pid")


def outbox(changed: DataFrame, paths: DataFrame) -> DataFrame:
    """src_pid, dst_pid, vid, value: one message per changed vertex and reader."""
    return per_vertex(changed.select("vid", "value")).join(paths, "vid").select("src_pid", "dst_pid", "vid", "value")


def per_vertex_messages(changed: DataFrame, paths: DataFrame) -> DataFrame:
    """The unaggregated baseline: a key per vertex; readers look it up themselves."""
    return per_vertex(changed).join(paths.select("vid").distinct(), "vid", "left_semi").select("vid", "value")


#: Items of one payload row; a larger payload is several rows with a running part.
PAYLOAD_ITEMS = 10_000


def partition_payloads(messages: DataFrame, chunk: int = PAYLOAD_ITEMS) -> DataFrame:
    """src_pid, dst_pid, part, items: all updates from one partition to another.

    Parts are cut by hash of the vertex from the pair's own count, so a payload
    row stays near ``chunk`` items however much a pair exchanges.
    """
    sizes = messages.groupBy("src_pid", "dst_pid").agg(F.count(F.lit(1)).alias("_n"))
    cut = messages.join(sizes, ["src_pid", "dst_pid"])
    part = F.pmod(F.xxhash64("vid"), F.ceil(F.col("_n") / chunk)).cast("int")
    grouped = cut.withColumn("part", part).groupBy("src_pid", "dst_pid", "part")
    return grouped.agg(F.sort_array(F.collect_list(F.struct("vid", "value"))).alias("items"))


def explode_payloads(payloads: DataFrame) -> DataFrame:
    """src_pid, dst_pid, vid, value of every item."""
    return payloads.select("src_pid", "dst_pid", F.explode("items").alias("item")).select("src_pid", "dst_pid", "item.vid", "item.value")


def function_targets(adjacency: DataFrame, workers: DataFrame, home: DataFrame) -> DataFrame:
    """vid, wid, target_pid: each vertex once to every other function that reads it.

    ``adjacency`` has vid, word, bits; ``workers`` wid, word, bits; ``home`` vid, wid.
    The common bits of both maps are the function's partitions that read the vertex;
    the lowest is addressed.
    """
    both = adjacency.join(F.broadcast(workers.withColumnRenamed("bits", "wbits")), "word")
    hit = both.withColumn("common", F.col("bits").bitwiseAND(F.col("wbits"))).filter("common <> 0")
    own = home.select("vid", F.col("wid").alias("own_wid"))
    hit = hit.join(per_vertex(own), "vid").filter("wid <> own_wid")
    pid = (F.col("word") * WORD_BITS + lowest_bit_index("common")).cast("int")
    return hit.groupBy("vid", "wid").agg(F.min(pid).alias("target_pid"))


def function_routes(g: GraphSpec, placement: DataFrame, workers: DataFrame, direction: str = "both") -> DataFrame:
    """src_wid, vid, dst_wid by set arithmetic: the cross-check of the bitmaps."""
    named = workers.withColumnRenamed("pid", "dst_pid").withColumnRenamed("wid", "dst_wid")
    paths = routes(g, placement, direction).join(F.broadcast(named), "dst_pid")
    paths = paths.join(F.broadcast(workers.select(F.col("pid").alias("src_pid"), F.col("wid").alias("src_wid"))), "src_pid")
    return paths.filter("src_wid <> dst_wid").select("src_wid", "vid", "dst_wid").distinct()


def deliver(messages: DataFrame, workers: DataFrame) -> DataFrame:
    """Messages with ``is_local``: those that stay within one function need no store."""
    src = workers.select(F.col("pid").alias("src_pid"), F.col("wid").alias("src_wid"))
    dst = workers.select(F.col("pid").alias("dst_pid"), F.col("wid").alias("dst_wid"))
    both = messages.join(F.broadcast(src), "src_pid").join(F.broadcast(dst), "dst_pid")
    return both.withColumn("is_local", F.col("src_wid") == F.col("dst_wid"))


def unified_mirror(g: GraphSpec, placement: DataFrame, workers: DataFrame) -> DataFrame:
    """wid, vid, is_inner: boundary vertices of co-located partitions are held once."""
    held = mirrors(g, placement).join(F.broadcast(workers), "pid")
    return held.groupBy("wid", "vid").agg(F.bool_or("is_inner").alias("is_inner"))


def message_counts(g: GraphSpec, placement: DataFrame, workers: DataFrame) -> DataFrame:
    """One row: cut arcs, messages per partition and per function, and the keys of both schemes."""
    arcs = placed_arcs(g, placement, "out").agg(
        F.count(F.lit(1)).alias("arcs"), F.count_if(F.col("src_pid") != F.col("pid")).alias("cut_arcs")
    )
    paths = routes(g, placement)
    by_partition = paths.agg(
        F.count(F.lit(1)).alias("partition_messages"), F.count_distinct("src_pid", "dst_pid").alias("partition_keys")
    )
    by_function = function_routes(g, placement, workers).agg(
        F.count(F.lit(1)).alias("function_messages"), F.count_distinct("src_wid", "dst_wid").alias("function_keys")
    )
    return arcs.crossJoin(by_partition).crossJoin(by_function)  # one row each


def key_accesses(g: GraphSpec, placement: DataFrame, scheme: str = "partition", workers: DataFrame | None = None) -> DataFrame:
    """wid, writes, reads, accesses: keys a worker touches in a superstep in which everything changes.

    ``vertex``: writes each own boundary vertex, reads each outer one. The other
    schemes: one key per ordered pair of workers that exchange anything.
    """
    if scheme == "vertex":
        own = routes(g, placement).groupBy(F.col("src_pid").alias("wid")).agg(F.count_distinct("vid").alias("writes"))
        read = mirrors(g, placement).filter(~F.col("is_inner")).groupBy(F.col("pid").alias("wid")).agg(F.count(F.lit(1)).alias("reads"))
    else:
        if scheme == "partition":
            pairs = routes(g, placement).select(F.col("src_pid").alias("a"), F.col("dst_pid").alias("b")).distinct()
        else:
            pairs = function_routes(g, placement, workers).select(F.col("src_wid").alias("a"), F.col("dst_wid").alias("b")).distinct()
        own = pairs.groupBy(F.col("a").alias("wid")).agg(F.count(F.lit(1)).alias("writes"))
        read = pairs.groupBy(F.col("b").alias("wid")).agg(F.count(F.lit(1)).alias("reads"))
    none = lambda c: F.coalesce(c, F.lit(0).cast("long"))
    both = own.join(read, "wid", "full")
    return both.select("wid", none("writes").alias("writes"), none("reads").alias("reads"), (none("writes") + none("reads")).alias("accesses"))
