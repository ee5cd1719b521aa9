"""Preparation: cleaning, degrees, placement of vertices, mirrors and routes."""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.functions.ranking import global_prefix, global_rank
from subgraph_engine.model import GraphSpec

WORD_BITS = 32  # of a bigint: its sign bit stays out of the arithmetic


def prepare(
    name: str,
    edges: DataFrame,
    directed: bool = False,
    weighted: bool = False,
    vertices: DataFrame | None = None,
    dedup: bool = True,
    drop_loops: bool = False,
) -> GraphSpec:
    """A graph from raw edges: one edge per pair, weights summed, kinds fixed."""
    rows = edges.select(F.col("src").cast("long"), F.col("dst").cast("long"), *([F.col("weight").cast("double")] if weighted else []))
    rows = rows.filter("src is not null and dst is not null")
    if drop_loops:
        rows = rows.filter("src <> dst")
    if dedup:
        rows = rows.groupBy("src", "dst").agg(F.sum("weight").alias("weight")) if weighted else rows.distinct()
    ends = rows.select(F.col("src").alias("vid")).unionByName(rows.select(F.col("dst").alias("vid")))
    if vertices is not None:
        ends = ends.unionByName(vertices.select(F.col("vid").cast("long")))
    return GraphSpec(name, directed, weighted, ends.distinct(), rows)


def undirected(g: GraphSpec) -> GraphSpec:
    """The same graph without directions: one edge per unordered pair."""
    low, high = F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")
    rows = g.edges.select(low, high, *(["weight"] if g.weighted else []))
    return prepare(g.name, rows, directed=False, weighted=g.weighted, vertices=g.vertices)


def degrees(g: GraphSpec) -> DataFrame:
    """vid, out_deg, in_deg, degree; vertices without edges have 0."""
    ends = g.edges.select(F.col("src").alias("vid"), F.lit(1).alias("o"), F.lit(0).alias("i"), (F.col("src") == F.col("dst")).cast("int").alias("loop"))
    ends = ends.unionByName(g.edges.select(F.col("dst").alias("vid"), F.lit(0).alias("o"), F.lit(1).alias("i"), F.lit(0).alias("loop")))
    ends = ends.unionByName(g.vertices.select("vid", F.lit(0).alias("o"), F.lit(0).alias("i"), F.lit(0).alias("loop")))
    out, into = F.sum("o").cast("long"), F.sum("i").cast("long")
    if g.directed:
        return ends.groupBy("vid").agg(out.alias("out_deg"), into.alias("in_deg"), (out + into).alias("degree"))
    both = out + into - F.sum("loop").cast("long")
    return ends.groupBy("vid").agg(both.alias("out_deg"), both.alias("in_deg"), both.alias("degree"))


def partition_by_degree(spark: SparkSession, g: GraphSpec, p: int) -> DataFrame:
    """vid, pid: contiguous ranges of ids, cut where the running degree passes each p-th of all."""
    rows = global_prefix(spark, degrees(g).select("vid", "degree"), [F.col("vid")], "degree", "_before", "place-degree")
    total = rows.agg(F.sum("degree")).first()[0] or 0
    pid = F.least(F.lit(p - 1), F.floor(F.col("_before") * p / F.lit(float(total or 1)))).cast("int")
    return rows.select("vid", pid.alias("pid"))


def partition_by_count(spark: SparkSession, g: GraphSpec, p: int) -> DataFrame:
    """vid, pid: contiguous ranges of equally many vertices."""
    ranked = global_rank(spark, g.vertices, [F.col("vid")], "_rank", "place-count")
    total = ranked.count()
    return ranked.select("vid", F.floor(F.col("_rank") * p / F.lit(float(total or 1))).cast("int").alias("pid"))


def partition_by_hash(g: GraphSpec, p: int) -> DataFrame:
    """vid, pid: remainder of the id."""
    return g.vertices.select("vid", F.pmod("vid", F.lit(p)).cast("int").alias("pid"))


def partition_by_column(vertices: DataFrame, column: str) -> DataFrame:
    """vid, pid as the user has them."""
    return vertices.select("vid", F.col(column).cast("int").alias("pid"))


#: The greedy partitioner looks at single vertices above this degree; the rest go by their count.
GREEDY_HEAVY = 100_000


def partition_greedy(spark: SparkSession, g: GraphSpec, p: int, heavy: int = GREEDY_HEAVY) -> DataFrame:
    """vid, pid: largest degree first, each to the lightest partition.

    Only a histogram of degrees reaches the driver (as many rows as there are
    different degrees): vertices of one degree are dealt round, in numbers that
    level the loads, and ranked within their degree to find their place.
    """
    deg = degrees(g).select("vid", "degree")
    histogram = deg.groupBy("degree").agg(F.count(F.lit(1)).alias("n")).orderBy(F.col("degree").desc()).limit(heavy).collect()
    loads = [(0, k) for k in range(p)]
    shares = []
    for degree, n in histogram:
        given = [0] * p
        if n <= 16 * p:
            for _ in range(n):
                load, k = heapq.heappop(loads)
                given[k] += 1
                heapq.heappush(loads, (load + degree, k))
        else:
            each, rest = divmod(n, p)
            order = [k for _, k in sorted(loads)]
            for place, k in enumerate(order):
                given[k] = each + (place < rest)
            loads = [(load + given[k] * degree, k) for load, k in loads]
            heapq.heapify(loads)
        start = 0
        for k, count in enumerate(given):
            if count:
                shares.append((degree, k, start, start + count))
                start += count
    from subgraph_engine.functions.ranking import rank_within

    table = spark.createDataFrame(shares, "d long, pid int, lo long, hi long")
    ranked = rank_within(spark, deg, "degree", [F.col("vid")], "_rank", "place-greedy")
    found = ranked.join(F.broadcast(table), (F.col("degree") == F.col("d")) & (F.col("_rank") >= F.col("lo")) & (F.col("_rank") < F.col("hi")), "left")
    return found.select("vid", F.coalesce("pid", F.pmod("vid", F.lit(p)).cast("int")).alias("pid"))


def remap(spark: SparkSession, placement: DataFrame) -> DataFrame:
    """vid, pid, rid: dense ids, contiguous within each partition."""
    ranked = global_rank(spark, placement, [F.col("pid"), F.col("vid")], "rid", "remap")
    return ranked.select("vid", "pid", F.col("rid").cast("long").alias("rid"))


def per_vertex(rows: DataFrame) -> DataFrame:
    """Rows of single vertices, for a join by exchange.

    Written ids in order take about a byte a row, so by the size of their files ten
    million of them pass for few and would be broadcast through the driver.
    """
    return rows.hint("merge")


def placed_arcs(g: GraphSpec, placement: DataFrame, direction: str = "both") -> DataFrame:
    """pid (of dst, the updated end), src_pid, src, dst (and weight)."""
    src = placement.select(F.col("vid").alias("src"), F.col("pid").alias("src_pid"))
    dst = placement.select(F.col("vid").alias("dst"), "pid")
    return g.arcs(direction).join(per_vertex(src), "src").join(per_vertex(dst), "dst")


def mirrors(g: GraphSpec, placement: DataFrame, direction: str = "both") -> DataFrame:
    """pid, vid, is_inner: the vertices each partition holds, its own and its neighbours'."""
    outer = placed_arcs(g, placement, direction).filter("src_pid <> pid").select("pid", F.col("src").alias("vid"), F.lit(False).alias("is_inner"))
    return placement.select("pid", "vid", F.lit(True).alias("is_inner")).unionByName(outer.distinct())


def adjacency_sets(g: GraphSpec, placement: DataFrame, direction: str = "both") -> DataFrame:
    """vid, dst_pid: the other partitions that hold a copy of the vertex."""
    arcs = placed_arcs(g, placement, direction).filter("src_pid <> pid")
    return arcs.select(F.col("src").alias("vid"), F.col("pid").alias("dst_pid")).distinct()


def routes_from(arcs: DataFrame) -> DataFrame:
    """pid (the vertex's own), vid, dst_pid: the other partitions that read it, from placed arcs."""
    cut = arcs.filter("src_pid <> pid")
    return cut.select(F.col("src_pid").alias("_own"), F.col("src").alias("vid"), F.col("pid").alias("dst_pid")).distinct().withColumnRenamed("_own", "pid")


def bit(pid: str):
    return F.expr(f"shiftleft(1L, {pid} % {WORD_BITS})")


def adjacency_bitmaps(g: GraphSpec, placement: DataFrame, direction: str = "both") -> DataFrame:
    """vid, word, bits: the same sets, 32 partitions to a word; empty words are left out."""
    sets = adjacency_sets(g, placement, direction)
    word = F.floor(F.col("dst_pid") / WORD_BITS).cast("int")
    return sets.groupBy("vid", word.alias("word")).agg(F.bit_or(bit("dst_pid")).alias("bits"))


def partition_quality(g: GraphSpec, placement: DataFrame) -> DataFrame:
    """pid, n_inner, n_outer, degree_sum, arcs, cut_arcs: one row per partition."""
    held = mirrors(g, placement).groupBy("pid").agg(
        F.count_if("is_inner").alias("n_inner"), F.count_if(~F.col("is_inner")).alias("n_outer")
    )
    load = degrees(g).join(per_vertex(placement), "vid").groupBy("pid").agg(F.sum("degree").cast("long").alias("degree_sum"))
    arcs = placed_arcs(g, placement, "out").groupBy("pid").agg(
        F.count(F.lit(1)).alias("arcs"), F.count_if(F.col("src_pid") != F.col("pid")).alias("cut_arcs")
    )
    none = lambda c: F.coalesce(c, F.lit(0).cast("long")).alias(c)
    return held.join(load, "pid", "left").join(arcs, "pid", "left").select(
        "pid", "n_inner", "n_outer", none("degree_sum"), none("arcs"), none("cut_arcs")
    )


def quality_summary(quality: DataFrame) -> DataFrame:
    """partitions, cut_ratio, imbalance (largest over mean degree load), outer_copies: one row."""
    return quality.agg(
        F.count(F.lit(1)).alias("partitions"),
        (F.sum("cut_arcs") / F.sum("arcs")).alias("cut_ratio"),
        (F.max("degree_sum") / F.avg("degree_sum")).alias("imbalance"),
        F.sum("n_outer").alias("outer_copies"),
    )
