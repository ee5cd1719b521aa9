"""The algorithms as functions of a graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.coordinator import run_job
from subgraph_engine.functions.components import star_components
from subgraph_engine.model import UNREACHABLE, GraphSpec


def bfs(spark: SparkSession, g: GraphSpec, source: int | None = None, sources: tuple[int, ...] = (), max_depth: int | None = None, null_unreachable: bool = False, **how) -> DataFrame:
    """vid, depth: hops from the nearest source (default: the smallest id)."""
    if not sources:
        sources = (source if source is not None else g.vertices.agg(F.min("vid")).first()[0],)
    got = run_job(spark, g, "bfs", sources=tuple(sources), max_depth=max_depth, **how).values.withColumnRenamed("value", "depth")
    return got.withColumn("depth", F.when(F.col("depth") < UNREACHABLE, F.col("depth"))) if null_unreachable else got


def bfs_parents(g: GraphSpec, depths: DataFrame) -> DataFrame:
    """vid, depth, parent: the smallest neighbour one level up (null for sources and unreachable vertices)."""
    reached = depths.filter(F.col("depth") < UNREACHABLE)
    up = reached.select(F.col("vid").alias("src"), (F.col("depth") + 1).alias("depth"))
    arcs = g.arcs("out").select("src", "dst").join(up, "src").select(F.col("dst").alias("vid"), "depth", "src")
    found = arcs.join(reached, ["vid", "depth"]).groupBy("vid").agg(F.min("src").alias("parent"))
    return depths.join(found, "vid", "left")


def pagerank(spark: SparkSession, g: GraphSpec, **how) -> DataFrame:
    """vid, rank; options damping, iters, tol, restart (ids), weighted."""
    return run_job(spark, g, "pagerank", **how).values.withColumnRenamed("value", "rank")


def cdlp(spark: SparkSession, g: GraphSpec, iters: int = 10, **how) -> DataFrame:
    """vid, label after so many rounds."""
    return run_job(spark, g, "cdlp", iters=iters, **how).values.withColumnRenamed("value", "label")


def wcc(spark: SparkSession, g: GraphSpec, method: str = "superstep", **how) -> DataFrame:
    """vid, component: by supersteps, or by star contraction where paths are long."""
    if method == "star":
        found = star_components(spark, g.edges.select("src", "dst"))
        return g.vertices.join(found, "vid", "left").select("vid", F.coalesce("component", "vid").alias("component"))
    return run_job(spark, g, "wcc", **how).values.withColumnRenamed("value", "component")


def sssp(spark: SparkSession, g: GraphSpec, source: int, **how) -> DataFrame:
    """vid, dist: least sum of weights from the source."""
    return run_job(spark, g, "sssp", source=source, **how).values.withColumnRenamed("value", "dist")


def group_sizes(labels: DataFrame, column: str) -> DataFrame:
    """Members of each component or community."""
    return labels.groupBy(column).agg(F.count(F.lit(1)).alias("members"))


def level_histogram(depths: DataFrame) -> DataFrame:
    """depth, vertices at it; unreachable ones are left out."""
    return depths.filter(F.col("depth") < UNREACHABLE).groupBy("depth").agg(F.count(F.lit(1)).alias("vertices"))


def top_ranked(ranks: DataFrame, k: int) -> DataFrame:
    return ranks.orderBy(F.col("rank").desc(), "vid").limit(k)


def reachable_fraction(depths: DataFrame) -> DataFrame:
    return depths.agg((F.count_if(F.col("depth") < UNREACHABLE) / F.count(F.lit(1))).alias("reachable"))
