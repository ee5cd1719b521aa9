"""Connected components by alternating star contractions.

Every round rewires edges towards smaller ids: first all larger neighbours of a
vertex to the smallest vertex next to it, then all smaller ones. The diameter
shrinks by a constant factor at least, so long paths take O(log V) rounds where
passing labels along takes as many rounds as the path is long. What is left is a
star for each component, its smallest id in the middle.

Minima are grouped aggregates with partial sums, joins are by a vertex's id and
can be split where an id is hot; no neighbour lists are collected. Each round is
written to the shared folder, which cuts the lineage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.storage import release, written_table


def star_components(spark: SparkSession, edges: DataFrame, label: str = "components") -> DataFrame:
    """vid, component of every vertex that has an edge; ``edges`` has src and dst.

    Directions are ignored, loops and repeats do no harm, components are named by
    their smallest vertex.
    """
    now = edges.select(F.greatest("src", "dst").alias("src"), F.least("src", "dst").alias("dst")).distinct()
    now = written_table(spark, now, label)
    before = None
    while True:
        seen = now.agg(
            F.count(F.lit(1)).alias("n"),
            F.sum(F.xxhash64("src", "dst").cast("decimal(38,0)")).alias("h"),
        ).first()
        if before == tuple(seen):
            break
        before = tuple(seen)
        last, now = now, written_table(spark, _small_star(_large_star(now)), label)
        release(spark, last)
    roots = now.filter("src <> dst").select(F.col("src").alias("vid"), F.col("dst").alias("component"))
    return roots.unionByName(roots.select(F.col("component").alias("vid"), "component").distinct()).unionByName(
        now.filter("src = dst").select(F.col("src").alias("vid"), F.col("dst").alias("component"))
    ).distinct()


def _large_star(edges: DataFrame) -> DataFrame:
    """Larger neighbours of each vertex hang on the smallest of it and all its neighbours."""
    both = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    least = both.groupBy("src").agg(F.least(F.col("src"), F.min("dst")).alias("m"))
    up = both.filter("dst >= src").join(least, "src")
    return up.select(F.col("dst").alias("src"), F.col("m").alias("dst")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Smaller neighbours of each vertex, and the vertex, hang on the smallest of them."""
    least = edges.groupBy("src").agg(F.min("dst").alias("m"))
    joined = edges.join(least, "src")
    down = joined.filter("dst <> m").select(F.col("dst").alias("src"), F.col("m").alias("dst"))
    return down.unionByName(least.select("src", F.col("m").alias("dst"))).distinct()
