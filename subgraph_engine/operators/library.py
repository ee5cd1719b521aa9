"""Operators that users of the engine combine: subgraphs, as-of and range joins, combiners, modes, functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def induced_subgraph(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges whose ends are both among ``vertices`` (vid)."""
    keep = vertices.select("vid")
    return edges.join(keep.withColumnRenamed("vid", "src"), "src", "left_semi").join(keep.withColumnRenamed("vid", "dst"), "dst", "left_semi")


def as_of(left: DataFrame, right: DataFrame, by: list[str], at: str, value: str) -> DataFrame:
    """Each left row with ``value`` of the latest right row of its key at or before its time.

    Both sides go through one window in time order, so no range join is planned:
    a right row passes its value on to the left rows behind it.
    """
    a = left.withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).withColumn("_left", F.lit(True))
    b = right.select(*by, at, F.col(value).alias("_v"))
    for c in left.columns:
        if c not in (*by, at):
            b = b.withColumn(c, F.lit(None).cast(left.schema[c].dataType))
    b = b.withColumn("_left", F.lit(False))
    order = Window.partitionBy(*by).orderBy(F.col(at), F.col("_left")).rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn(value, F.last(F.when(~F.col("_left"), F.col("_v")), ignorenulls=True).over(order))
    return both.filter("_left").drop("_v", "_left")


def range_join(points: DataFrame, spans: DataFrame, at: str, start: str, end: str, width: float, keys: list[str]) -> DataFrame:
    """Points with the spans [start, end) that hold them, as an equi join on buckets of ``width``.

    A span is repeated for every bucket it touches, a point has one bucket.
    """
    bucket = lambda c: F.floor(c / F.lit(width)).cast("long")
    p = points.withColumn("_b", bucket(F.col(at)))
    s = spans.withColumn("_b", F.explode(F.sequence(bucket(F.col(start)), bucket(F.col(end)))))
    return p.join(s, ["_b", *keys]).filter((F.col(at) >= F.col(start)) & (F.col(at) < F.col(end))).drop("_b")


def most_frequent(rows: DataFrame, by: list[str], label: str) -> DataFrame:
    """``by`` and the label that is there most often, the smallest of equals."""
    votes = rows.groupBy(*by, label).agg(F.count(F.lit(1)).alias("_n"))
    return votes.groupBy(*by).agg(F.max_by(label, F.struct("_n", -F.col(label))).alias(label))


def top_per_group(rows: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    return rows.withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).filter(F.col("rank") <= k)


def salted_counts(rows: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """``key`` and its rows, counted in two steps so that no task holds a hot key."""
    part = rows.withColumn("_salt", F.pmod(F.xxhash64(*rows.columns), F.lit(salts)))
    return part.groupBy(key, "_salt").agg(F.count(F.lit(1)).alias("_n")).groupBy(key).agg(F.sum("_n").alias("n"))
