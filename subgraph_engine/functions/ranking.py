"""Distributed ranks and prefix sums without a single-task window.

``Window.orderBy`` without ``partitionBy`` sends every row to one task, and a
window over a hot key sends a third of them there. Here rows are range-placed
by the whole sort key instead, every partition numbers its own rows, and only
one small row per partition (and group) is summed up front to back.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subgraph_engine.storage import shuffle_width, written_table

_SLOT_MASK = (1 << 33) - 1  # monotonically_increasing_id keeps the row's number below this


def ranged(spark: SparkSession, df: DataFrame, order: list[Column], label: str) -> DataFrame:
    """``df`` written in range order, with its ``_part`` and ``_row`` (from 0) in it.

    ``df`` should be narrow and cheap to compute: it is read twice, once for the
    range bounds. ``order`` should be a total order, so that no key is too large
    for a partition.
    """
    placed = df.repartitionByRange(shuffle_width(spark), *order).sortWithinPartitions(*order)
    return written_table(
        spark,
        placed.select(
            "*",
            F.spark_partition_id().alias("_part"),
            F.monotonically_increasing_id().bitwiseAND(F.lit(_SLOT_MASK)).alias("_row"),
        ),
        label,
    )


def global_rank(
    spark: SparkSession, df: DataFrame, order: list[Column], out: str = "rank", label: str = "ranked"
) -> DataFrame:
    """Adds ``out``: the row's position from 0 in the order of all rows."""
    rows = ranged(spark, df, order, label)
    parts = rows.groupBy("_part").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = parts.select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    # one row for each range partition: bounded by spark.sql.shuffle.partitions
    return (
        rows.join(F.broadcast(offsets), "_part")
        .withColumn(out, F.col("_before") + F.col("_row"))
        .drop("_part", "_row", "_before")
    )


def rank_within(
    spark: SparkSession,
    df: DataFrame,
    group: str,
    order: list[Column],
    out: str = "rank",
    label: str = "ranked",
) -> DataFrame:
    """Adds ``out``: the row's position from 0 within its ``group`` (null is a group).

    A group may hold any share of the rows: it spans as many partitions as its
    rows fill, and the join is by broadcast of one row for each group that a
    partition holds. A partition's rows are in group order, so all partitions
    together hold at most (partitions + groups) such rows.
    """
    rows = ranged(spark, df, [F.col(group).asc_nulls_last(), *order], label)
    cells = rows.groupBy(group, "_part").agg(F.count(F.lit(1)).alias("_n"), F.min("_row").alias("_first"))
    before = Window.partitionBy(group).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = cells.select(
        F.col(group).alias("_g"),
        F.col("_part").alias("_p"),
        (F.coalesce(F.sum("_n").over(before), F.lit(0)) - F.col("_first")).alias("_shift"),
    )
    return (
        rows.join(offsets, (F.col("_part") == F.col("_p")) & F.col(group).eqNullSafe(F.col("_g")))
        .withColumn(out, F.col("_shift") + F.col("_row"))
        .drop("_part", "_row", "_shift", "_g", "_p")
    )


def global_prefix(
    spark: SparkSession, df: DataFrame, order: list[Column], value: str, out: str, label: str = "prefix"
) -> DataFrame:
    """Adds ``out``: the sum of ``value`` over all rows before this one in the order.

    Each range partition sums its own rows; a window within a partition is over
    rows that are already there and in order.
    """
    rows = ranged(spark, df, order, label)
    parts = rows.groupBy("_part").agg(F.sum(value).alias("_sum"))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = parts.select("_part", F.coalesce(F.sum("_sum").over(before), F.lit(0)).alias("_before_part"))
    inside = Window.partitionBy("_part").orderBy("_row").rowsBetween(Window.unboundedPreceding, -1)
    local = rows.withColumn("_local", F.coalesce(F.sum(value).over(inside), F.lit(0)))
    return (
        local.join(F.broadcast(offsets), "_part")
        .withColumn(out, F.col("_before_part") + F.col("_local"))
        .drop("_part", "_row", "_before_part", "_local")
    )
