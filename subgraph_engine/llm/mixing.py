"""Mixing sources to target weights by systematic sampling.

A document's expected copies are its source's target over its source's size. Within
each source the expected copies are summed over the documents in order of size; with
one random offset added, a document is emitted once for every integer that its
stretch of the sum crosses. As the offset is drawn evenly from [0, 1), every document
has its expected copies on average, and as neighbours have about the same size, the
words taken stay within about one large document of the target. All documents of a
source have the same expected copies, so the sum before a document is that number
times its rank, which is exact where a running sum of fractions would drift.

Targets: the sources, by code point with null last, weigh 3, 1, 2, repeating, and
share ``share`` times all words; a target stops at ``most`` times its source's size and
the excess is dealt again by weight until none is above. In closed form: sources
in the order of cap over weight reach their cap first, so a running sum over the
(few) sources finds the level at which the rest stop.

Defined results: null texts and texts without words have size 0, are never over
their bound and take part with their place in the order; an empty table gives an
empty result; repeated rows are interchangeable; extra columns are ignored.
"""

from __future__ import annotations

import random

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subgraph_engine.functions.ranking import rank_within
from subgraph_engine.functions.sqltools import fresh
from subgraph_engine.storage import broadcast_if_few, only_result, written_table

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (3.0, 1.0, 2.0)
SEED = 7
#: Copies per document are broadcast up to this many rows, 16 bytes each.
BROADCAST_ROWS = 1_000_000


def offset(seed: int = SEED) -> float:
    """The seeded offset in [0, 1)."""
    return random.Random(seed).random()


def words(text: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")


def targets(sizes: DataFrame, share: float = 1.5, most: float = 2.0, weights: tuple[float, ...] = WEIGHTS) -> DataFrame:
    """source, source_size, target from (source, source_size); one row per source."""
    place = Window.orderBy(F.col("source").asc_nulls_last())
    turn = (F.row_number().over(place) - 1) % len(weights)
    weighed = sizes.withColumn("_w", F.element_at(F.array(*map(F.lit, weights)), (turn + 1).cast("int")))
    weighed = weighed.withColumn("_cap", F.col("source_size") * F.lit(most))
    total = F.sum("source_size").over(Window.partitionBy()) * F.lit(share)
    up = Window.orderBy(F.col("_cap") / F.col("_w"), F.col("source").asc_nulls_last())
    filled = F.coalesce(F.sum("_cap").over(up.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    open_weight = F.sum("_w").over(up.rowsBetween(0, Window.unboundedFollowing))
    levels = weighed.withColumns({"_level": (total - filled) / open_weight, "_turn": F.row_number().over(up)})
    # capped while the level offered to it and all after it is above its cap
    capped = F.col("_level") * F.col("_w") >= F.col("_cap")
    level = F.min(F.when(~capped, F.struct("_turn", "_level"))).over(Window.partitionBy())
    return levels.withColumn("_last", level["_level"]).select(
        "source",
        "source_size",
        F.when(capped | F.col("_last").isNull(), F.col("_cap"))
        .otherwise(F.least(F.col("_cap"), F.col("_last") * F.col("_w")))
        .alias("target"),
    )


def mix(
    spark: SparkSession,
    docs: DataFrame,
    share: float = 1.5,
    most: float = 2.0,
    weights: tuple[float, ...] = WEIGHTS,
    seed: int = SEED,
) -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken: one row per document."""
    return only_result(spark, "mix", lambda: _mixed(spark, docs, share, most, weights, seed))


def _mixed(spark: SparkSession, docs: DataFrame, share: float, most: float, weights: tuple[float, ...], seed: int) -> DataFrame:
    light = written_table(spark, docs.select("doc_id", "source", words().alias("size")), "mix-light")
    sizes = light.groupBy("source").agg(F.sum("size").alias("source_size"))
    goal = targets(sizes, share, most, weights).select(
        F.col("source").alias("_s"), "source_size", "target", _ratio().alias("_ratio")
    )
    tie = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("doc_id").cast("string")))
    order = [F.col("size"), tie, F.col("doc_id")]
    ranked = rank_within(spark, light, "source", order, "_rank", "mix-ranked")
    ranked = ranked.join(goal, F.col("source").eqNullSafe(F.col("_s"))).drop("_s")
    return ranked.withColumn("copies", _copies(F.lit(offset(seed)))).select(
        "doc_id",
        "source",
        "size",
        "source_size",
        "target",
        "copies",
        (F.col("copies") * F.col("size")).alias("taken"),
    )


def _ratio() -> Column:
    return F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))


def _copies(offset: Column) -> Column:
    """Integers in (ratio * rank + offset, ratio * (rank + 1) + offset]."""
    upto = lambda r: F.floor(F.col("_ratio") * r + offset)
    return upto(F.col("_rank") + 1) - upto(F.col("_rank"))


def emit(spark: SparkSession, docs: DataFrame, **options) -> DataFrame:
    """The mixed corpus: each row of ``docs`` as often as it is taken, all columns kept.

    Rows that share an id (null included) are taken equally often, as often as
    the most taken of them.
    """
    doc_id, copies, again = fresh(docs, "mix_id", "mix_copies", "mix_again")
    taken = mix(spark, docs, **options).groupBy(F.col("doc_id").alias(doc_id)).agg(F.max("copies").alias(copies))
    taken = broadcast_if_few(written_table(spark, taken, "mix-taken"), BROADCAST_ROWS)
    rows = docs.join(taken, docs["doc_id"].eqNullSafe(taken[doc_id])).filter(F.col(copies) > 0)
    return rows.withColumn(again, F.explode(F.sequence(F.lit(1), F.col(copies).cast("int")))).select(*docs.columns)
