"""Sharding by proportional stratified interleaving.

Rows are shuffled with a seed within each source and get the fractional rank
``(rank + 1/2) / rows of the source``. All rows are then put in the order of that
fraction, which interleaves the sources in proportion, and the order is cut into
runs of equal length: every shard has the mixture of the whole, and the counts
of any two shards differ by one at most (law ``rows``).

Both ranks are distributed (range placement plus one offset per partition), so a
source may hold any share of the rows. The texts are read once, for their size
and checksum; only narrow rows are sorted.

Defined results: a null source is a source of its own, null texts have size 1
and the checksum of the empty string; an empty table gives an empty result; rows that repeat in every
column are told apart by their place only, so they are interchangeable; extra
columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.functions.ranking import global_rank, rank_within
from subgraph_engine.storage import only_result, written_table

SEED = 20_240_917


def shard_rows(spark: SparkSession, docs: DataFrame, shards: int, seed: int = SEED) -> DataFrame:
    """doc_id, source, size, text_crc32, shard (0 ..) and slot (0 .. within its shard)."""
    return only_result(spark, "shards", lambda: _sharded(spark, docs, shards, seed))


def _sharded(spark: SparkSession, docs: DataFrame, shards: int, seed: int) -> DataFrame:
    light = docs.select(
        "doc_id",
        "source",
        (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"),
        F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"),
    )
    light = light.withColumn("_mix", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("doc_id").cast("string"), F.col("text_crc32").cast("string"))))
    light = written_table(spark, light, "shard-light")
    ranked = rank_within(spark, light, "source", [F.col("_mix"), F.col("doc_id")], "_rank", "shard-source")
    counts = light.groupBy(F.col("source").alias("_s")).agg(F.count(F.lit(1)).alias("_rows"))
    fractions = ranked.join(counts, F.col("source").eqNullSafe(F.col("_s"))).withColumn(
        "_at", (F.col("_rank") + F.lit(0.5)) / F.col("_rows")
    )
    fractions = written_table(spark, fractions.drop("_s", "_rank", "_rows"), "shard-fraction")
    order = [F.col("_at"), F.col("source").asc_nulls_last(), F.col("_mix"), F.col("doc_id")]
    placed = global_rank(spark, fractions, order, "_pos", "shard-order")
    total = light.count()
    small, longer = divmod(total, shards)  # the first `longer` shards hold one row more
    edge = longer * (small + 1)
    pos = F.col("_pos")
    shard = F.when(pos < edge, F.floor(pos / (small + 1))).otherwise(
        longer + F.floor((pos - edge) / max(small, 1))
    )
    start = F.col("shard") * small + F.least(F.col("shard"), F.lit(longer))
    return (
        placed.withColumn("shard", shard.cast("int"))
        .withColumn("slot", (pos - start).cast("long"))
        .select("doc_id", "source", "size", "text_crc32", "shard", "slot")
    )


def write_shards(spark: SparkSession, docs: DataFrame, shards: int, path: str, seed: int = SEED) -> None:
    """Writes the documents, one folder per shard, in slot order within it."""
    placed = shard_rows(spark, docs, shards, seed).select(F.col("doc_id").alias("_id"), "shard", "slot")
    rows = docs.join(placed, docs["doc_id"].eqNullSafe(placed["_id"])).drop("_id")
    rows.repartition(shards, "shard").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
