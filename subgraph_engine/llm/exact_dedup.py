"""Exact duplicates by progressive refinement: length, then prefix hash, then full hash.

Texts are equal when they are identical after each run of ASCII white space
(``[\\x20\\x09-\\x0D]+``) is replaced by one space; null counts as empty. Of equal
texts the row with the smallest ``doc_id`` stays (a null id counts as larger
than any number).

Each level only looks at what the level above could not tell apart, and only
the last level hashes whole contents. All counts are grouped aggregates with
map-side partial sums, so a group of copies of any size costs one row per task.

Defined results: an empty table gives an empty result; null and empty texts are
equal; a row that repeats both id and text is one more copy, and exactly one row
of a group is ``kept``; columns besides ``doc_id`` and ``text`` are ignored by
``find_duplicates`` and carried along by ``drop_duplicates``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.functions.sqltools import fresh
from subgraph_engine.storage import broadcast_if_few, release, written_table

PREFIX_CHARS = 256
WHITE_SPACE = r"[\x20\x09-\x0D]+"
KEYS = ["_len", "_head"]
#: Surviving (length, prefix hash) keys and ids to drop are broadcast up to this many, 40 MB.
BROADCAST_KEYS = 1_000_000


def normalised(text: str = "text") -> Column:
    return F.regexp_replace(F.coalesce(F.col(text), F.lit("")), WHITE_SPACE, " ")


def _length() -> Column:
    return F.length("_text")


def _head() -> Column:
    return F.xxhash64(F.substring("_text", 1, PREFIX_CHARS))


def _survivors(rows: DataFrame, keys: list[str]) -> DataFrame:
    return rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("_copies")).filter("_copies > 1").select(*keys)


def find_duplicates(spark: SparkSession, docs: DataFrame, digest: bool = False) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept (and text_sha256).

    ``digest=True`` also returns the SHA-256 of every normalised text, which
    means a full hash of every row; without it only rows that share length and
    prefix hash with another row are hashed whole.
    """
    text = docs.select("doc_id", normalised().alias("_text"))
    extra = ["text_sha256"] if digest else []
    light = text.select(
        "doc_id",
        _length().alias("_len"),
        _head().alias("_head"),
        *([F.sha2("_text", 256).alias("text_sha256")] if digest else []),
    )
    light = written_table(spark, light.withColumn("_row", F.monotonically_increasing_id()), "dedup-light")
    lengths = written_table(spark, _survivors(light, ["_len"]), "dedup-lengths")
    by_length = light.join(broadcast_if_few(lengths, BROADCAST_KEYS), "_len", "left_semi")
    suspects = written_table(spark, _survivors(by_length, KEYS), "dedup-suspects")
    few = broadcast_if_few(suspects, BROADCAST_KEYS)
    if digest:
        whole = light.join(few, KEYS, "left_semi").withColumn("_full", F.col("text_sha256"))
    else:
        again = text.withColumns({"_len": _length(), "_head": _head()})
        whole = again.join(few, KEYS, "left_semi").withColumn("_full", F.sha2("_text", 256)).drop("_text")
        whole = whole.withColumn("_row", F.monotonically_increasing_id())
    whole = written_table(spark, whole, "dedup-whole")
    release(spark, lengths)
    groups = whole.groupBy(*KEYS, "_full").agg(
        F.min(F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), F.col("_row").alias("row"))).alias("_first"),
        F.count(F.lit(1)).alias("group_size"),
    )
    # written, so that the join below has two exchanges of its own and a hot group can be split
    groups = written_table(spark, groups, "dedup-groups")
    told = whole.join(groups, [*KEYS, "_full"]).select(
        "doc_id",
        F.col("_first.id").alias("keep_id"),
        "group_size",
        (F.col("_row") == F.col("_first.row")).alias("kept"),
        *extra,
    )
    alone = light.join(few, KEYS, "left_anti").select(
        "doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"), *extra
    )
    return told.unionByName(alone)


def drop_duplicates(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns.

    Only the ids of rows to drop are joined back (an anti join on a narrow
    table); rows whose id is null take part by their text's full hash.
    """
    found = written_table(spark, find_duplicates(spark, docs), "dedup-found")
    name, full, row = fresh(docs, "dedup_gone", "dedup_full", "dedup_row")
    gone = found.filter(~F.col("kept")).select(F.col("doc_id").alias(name))
    clash = found.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).filter((F.col("n") > 1) | F.col("doc_id").isNull())
    if clash.isEmpty():
        gone = broadcast_if_few(gone, BROADCAST_KEYS)
        return docs.join(gone, docs["doc_id"] == gone[name], "left_anti")
    # ids that repeat or are null cannot name a row: the text's hash does
    keyed = docs.withColumn(full, F.sha2(normalised(), 256)).withColumn(row, F.monotonically_increasing_id())
    keyed = written_table(spark, keyed, "dedup-keyed")
    order = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), F.col(row).alias("row"))
    first = keyed.groupBy(full).agg(F.min(order).alias("_m")).select(F.col("_m.row").alias(name))
    return keyed.join(first, keyed[row] == first[name], "left_semi").select(*docs.columns)
