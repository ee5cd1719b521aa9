"""A corpus pipeline of the training-data operators, stage after stage.

Each stage takes what the one before it has kept, as a table that was written and
is read again, so a lost executor never costs more than the stage at hand. All
stages but the last return the columns of ``documents``.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from subgraph_engine.llm import bpe, exact_dedup, minhash, mixing, toxicity
from subgraph_engine.storage import written_table

#: Near-duplicates: words in a shingle, least similarity in percent.
SHINGLE_WORDS = 5
SIMILARITY = 80


def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the class-conditional models do not reject."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return toxicity.drop_toxic(spark, docs, toxicity.fit(spark, docs, labels))


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts."""
    return exact_dedup.drop_duplicates(spark, docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates."""
    return minhash.drop_near_duplicates(spark, docs, SHINGLE_WORDS, SIMILARITY)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mixture takes it."""
    return mixing.emit(spark, docs)


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document, and whether they decode to its text."""
    encoded = bpe.encode(docs, bpe.byte_bpe_path())
    ids, n_tokens, decoded = (encoded[c] for c in encoded.columns[-3:])
    text = encoded["text"]
    round_trip = decoded.eqNullSafe(text) | text.isNull() & (decoded == "")
    return encoded.select("doc_id", "lang", "source", "n_chars", n_tokens.alias("n_tokens"), ids.alias("token_ids"), round_trip.alias("round_trip"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", reject_toxic),
    ("exact_dedup", drop_copies),
    ("minhash_dedup", drop_near_copies),
    ("mixing", mix_sources),
    ("bpe", encode_tokens),
]

#: Learned scores and token ids are beyond SQL; tests compare with a brute-force version.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = written_table(spark, stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
