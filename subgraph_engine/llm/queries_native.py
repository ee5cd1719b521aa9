"""Queries and SQL of the operators on DataFrame functions alone."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.llm import exact_dedup, mixing, sharding

SHARDS = 16


def op2_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return mixing.mix(spark, docs).select("doc_id", "size", "source_size", "target", "taken")


def op8_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return exact_dedup.find_duplicates(spark, docs, digest=True)


def op9_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    placed = sharding.shard_rows(spark, docs, SHARDS)
    return placed.select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("rows").alias("law"),
        "shard",
        "slot",
        F.lit(None).cast("int").alias("grown_shard"),
    )


QUERIES = {"op2_mixing": op2_mixing, "op8_exact_dedup": op8_exact_dedup, "op9_sharding": op9_sharding}

ORACLE_SQL = {
    "op2_mixing": f"""
WITH doc AS (
  SELECT doc_id, source,
         CAST(coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0) AS BIGINT) AS size
  FROM documents),
src AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size,
         [3.0, 1.0, 2.0][1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3]::DOUBLE AS w
  FROM doc GROUP BY source),
cap AS (SELECT *, source_size * 2.0::DOUBLE AS cap, sum(source_size) OVER () * 1.5::DOUBLE AS total FROM src),
lev AS (
  SELECT *, (total - coalesce(sum(cap) OVER (ORDER BY cap / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
            / sum(w) OVER (ORDER BY cap / w, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS lvl
  FROM cap),
fin AS (
  SELECT *, (SELECT lvl FROM lev WHERE lvl * w < cap ORDER BY cap / w, source NULLS LAST LIMIT 1) AS last FROM lev),
goal AS (
  SELECT source, source_size,
         CASE WHEN lvl * w >= cap OR last IS NULL THEN cap ELSE least(cap, last * w) END AS target
  FROM fin),
ranked AS (
  SELECT d.doc_id, d.source, d.size, g.source_size, g.target,
         CASE WHEN g.source_size > 0 THEN g.target / g.source_size ELSE 0 END AS ratio,
         row_number() OVER (PARTITION BY d.source ORDER BY d.size, md5('{mixing.SEED}:' || d.doc_id), d.doc_id) - 1 AS r
  FROM doc d JOIN goal g ON d.source IS NOT DISTINCT FROM g.source)
SELECT doc_id, size, source_size, target,
       CAST((floor(ratio * (r + 1) + u) - floor(ratio * r + u)) * size AS BIGINT) AS taken
FROM ranked, (SELECT CAST({mixing.offset()!r} AS DOUBLE) AS u) AS o
""",
    "op8_exact_dedup": """
WITH t AS (
  SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]+', ' ', 'g')) AS text_sha256
  FROM documents)
SELECT doc_id, min(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id = min(doc_id) OVER w AS kept, text_sha256
FROM t WINDOW w AS (PARTITION BY text_sha256)
""",
}
