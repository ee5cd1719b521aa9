"""Edge lists as text (``src dst [weight]`` and one vertex a line), and tabular edges.

Blank lines and lines that begin with ``#`` are left out; a line that does not
parse is an error, not a lost edge.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.model import EDGE, WEIGHTED_EDGE


def _lines(spark: SparkSession, path: str) -> DataFrame:
    lines = spark.read.text(path).select(F.trim("value").alias("line"))
    return lines.filter("line <> '' and line not like '#%'").select(F.split("line", r"\s+").alias("f"))


def read_edge_list(spark: SparkSession, path: str, weighted: bool = False) -> DataFrame:
    columns = [F.col("f")[0].cast("long").alias("src"), F.col("f")[1].cast("long").alias("dst")]
    if weighted:
        columns.append(F.col("f")[2].cast("double").alias("weight"))
    return _lines(spark, path).select(*columns)


def read_vertex_list(spark: SparkSession, path: str) -> DataFrame:
    return _lines(spark, path).select(F.col("f")[0].cast("long").alias("vid"))


def write_edge_list(edges: DataFrame, path: str) -> None:
    columns = [F.col(c).cast("string") for c in ("src", "dst", "weight") if c in edges.columns]
    edges.select(F.concat_ws(" ", *columns).alias("value")).write.text(path)


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", weighted: bool = False, **options: str) -> DataFrame:
    """src, dst (and weight) from csv, json, orc, parquet or a table; the schema is explicit, not inferred."""
    schema = WEIGHTED_EDGE if weighted else EDGE
    if fmt == "table":
        return spark.table(path).select(*schema.names)
    return spark.read.format(fmt).options(**options).schema(schema).load(path)


def write_result(values: DataFrame, path: str, fmt: str = "parquet", **options: str) -> None:
    """Vertex values to parquet, csv, json, orc, or nowhere (``noop``) for timing."""
    writer = values.write.format(fmt).options(**options)
    writer.mode("overwrite").save() if fmt == "noop" else writer.save(path)


def read_result(spark: SparkSession, path: str, fmt: str = "parquet", value_type: str = "bigint") -> DataFrame:
    return spark.read.format(fmt).schema(f"vid bigint, value {value_type}").load(path)
