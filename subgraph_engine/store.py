"""Where a job's data lives between supersteps: blocks, routes, messages, partial results, control rows.

What a function leaves in a superstep is one write, so a reader sees the whole of it
or nothing; folders written by Spark give that by their commit. All that is asked of a
back end is that, and that each kind can be read apart and by function.
"""

from __future__ import annotations

from abc import ABC, abstractmethod

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.storage import drop_path

#: Rows of every kind have these columns; ``wid`` is the function that reads the row.
ROW = "kind string, wid int, x int, y int, n long, data array<binary>"
KINDS = ("block", "routes", "messages", "partial", "control")


class StateStore(ABC):
    """Rows by kind and superstep; ``part`` names one of several writes of a superstep."""

    @abstractmethod
    def put(self, superstep: int, rows: DataFrame, part: int = 0) -> None: ...

    @abstractmethod
    def get(self, kind: str, superstep: int, wids: list[int] | None = None) -> DataFrame: ...

    @abstractmethod
    def drop(self, superstep: int) -> None: ...

    def _chosen(self, rows: DataFrame, kind: str, wids: list[int] | None) -> DataFrame:
        if kind not in KINDS:
            raise ValueError(f"{kind!r} is none of {KINDS}")
        rows = rows.filter(F.col("kind") == kind)
        return rows.filter(F.col("wid").isin(*wids)) if wids is not None else rows


class ParquetStore(StateStore):
    """Folders below a path: a superstep, the function that wrote, and a subfolder per kind and reading function."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def put(self, superstep: int, rows: DataFrame, part: int = 0) -> None:
        writer = rows.write.mode("overwrite").option("compression", "zstd")
        writer.partitionBy("kind", "wid").parquet(f"{self.path}/superstep={superstep}/part={part}")

    def get(self, kind: str, superstep: int, wids: list[int] | None = None) -> DataFrame:
        root = f"{self.path}/superstep={superstep}"
        rows = self.spark.read.schema(ROW + ", part int").option("basePath", root).parquet(root).drop("part")
        return self._chosen(rows, kind, wids).select("kind", "wid", "x", "y", "n", "data")

    def drop(self, superstep: int) -> None:
        drop_path(self.spark, f"{self.path}/superstep={superstep}")


class MemoryStore(StateStore):
    """Persisted DataFrames; what an executor loses is computed again from where it came."""

    def __init__(self) -> None:
        self.tables: dict[int, dict[int, DataFrame]] = {}

    def put(self, superstep: int, rows: DataFrame, part: int = 0) -> None:
        step = self.tables.setdefault(superstep, {})
        old = step.pop(part, None)
        step[part] = rows.persist(StorageLevel.MEMORY_AND_DISK)
        if old is not None:
            old.unpersist()

    def get(self, kind: str, superstep: int, wids: list[int] | None = None) -> DataFrame:
        rows = None
        for part in self.tables[superstep].values():
            rows = part if rows is None else rows.unionByName(part)
        return self._chosen(rows, kind, wids)

    def drop(self, superstep: int) -> None:
        for rows in self.tables.pop(superstep, {}).values():
            rows.unpersist()
