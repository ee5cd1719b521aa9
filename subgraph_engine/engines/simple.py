"""The models that the partition engine is compared with, as strategies of the same job."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.engines.base import Engine
from subgraph_engine.model import UnsupportedAlgorithm
from subgraph_engine.storage import shared_path, written_table

#: A state that is held by every executor may have so many rows, 32 bytes each.
SHARED_STATE_ROWS = 4_000_000


class VertexCentricEngine(Engine):
    """Every vertex sends along its arcs; a combiner merges messages before they move."""

    needs_routes = False

    def gather(self, k: int, state: DataFrame, pids: list[int] | None) -> DataFrame:
        values = state.select(F.col("vid").alias("src"), "value", "changed")
        arcs = self.arcs.select("src", "dst", *self.program.arc_columns)
        return self._combined(arcs.join(values, "src"), state)

    def _combined(self, seen: DataFrame, state: DataFrame) -> DataFrame:
        got = self.program.combine(seen.withColumn("msg", self.program.message()).filter("msg is not null"), ["dst"])
        return got.withColumnRenamed("dst", "vid").join(state.select("vid", "pid"), "vid")

    def activated(self, k: int) -> bool:
        return False


class EdgeCentricEngine(VertexCentricEngine):
    """All arcs stream through every superstep: scatter writes a message per arc, gather reads them."""

    def gather(self, k: int, state: DataFrame, pids: list[int] | None) -> DataFrame:
        values = state.select(F.col("vid").alias("src"), "value")
        arcs = self.arcs.select("src", "dst", *self.program.arc_columns)
        scattered = arcs.join(values, "src").withColumn("msg", self.program.message()).filter("msg is not null").select("dst", "msg")
        stream = written_table(self.spark, scattered, "job-scatter")
        got = self.program.combine(stream, ["dst"])
        return got.withColumnRenamed("dst", "vid").join(state.select("vid", "pid"), "vid")


class SharedMemoryEngine(VertexCentricEngine):
    """Every executor holds the whole state; no message is keyed. It has no label propagation."""

    def prepare(self) -> DataFrame:
        if self.program.name == "cdlp":
            raise UnsupportedAlgorithm("the shared-memory strategy has no label propagation")
        state = super().prepare()
        if self.n_vertices > SHARED_STATE_ROWS:
            raise MemoryError(f"{self.n_vertices} vertices are more than an executor may hold ({SHARED_STATE_ROWS})")
        return state

    def gather(self, k: int, state: DataFrame, pids: list[int] | None) -> DataFrame:
        values = F.broadcast(state.select(F.col("vid").alias("src"), "value", "changed"))  # checked in prepare
        arcs = self.arcs.select("src", "dst", *self.program.arc_columns)
        return self._combined(arcs.join(values, "src"), state)


class PerVertexKeyEngine(VertexCentricEngine):
    """All state in an external store under a key per vertex, as text, written and read in every superstep."""

    def gather(self, k: int, state: DataFrame, pids: list[int] | None) -> DataFrame:
        path = shared_path(self.spark, "job-kv")
        body = F.to_json(F.struct("value", "changed"))
        state.select(F.concat(F.col("vid").cast("string"), F.lit("\t"), body).alias("value")).write.text(path)
        kind = self.program.value_type
        read = self.spark.read.text(path).select(F.split("value", "\t", 2).alias("kv"))
        read = read.select(F.col("kv")[0].cast("long").alias("src"), F.from_json(F.col("kv")[1], f"value {kind}, changed boolean").alias("b"))
        values = read.select("src", "b.value", "b.changed")
        arcs = self.arcs.select("src", "dst", *self.program.arc_columns)
        return self._combined(arcs.join(values, "src"), state)
