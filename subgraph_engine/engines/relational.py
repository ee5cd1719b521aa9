"""Supersteps over partitions as joins that stay inside them.

Arcs are placed by the partition of their updated end and stay there. A
superstep moves two things: the state to its partitions, and the values of
boundary vertices to the partitions that read them (one row per vertex and reading
partition, however many arcs cross). The join of arcs with these mirrors and the
aggregation of messages need no exchange. Joins merge sorted rows, which go to disk
where a partition is larger than a task's memory; what pinned workers keep is sorted once.
"""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.engines.base import Engine, explicit_layout


class PartitionEngine(Engine):
    """Pinned: arcs and routes are kept by the workers. Rotating: they are read again, a wave at a time."""

    def _load(self) -> None:
        self._kept: list[DataFrame] = []
        if self.pinned:
            # what is cached under adaptive planning has no partitioning that a join could rely on
            with explicit_layout(self.spark):
                self._keep()

    def _keep(self) -> None:
        self.kept_arcs = self._place(self.arcs.drop("src_pid"), keep="src")
        self.kept_routes = self._place(self.routes, keep="vid")

    def _place(self, df: DataFrame, keep: str | None = None) -> DataFrame:
        placed = df.repartitionById(self.request.partitions, "pid")
        if keep:
            placed = placed.sortWithinPartitions("pid", keep).persist(StorageLevel.MEMORY_AND_DISK)
            self._kept.append(placed)
        return placed

    def own(self, state: DataFrame, pids: list[int] | None) -> DataFrame:
        return self._place(super().own(state, pids))

    def mirror(self, state: DataFrame, pids: list[int] | None) -> DataFrame:
        """pid, src, value, changed: every vertex in its own partition and in those that read it."""
        inner = state.select("pid", "vid", "value", "changed")
        routes = self.kept_routes if self.pinned else self._place(self.routes)
        sent = self._place(inner).join(routes.hint("merge"), ["pid", "vid"]).select(F.col("dst_pid").alias("pid"), "vid", "value", "changed")
        both = inner.unionByName(sent)
        if pids is not None:
            both = both.filter(F.col("pid").isin(*pids))
        return self._place(both).withColumnRenamed("vid", "src")

    def wave_arcs(self, pids: list[int] | None) -> DataFrame:
        if self.pinned:
            return self.kept_arcs
        arcs = self.arcs.drop("src_pid")
        return self._place(arcs.filter(F.col("pid").isin(*pids)) if pids is not None else arcs)

    def gather(self, k: int, state: DataFrame, pids: list[int] | None) -> DataFrame:
        program = self.program
        mirror = self.mirror(state, pids)
        arcs = self.wave_arcs(pids)
        selective = program.incremental and self.activated(k)
        if selective:
            touched = arcs.join(mirror.filter("changed").select("pid", "src").hint("merge"), ["pid", "src"], "left_semi")
            touched = touched.select("pid", "dst").distinct()
            arcs = arcs.join(touched.hint("merge"), ["pid", "dst"], "left_semi")
        seen = arcs.join(mirror.hint("merge"), ["pid", "src"]).withColumn("msg", program.message()).filter("msg is not null")
        got = program.combine(seen, ["pid", "dst"]).withColumnRenamed("dst", "vid")
        if selective:
            active = touched.select("pid", F.col("dst").alias("vid"), F.lit(True).alias("_seen"))
            got = active.join(got, ["pid", "vid"], "left")
        return got

    def close(self) -> None:
        for df in getattr(self, "_kept", ()):
            df.unpersist()
        super().close()
