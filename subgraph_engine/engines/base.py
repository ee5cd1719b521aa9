"""What all engines share: the state table and its change in a superstep.

The state has a row per vertex: pid, vid, value, changed, active, n_arcs,
n_routes, and the program's static columns. It is written after every superstep,
which is the barrier: readers see the old values until all new ones are there,
and a lost executor costs one superstep at most.
"""

from __future__ import annotations

from contextlib import contextmanager
from dataclasses import dataclass, field
from typing import Any

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.model import GraphSpec, JobRequest
from subgraph_engine.prepare import degrees, partition_by_degree, placed_arcs, routes_from
from subgraph_engine.programs.core import Program
from subgraph_engine.storage import drop_path, shared_path, written_table


@contextmanager
def _settings(spark: SparkSession, wanted: dict[str, str]):
    before = {k: spark.conf.get(k, None) for k in wanted}
    for k, v in wanted.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def explicit_layout(spark: SparkSession):
    """Rows are where the engine has put them: no re-planning, no broadcast of arcs by wrong estimates."""
    return _settings(spark, {"spark.sql.adaptive.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1"})


def marked_broadcasts(spark: SparkSession):
    """No broadcast but of what is marked: by their files' sizes, written rows of vertices pass for few."""
    return _settings(spark, {"spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.adaptive.autoBroadcastJoinThreshold": "-1"})


def bytes_by_row(spark: SparkSession):
    """Lists of bytes are read row by row: a batch of the reader is thousands of rows, so whole functions of the store."""
    return _settings(spark, {"spark.sql.parquet.enableNestedColumnVectorizedReader": "false"})


@dataclass
class Engine:
    """A prepared job: graph, program and where vertices are."""

    spark: SparkSession
    graph: GraphSpec
    program: Program
    request: JobRequest
    placement: DataFrame | None = None
    #: whether arcs stay in memory from superstep to superstep
    pinned: bool = True
    totals: dict[str, Any] = field(default_factory=dict, init=False)
    changed_share: float = field(default=1.0, init=False)
    _paths: list[str] = field(default_factory=list, init=False)
    on_close: list[Any] = field(default_factory=list, init=False)
    worked: list[tuple[int, int, int, float, float]] = field(default_factory=list, init=False)

    needs_routes = True

    def prepare(self) -> DataFrame:
        """Writes placement, arcs and routes; returns the state before superstep 0."""
        spark, p, program = self.spark, self.request.partitions, self.program
        if self.placement is None:
            self.placement = partition_by_degree(spark, self.graph, p)
        self.placement = written_table(spark, self.placement, "job-placement")
        arcs = placed_arcs(self.graph, self.placement, program.direction)
        deg = None
        if "out_deg" in program.arc_columns or "sink" in program.static_columns:
            deg = written_table(spark, degrees(self.graph).select("vid", "out_deg"), "job-degrees")
        if "out_deg" in program.arc_columns:
            arcs = arcs.join(deg.withColumnRenamed("vid", "src"), "src")
        if "out_weight" in program.arc_columns:
            arcs = arcs.join(self.graph.arcs(program.direction).groupBy("src").agg(F.sum("weight").alias("out_weight")), "src")
        columns = ["pid", "src_pid", "src", "dst", *program.arc_columns]
        self.arcs_path = shared_path(spark, "job-arcs")
        arcs = arcs.select(*columns)
        arcs.repartition(p, "pid").write.partitionBy("pid").option("compression", "zstd").parquet(self.arcs_path)
        self.arcs = spark.read.schema(arcs.schema).parquet(self.arcs_path).select(*columns)
        self.n_arcs = self.arcs.count()
        state = self.placement.withColumn("vid", F.col("vid").cast("long"))
        held = self.arcs.groupBy(F.col("dst").alias("vid")).agg(F.count(F.lit(1)).alias("n_arcs"))
        state = state.join(held, "vid", "left")
        if self.needs_routes:
            self.routes = written_table(spark, routes_from(self.arcs), "job-routes")
            sent = self.routes.groupBy("vid").agg(F.count(F.lit(1)).alias("n_routes"))
            state = state.join(sent, "vid", "left")
        else:
            state = state.withColumn("n_routes", F.lit(0).cast("long"))
        if deg is not None:
            state = state.join(deg, "vid", "left")
        self.n_vertices = self.placement.count()
        state = state.withColumns(program.static(self.n_vertices)) if program.static_columns else state
        none = lambda c: F.coalesce(c, F.lit(0).cast("long")).alias(c)
        state = state.withColumn("value", program.first_value().cast(program.value_type)).withColumn("changed", program.first_changed())
        state = state.select("pid", "vid", "value", "changed", F.lit(True).alias("active"), none("n_arcs"), none("n_routes"), *program.static_columns)
        self._load()
        state = self._written(state.withColumn("old", F.col("value")))[0]
        return state

    def _load(self) -> None:
        """Hook: what pinned workers keep."""

    def superstep(self, k: int, state: DataFrame) -> tuple[DataFrame, dict[str, Any]]:
        """The next state, and what was counted on the way."""
        with explicit_layout(self.spark):
            new, counted = self._written(self.advance(k, state))
        self.changed_share = counted["changed"] / max(1, counted["vertices"])
        return new, counted

    def advance(self, k: int, state: DataFrame, pids: list[int] | None = None) -> DataFrame:
        """The next state of the partitions ``pids`` (all when None)."""
        got = self.gather(k, state, pids)
        own = self.own(state, pids)
        new = own.join(got, ["pid", "vid"], "left")
        if not self.program.incremental or not self.activated(k):
            new = new.withColumn("_seen", F.lit(True))
        else:
            new = new.withColumn("_seen", F.coalesce("_seen", F.lit(False)))
        value = F.when(F.col("_seen"), self.program.apply(self.totals)).otherwise(F.col("value"))
        new = new.withColumn("_new", value.cast(self.program.value_type))
        return new.select(
            "pid", "vid", F.col("_new").alias("value"), (F.col("_new") != F.col("value")).alias("changed"), F.col("_seen").alias("active"),
            "n_arcs", "n_routes", *self.program.static_columns, F.col("value").alias("old"),
        )

    def own(self, state: DataFrame, pids: list[int] | None) -> DataFrame:
        state = state.drop("old", "active")
        return state.filter(F.col("pid").isin(*pids)) if pids is not None else state

    def activated(self, k: int) -> bool:
        """Whether superstep k computes only vertices that changed or saw a change."""
        policy = self.request
        if policy.activate_from is not None and k >= policy.activate_from:
            return True
        return policy.activate_below is not None and k > 0 and self.changed_share < policy.activate_below

    def gather(self, k: int, state: DataFrame, pids: list[int] | None) -> DataFrame:
        """pid, vid, got, and _seen where only active vertices are computed."""
        raise NotImplementedError

    def _written(self, new: DataFrame, path: str | None = None, mode: str = "errorifexists") -> tuple[DataFrame, dict[str, Any]]:
        watch = Observation()
        counts = {
            "vertices": F.count(F.lit(1)),
            "changed": F.count_if("changed"),
            "active": F.count_if("active"),
            "arcs_scanned": F.sum(F.when(F.col("active"), F.col("n_arcs")).otherwise(0)),
            "messages": F.sum(F.when(F.col("changed") | F.lit(not self.program.incremental), F.col("n_routes")).otherwise(0)),
            **self.program.totals(),
        }
        path = path or shared_path(self.spark, "job-state")
        new.observe(watch, *(c.alias(n) for n, c in counts.items())).write.mode(mode).option("compression", "zstd").parquet(path)
        metrics = dict(watch.get)
        self.totals = {n: metrics[n] for n in self.program.totals()}
        self._paths.append(path)
        for old in self._paths[:-3]:
            drop_path(self.spark, old)
        self._paths = self._paths[-3:]
        return self.spark.read.schema(new.schema).parquet(path), metrics

    def values(self, state: DataFrame) -> DataFrame:
        """vid, value after the last superstep."""
        return state.select("vid", "value")

    def close(self) -> None:
        """Frees what pinned workers keep."""
        for stop in self.on_close:
            stop()
