"""Graphs, requests and schemas."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import types as T

UNREACHABLE = 9223372036854775807

EDGE = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])
WEIGHTED_EDGE = T.StructType([*EDGE.fields, T.StructField("weight", T.DoubleType())])
VERTEX = T.StructType([T.StructField("vid", T.LongType())])


class UnsupportedAlgorithm(ValueError):
    """The strategy has no form of this algorithm."""


@dataclass(frozen=True)
class GraphSpec:
    """A graph as prepared: its kind is fixed, its rows are DataFrames.

    Undirected graphs hold each edge once, in either direction; ``arcs`` gives both.
    """

    name: str
    directed: bool
    weighted: bool
    vertices: DataFrame  # vid
    edges: DataFrame  # src, dst (and weight)

    def arcs(self, direction: str = "out") -> DataFrame:
        """Arcs along which values travel: ``out`` as directed, ``both`` with all reversed.

        Undirected graphs give every edge both ways, loops once. ``both`` on a
        directed graph keeps multiplicity: a reciprocal pair counts twice.
        """
        from pyspark.sql import functions as F

        cols = ["src", "dst", *(["weight"] if self.weighted else [])]
        out = self.edges.select(*cols)
        back = self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *cols[2:])
        if not self.directed:
            return out.unionByName(back.filter("src <> dst"))
        return out.unionByName(back) if direction == "both" else out


@dataclass(frozen=True)
class JobRequest:
    """What a user asks for: an algorithm by name, partitions, and a cap on workers."""

    algorithm: str
    partitions: int = 4
    max_worker: int = 1 << 30
    threads: int = 1
    activate_from: int | None = None
    #: activate once the share of changed vertices falls below this
    activate_below: float | None = None
    preload: bool = False
    #: of the store engine: one payload per ordered pair of functions, or a key per vertex
    aggregate: bool = True
    #: of the store engine's messages: json, binary, or binary+zstd
    codec: str = "binary+zstd"
    #: of the store engine: items of one payload row at most
    batch_rows: int = 10_000
    mode: str | None = None
    strict_partition_rule: bool = False
    max_supersteps: int = 10_000
    options: dict[str, Any] = field(default_factory=dict)

    def but(self, **changes: Any) -> "JobRequest":
        return replace(self, **changes)


@dataclass
class JobResult:
    """Vertex values, and one control row for each superstep."""

    values: DataFrame  # vid, value
    history: list[dict[str, Any]]
    mode: str
    request: JobRequest
    #: of rotating workers: worker, superstep, function, start and end in seconds
    worked: list[tuple[int, int, int, float, float]] = field(default_factory=list)
