"""Functions and views that make graphs and payloads usable from SQL.

``register`` adds to a session: ``varint_pack`` and ``varint_unpack`` (sorted ids to
packed gaps and back), ``payload_pack`` (an aggregate of vertices and values into one
body), and the table function ``payload_rows``. ``graph_views`` adds the edges, arcs
and vertices of a graph as views.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from subgraph_engine.blocks import decode_items, encode_items, pack_neighbours, unpack_neighbours
from subgraph_engine.model import GraphSpec

CODEC = "binary"


def _pack(ids: pd.Series) -> pd.Series:
    return ids.map(lambda a: None if a is None else pack_neighbours(np.asarray(a, np.int64)))


def _unpack(bodies: pd.Series) -> pd.Series:
    return bodies.map(lambda b: None if b is None else unpack_neighbours(bytes(b)))


def _payload(vid: pd.Series, value: pd.Series) -> bytes:
    return encode_items([(int(v), int(x)) for v, x in zip(vid, value)], CODEC)


class PayloadRows:
    """vid, value of every item of a payload's body."""

    def eval(self, body: bytes) -> Iterator[tuple[int, int]]:
        yield from decode_items(bytes(body), CODEC) if body else ()


def register(spark: SparkSession) -> None:
    spark.udf.register("varint_pack", pandas_udf(_pack, "binary"))
    spark.udf.register("varint_unpack", pandas_udf(_unpack, "array<bigint>"))
    spark.udf.register("payload_pack", pandas_udf(_payload, "binary"))
    spark.udtf.register("payload_rows", udtf(PayloadRows, returnType="vid bigint, value bigint"))


def graph_views(g: GraphSpec) -> None:
    """``graph_<name>_edges``, ``graph_<name>_arcs`` and ``graph_<name>_vertices``."""
    g.edges.createOrReplaceTempView(f"graph_{g.name}_edges")
    g.arcs("both").createOrReplaceTempView(f"graph_{g.name}_arcs")
    g.vertices.createOrReplaceTempView(f"graph_{g.name}_vertices")
