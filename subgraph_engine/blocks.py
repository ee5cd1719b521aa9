"""Compact adjacency blocks and message codecs."""

from __future__ import annotations

import json
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subgraph_engine.functions.sqltools import varint_bytes
from subgraph_engine.model import GraphSpec
from subgraph_engine.prepare import placed_arcs

ZSTD_LEVEL = 3


def varint_encode(values: np.ndarray) -> bytes:
    """Non-negative integers, seven bits a byte, low bits first, the last byte below 128."""
    v = np.asarray(values, np.uint64)
    if not len(v):
        return b""
    size = np.ones(len(v), np.int64)
    for k in range(1, 10):
        size += v >= np.uint64(1 << (7 * k))
    out = np.zeros(int(size.sum()), np.uint8)
    start = np.concatenate([[0], np.cumsum(size)[:-1]])
    for k in range(int(size.max())):
        has = size > k
        byte = (v[has] >> np.uint64(7 * k)) & np.uint64(127)
        out[start[has] + k] = byte.astype(np.uint8) | np.where(size[has] > k + 1, 128, 0).astype(np.uint8)
    return out.tobytes()


def varint_decode(data: bytes) -> np.ndarray:
    raw = np.frombuffer(data, np.uint8)
    if not len(raw):
        return np.empty(0, np.int64)
    ends = np.flatnonzero(raw < 128)
    starts = np.concatenate([[0], ends[:-1] + 1])
    place = np.arange(len(raw)) - np.repeat(starts, ends - starts + 1)
    parts = (raw & 127).astype(np.uint64) << (7 * place).astype(np.uint64)
    return np.add.reduceat(parts, starts).astype(np.int64)


def pack_neighbours(ids: np.ndarray) -> bytes:
    """Sorted ids: the first as it is, then the gaps."""
    return varint_encode(np.diff(np.sort(ids), prepend=0))


def unpack_neighbours(data: bytes) -> np.ndarray:
    return np.cumsum(varint_decode(data))


BLOCK = "pid int, vids array<long>, counts array<int>, nbrs binary, weights array<double>"


def build_blocks(g: GraphSpec, placement: DataFrame, direction: str = "both") -> DataFrame:
    """A block per partition: its updated vertices, their numbers of neighbours, and packed neighbour lists.

    A vertex's list starts anew, so the lists of a block can be cut apart by the counts.
    """
    arcs = placed_arcs(g, placement, direction).select("pid", "src", "dst", *(["weight"] if g.weighted else []))

    weighted = g.weighted

    def pack(table: pa.Table) -> pa.Table:
        table = table.sort_by([("dst", "ascending"), ("src", "ascending")])
        dst, src = table.column("dst").to_numpy(), table.column("src").to_numpy()
        vids, starts, counts = np.unique(dst, return_index=True, return_counts=True)
        gaps = np.diff(src, prepend=0)
        gaps[starts] = src[starts]
        weights = [table.column("weight").to_pylist()] if weighted else [None]
        columns = [
            pa.array([table.column("pid")[0].as_py()], pa.int32()),
            pa.array([vids], pa.list_(pa.int64())),
            pa.array([counts.astype(np.int32)], pa.list_(pa.int32())),
            pa.array([varint_encode(gaps)], pa.binary()),
            pa.array(weights, pa.list_(pa.float64())),
        ]
        return pa.Table.from_arrays(columns, ["pid", "vids", "counts", "nbrs", "weights"])

    return arcs.groupBy("pid").applyInArrow(pack, BLOCK)


def read_block(vids: np.ndarray, counts: np.ndarray, nbrs: bytes) -> tuple[np.ndarray, np.ndarray]:
    """src, dst of a block's arcs."""
    gaps = varint_decode(nbrs)
    upto = np.cumsum(gaps)
    starts = np.concatenate([[0], np.cumsum(counts)[:-1]]).astype(np.int64)
    before = np.where(starts > 0, upto[starts - 1], 0)
    return upto - np.repeat(before, counts), np.repeat(vids, counts)


def explode_blocks(blocks: DataFrame) -> DataFrame:
    """pid, src, dst of all blocks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                src, dst = read_block(np.array(row["vids"]), np.array(row["counts"]), row["nbrs"])
                yield pa.RecordBatch.from_arrays([pa.array([row["pid"]] * len(src), pa.int32()), pa.array(src), pa.array(dst)], ["pid", "src", "dst"])

    return blocks.select("pid", "vids", "counts", "nbrs").mapInArrow(run, "pid int, src long, dst long")


def write_blocks(blocks: DataFrame, path: str) -> None:
    """One folder per partition, so that a wave of partitions is read by pruning."""
    blocks.write.partitionBy("pid").option("compression", "zstd").parquet(path)


def encoded_sizes(g: GraphSpec, direction: str = "both") -> DataFrame:
    """codec, n_values, n_bytes of all neighbour lists: 4 and 8 bytes fixed, varint gaps, decimal text."""
    arcs = g.arcs(direction)
    order = Window.partitionBy("dst").orderBy("src")
    gap = F.col("src") - F.coalesce(F.lag("src").over(order), F.lit(0))
    rows = arcs.select("src", gap.alias("gap"))
    total = rows.agg(
        F.count(F.lit(1)).alias("n"),
        F.sum(varint_bytes(F.col("gap"))).alias("gaps"),
        F.sum(F.length(F.col("src").cast("string")) + 1).alias("text"),
    )
    sizes = F.expr("stack(4, 'fixed4', n * 4, 'fixed8', n * 8, 'text', text, 'varint_gaps', gaps) as (codec, n_bytes)")
    return total.select(F.col("n").alias("n_values"), sizes).select("codec", "n_values", F.col("n_bytes").cast("long").alias("n_bytes"))


def encode_items(items: list[tuple[int, float | int]], codec: str) -> bytes:
    """A payload's (vid, value) pairs as ``json``, ``binary`` or ``binary+zstd``."""
    if codec == "json":
        return json.dumps([{"vid": v, "value": x} for v, x in items], separators=(",", ":")).encode()
    items = sorted(items)
    vids = pack_neighbours(np.array([v for v, _ in items], np.int64))
    whole = all(isinstance(x, int) for _, x in items)
    values = np.array([x for _, x in items], "<i8" if whole else "<f8").tobytes()
    body = struct.pack("<BI", whole, len(vids)) + vids + values
    return zstandard.ZstdCompressor(level=ZSTD_LEVEL).compress(body) if codec.endswith("zstd") else body


def decode_items(data: bytes, codec: str) -> list[tuple[int, float | int]]:
    if codec == "json":
        return [(x["vid"], x["value"]) for x in json.loads(data)]
    body = zstandard.ZstdDecompressor().decompress(data) if codec.endswith("zstd") else data
    whole, n = struct.unpack_from("<BI", body)
    vids = unpack_neighbours(body[5 : 5 + n])
    values = np.frombuffer(body[5 + n :], "<i8" if whole else "<f8")
    return list(zip(vids.tolist(), values.tolist()))


def encode_payloads(payloads: DataFrame, codec: str = "binary+zstd") -> DataFrame:
    """src_pid, dst_pid, part, n_items, body of each payload."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            items = [[(x["vid"], x["value"]) for x in row] for row in batch.column("items").to_pylist()]
            bodies = [encode_items(row, codec) for row in items]
            columns = [*batch.columns[:3], pa.array(map(len, items), pa.int32()), pa.array(bodies, pa.binary())]
            yield pa.RecordBatch.from_arrays(columns, ["src_pid", "dst_pid", "part", "n_items", "body"])

    return payloads.select("src_pid", "dst_pid", "part", "items").mapInArrow(run, "src_pid int, dst_pid int, part int, n_items int, body binary")


def decode_payloads(encoded: DataFrame, codec: str = "binary+zstd", value_type: str = "long") -> DataFrame:
    """src_pid, dst_pid, vid, value of every item."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.int64() if value_type == "long" else pa.float64()
        for batch in batches:
            rows = [(a, b, v, x) for a, b, body in zip(*(batch.column(c).to_pylist() for c in ("src_pid", "dst_pid", "body"))) for v, x in decode_items(body, codec)]
            a, b, v, x = zip(*rows) if rows else ([], [], [], [])
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int32()), pa.array(b, pa.int32()), pa.array(v, pa.int64()), pa.array(x, kind)], ["src_pid", "dst_pid", "vid", "value"])

    return encoded.mapInArrow(run, f"src_pid int, dst_pid int, vid long, value {value_type}")
