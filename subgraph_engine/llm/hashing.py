"""Spark's xxhash64 of bigints and strings, over arrays."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash

# The primes of the public 64-bit xxHash.
P1, P2, P3, P4, P5 = map(np.uint64, (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
SPARK_SEED = 42


def _turned(x: np.ndarray, bits: int) -> np.ndarray:
    return (x << np.uint64(bits)) | (x >> np.uint64(64 - bits))


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ h >> np.uint64(33)) * P2
    h = (h ^ h >> np.uint64(29)) * P3
    return h ^ h >> np.uint64(32)


def long_hash(values: np.ndarray, seed: int = SPARK_SEED) -> np.ndarray:
    """``xxhash64`` of each bigint, as ``pyspark.sql.functions.xxhash64`` has it."""
    v = np.ascontiguousarray(values, np.int64).view(np.uint64)
    h = np.uint64((seed + int(P5) + 8) % 2**64) ^ (_turned(v * P2, 31) * P1)
    return _mixed(_turned(h, 27) * P1 + P4).view(np.int64)


def string_hash(texts: pa.Array, seed: int = SPARK_SEED) -> np.ndarray:
    """``xxhash64`` of each string, none of them null; those under 32 bytes all at once."""
    _, offsets, data = texts.buffers()
    ends = np.frombuffer(offsets, np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64) if len(texts) else np.zeros(1, np.int64)
    at, size = ends[:-1].copy(), np.diff(ends)
    raw = np.frombuffer(data, np.uint8) if data else np.empty(0, np.uint8)
    # every place of the bytes as the start of a number
    at_any = lambda kind, wide: np.ndarray(max(0, len(raw) - wide + 1), kind, raw, strides=(1,))
    eights, fours = at_any("<u8", 8), at_any("<u4", 4)
    h = size.astype(np.uint64) + np.uint64((seed + int(P5)) % 2**64)
    for k in (1, 2, 3):
        rows = np.flatnonzero(size >= 8 * k)
        h[rows] = _turned(h[rows] ^ (_turned(eights[at[rows]] * P2, 31) * P1), 27) * P1 + P4
        at[rows] += 8
    rows = np.flatnonzero(size & 4)
    h[rows] = _turned(h[rows] ^ (fours[at[rows]].astype(np.uint64) * P1), 23) * P2 + P3
    at[rows] += 4
    for k in (1, 2, 3):
        rows = np.flatnonzero(size & 3 >= k)
        h[rows] = _turned(h[rows] ^ (raw[at[rows]].astype(np.uint64) * P5), 11) * P1
        at[rows] += 1
    h = _mixed(h)
    for i in np.flatnonzero(size >= 32).tolist():
        h[i] = xxhash.xxh64_intdigest(raw[ends[i] : ends[i + 1]].tobytes(), seed)
    return h.view(np.int64)
