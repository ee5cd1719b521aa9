"""Exact top-k inner products from an impact-ordered, score-at-a-time index.

Vectors become integers, floor(256 * x) of every component. Rows are put in blocks of
bounded size by hash. A block's index is built once and written: for every dimension
its posting list by descending impact (the component's magnitude, quantised where it
is large), and where each impact segment ends.

A query takes the segments of all dimensions in the order of query weight times
impact: everything above a falling level is added to the accumulators, and each
row knows how many of its dimensions are still out. Below the level a dimension
can add or take at most the level (or all it has, if that is less), so every row
has a lower and an upper bound. The bar is the k-th best lower bound, or the k-th
best score among ``SEED_ROWS`` rows of the table that every task holds, if that is
higher. Rows whose upper bound is below the bar cannot be members, whatever is still
out: once an eighth of the block's rows or fewer are left, the query stops there
and scores these exactly. A block whose bound on all its rows is below the bar is
skipped. If nothing is proved, all postings are taken and the scores are exact anyway;
blocks of at most ``FEW`` rows are scored outright.

Queries meet blocks in tiles of a bounded number of queries and one block each; the k
best of every block are merged by a window per query, which has k rows per block.
Ties go to the smaller id, so bounds are compared inclusively.

Exactness: a block and query whose products sum below 2**53 are computed in doubles,
which is exact for integers. Rows and queries with a component beyond ``NARROW`` are
compared as Python integers, all of them; a score beyond a bigint's range is shown as
the nearest bigint.

Defined results: vectors that are null or hold null or non-finite components take no
part, nor do rows without an id; shorter vectors, empty ones too, count as padded with
zeros; every row is a candidate, also where an id repeats, but for the query's own row;
fewer than k candidates give all of them; an empty table gives an empty result; extra
columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subgraph_engine.storage import release, written_table

SCALE = 256
BLOCK_ROWS = 16_384
TILE_QUERIES = 4096
LEVELS = 4096
#: Components beyond this are Python integers.
NARROW = 1 << 24
#: Rows, and components, that every task holds to know a bar before it starts.
SEED_ROWS = 4096
SEED_VALUES = 1 << 20
#: Shares of a block's postings after which a query looks whether it may stop.
STOPS = (0.25, 0.35, 0.42, 0.5, 0.6, 0.7, 0.85, 1.0)
FEW = 192
EXACT = 1 << 53


def usable_vectors(rows: DataFrame, id_column: str = "vec_id", vector_column: str = "embedding") -> DataFrame:
    """row (unique), vec_id, x (array of double) of the rows that take part."""
    taken = rows.select(F.col(id_column).cast("long").alias("vec_id"), F.transform(vector_column, lambda e: e.cast("double")).alias("x"))
    finite = F.forall("x", lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < F.lit(float("inf"))))
    taken = taken.filter(F.col("vec_id").isNotNull() & F.col("x").isNotNull() & finite)
    return taken.select(F.monotonically_increasing_id().alias("row"), "vec_id", "x")


def integers(x: np.ndarray) -> list[int]:
    """floor(256 * x) of any finite doubles."""
    return [math.floor(s) if math.isfinite(s := SCALE * float(e)) else int(e) * SCALE for e in x]


def _lists(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """All components, and where each list ends."""
    whole = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    ends = whole.offsets.to_numpy().astype(np.int64)
    return whole.flatten().to_numpy(zero_copy_only=False), ends - ends[0]


class Vectors:
    """Rows of a table as one matrix of whole numbers, and the wide ones apart."""

    def __init__(self, table: pa.Table):
        order = np.argsort(table.column("vec_id").to_numpy(), kind="stable")
        table = table.take(pa.array(order))
        flat, ends = _lists(table.column("x"))
        with np.errstate(over="ignore"):
            whole = np.floor(SCALE * flat)
        sizes = np.diff(ends)
        dims = int(sizes.max()) if len(sizes) else 0
        big = np.concatenate([[0], np.cumsum(np.abs(whole) > NARROW)])
        wide = (big[ends[1:]] - big[ends[:-1]] > 0) | (dims > 1 << 14)
        row, ids = table.column("row").to_numpy(), table.column("vec_id").to_numpy()
        self.wide = [(int(row[i]), int(ids[i]), integers(flat[ends[i] : ends[i + 1]])) for i in np.flatnonzero(wide)]
        keep = np.flatnonzero(~wide)
        self.row, self.ids = row[keep], ids[keep]
        self.matrix = np.zeros((len(keep), dims))
        if len(keep) and (sizes[keep] == dims).all() and len(keep) == len(sizes):
            self.matrix = whole.reshape(len(keep), dims)
        else:
            for k, i in enumerate(keep):
                self.matrix[k, : sizes[i]] = whole[ends[i] : ends[i + 1]]


class BlockIndex:
    """Posting lists of one block, ordered by descending impact; rows are in the order of their ids."""

    def __init__(self, row: np.ndarray, ids: np.ndarray, matrix: np.ndarray, order: np.ndarray | None = None, ends: np.ndarray | None = None):
        self.row, self.ids, self.matrix = row, ids, matrix
        size = np.abs(matrix)
        self.largest = size.max(axis=0) if size.size else np.zeros(matrix.shape[1])
        most = int(self.largest.max()) if size.size else 0
        self.shift = max(0, most.bit_length() - LEVELS.bit_length() + 1)
        if order is None:
            impact = size.astype(np.int64) >> self.shift
            top = int(impact.max()) if impact.size else 0
            order = np.argsort(-impact, axis=0, kind="stable").T.copy()  # dimension x rank -> row
            # ends[d, i]: postings of dimension d with an impact of at least i
            counts = np.stack([np.bincount(c, minlength=top + 2) for c in impact.T]) if impact.size else np.zeros((matrix.shape[1], 2), int)
            ends = counts[:, ::-1].cumsum(axis=1)[:, ::-1]
        self.order, self.ends = order, ends
        self.values = np.take_along_axis(matrix.T, order, axis=1) if matrix.size else matrix.T
        self.norm = math.sqrt(float((matrix * matrix).sum(axis=1).max())) if matrix.size else 0.0

    def search(self, query_row: int, query: np.ndarray, k: int, floor: float = -math.inf) -> tuple[np.ndarray, np.ndarray]:
        """Ids and scores of the k best rows by score and then id; of those alone that reach ``floor`` where it is given."""
        own = np.flatnonzero(self.row == query_row)
        rows = self._possible(query, k, own, floor)
        rows = rows[~np.isin(rows, own)]
        if float(np.abs(query) @ self.largest) < EXACT:
            scores = (self.matrix[rows] @ query).astype(np.int64)
        else:
            scores = self.matrix[rows].astype(np.int64) @ query.astype(np.int64)
        best = np.lexsort((self.ids[rows], -scores))[:k]
        return self.ids[rows][best], scores[best]

    def _possible(self, query: np.ndarray, k: int, own: np.ndarray, floor: float) -> np.ndarray:
        n, dims = self.matrix.shape
        everything = np.arange(n)
        if n <= max(FEW, k + 1):
            return everything
        weight = np.abs(query)
        reach = weight * self.largest
        top = int(reach.max())
        if reach.sum() < floor or math.sqrt(float(query @ query)) * self.norm * (1 + 1e-9) < floor:
            return everything[:0]
        if top == 0 or reach.sum() >= EXACT:  # nothing to tell apart, or beyond exact sums
            return everything
        # levels of the product, falling; segments that each of them opens, per dimension
        levels = np.unique(np.maximum(1, (top * 0.93 ** np.arange(130)).astype(np.int64)))[::-1]
        step = -(-levels[:, None] // np.maximum(weight, 1).astype(np.int64)[None, :])  # least component that reaches the level
        impact = np.minimum((step + (1 << self.shift) - 1) >> self.shift, self.ends.shape[1] - 1)
        opened = np.where(weight[None, :] > 0, self.ends[np.arange(dims)[None, :], impact], 0)
        shares = opened.sum(axis=1) / (n * max(1, int((weight > 0).sum())))
        score, seen = np.zeros(n), np.zeros(n)
        at = np.zeros(dims, np.int64)
        few = max(FEW, n // 8)
        for stop in STOPS:
            pick = int(np.searchsorted(shares, stop)) if stop < 1 else len(levels)
            if pick >= len(levels):
                return everything  # not proved before: score all exactly
            to = opened[pick]
            more = np.flatnonzero(to > at)
            if len(more):
                rows = np.concatenate([self.order[d, at[d] : to[d]] for d in more])
                score += np.bincount(rows, np.concatenate([self.values[d, at[d] : to[d]] * query[d] for d in more]), n)
                seen += np.bincount(rows, minlength=n)
            at = np.maximum(at, to)
            # a dimension with open segments adds below its level, quantised up; one without, all it has
            limit = np.minimum(reach, weight * (impact[pick].astype(np.int64) << self.shift))
            touched = at > 0
            most = float(limit[touched].max()) if touched.any() else 0.0
            out = float(limit[~touched].sum()) + most * (int(touched.sum()) - seen)
            lower, upper = score - out, score + out
            lower[own], upper[own] = -math.inf, -math.inf
            bar = max(floor, float(np.partition(lower, n - k)[n - k]))
            left = np.flatnonzero(upper >= bar)
            if len(left) <= few:
                return left
        return everything


PACKED = "block int, dims int, order binary, ends binary, vectors binary, row binary, ids binary, wide array<struct<row: bigint, vec_id: bigint, x: array<double>>>"


def build_blocks(spark: SparkSession, vectors: DataFrame, rows: int = BLOCK_ROWS) -> tuple[DataFrame, int]:
    """One row per block with its vectors and posting lists, written; and the number of blocks."""
    blocks = max(1, -(-vectors.count() // rows))

    def pack(table: pa.Table) -> pa.Table:
        held = Vectors(table)
        index = BlockIndex(held.row, held.ids, held.matrix)
        wide = set(r for r, _, _ in held.wide)
        row = {
            "block": table.column("block")[0].as_py(),
            "dims": held.matrix.shape[1],
            "order": index.order.astype("<u4").tobytes(),
            "ends": index.ends.astype("<u4").tobytes(),
            "vectors": held.matrix.astype("<i4").tobytes(),
            "row": held.row.astype("<i8").tobytes(),
            "ids": held.ids.astype("<i8").tobytes(),
            "wide": [r for r in table.select(["row", "vec_id", "x"]).to_pylist() if r["row"] in wide] if wide else [],
        }
        whole, long, raw = pa.int32(), pa.int64(), pa.binary()
        wide_kind = pa.list_(pa.struct([("row", long), ("vec_id", long), ("x", pa.list_(pa.float64()))]))
        fields = [("block", whole), ("dims", whole), ("order", raw), ("ends", raw), ("vectors", raw), ("row", raw), ("ids", raw), ("wide", wide_kind)]
        return pa.Table.from_pylist([row], pa.schema(fields))

    placed = vectors.withColumn("block", F.pmod(F.xxhash64("row"), F.lit(blocks)).cast("int"))
    return written_table(spark, placed.groupBy("block").applyInArrow(pack, PACKED), "topk-blocks"), blocks


def _unpacked(packed: pa.Table) -> tuple[BlockIndex, list[tuple[int, int, list[int]]]]:
    of = {c: packed.column(c)[0].as_py() for c in packed.column_names}
    dims = of["dims"]
    row, ids = (np.frombuffer(of[c], "<i8") for c in ("row", "ids"))
    matrix = np.frombuffer(of["vectors"], "<i4").reshape(len(ids), dims).astype(float)
    order = np.frombuffer(of["order"], "<u4").reshape(dims, -1).astype(np.int64) if dims else np.empty((0, len(ids)), np.int64)
    ends = np.frombuffer(of["ends"], "<u4").reshape(dims, -1).astype(np.int64) if dims else np.empty((0, 2), np.int64)
    wide = [(w["row"], w["vec_id"], integers(w["x"])) for w in of["wide"]]
    return BlockIndex(row, ids, matrix, order, ends), wide


def _product(a: list[int], b: list[int]) -> int:
    """Exact, whatever the size; shown within a bigint's range."""
    return max(-(1 << 63), min((1 << 63) - 1, sum(x * y for x, y in zip(a, b))))


def _fitted(matrix: np.ndarray, dims: int) -> np.ndarray:
    """The matrix with so many dimensions; what others lack counts as zero."""
    out = np.zeros((len(matrix), dims))
    out[:, : min(dims, matrix.shape[1])] = matrix[:, :dims]
    return out


FOUND = "query_row long, query_id long, vec_id long, score long"


def top_k(spark: SparkSession, vectors: DataFrame, queries: DataFrame, k: int = 5, rows: int = BLOCK_ROWS, tile: int = TILE_QUERIES) -> DataFrame:
    """query_id, rank, vec_id, score: the k best rows of ``vectors`` for every row of ``queries``."""
    total, dims = vectors.agg(F.count(F.lit(1)), F.max(F.size("x"))).first()
    packed, blocks = build_blocks(spark, vectors, rows)
    groups = max(1, -(-queries.count() // tile))
    seeds = min(SEED_ROWS, SEED_VALUES // max(1, dims or 1))
    chosen = vectors.filter(F.pmod(F.xxhash64("row", F.lit(2)), F.lit(max(1, total))) < seeds).limit(2 * seeds)
    shared = spark.sparkContext.broadcast(Vectors(chosen.toArrow()))  # of bounded size; it can only raise the bar
    numbers = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = packed.withColumn("tile", numbers(groups))
    right = queries.select("row", "vec_id", "x", F.pmod(F.xxhash64("row", F.lit(1)), F.lit(groups)).cast("int").alias("tile"))
    right = right.withColumn("block", numbers(blocks))

    def floors(asked: Vectors) -> np.ndarray:
        """For each query, a score that k rows reach."""
        seed = shared.value
        if len(seed.ids) <= k or not len(asked.ids):
            return np.full(len(asked.ids), -math.inf)
        width = max(asked.matrix.shape[1], seed.matrix.shape[1])
        q, s = _fitted(asked.matrix, width), _fitted(seed.matrix, width)
        out = np.empty(len(q))
        for at in range(0, len(q), 256):
            scores = q[at : at + 256] @ s.T
            scores[asked.row[at : at + 256, None] == seed.row[None, :]] = -math.inf
            out[at : at + 256] = np.partition(scores, -k, axis=1)[:, -k]
        exact = np.abs(q).sum(axis=1) * (np.abs(s).max() if s.size else 0) < EXACT
        return np.where(exact, out, -math.inf)

    def search(index: pa.Table, asked: pa.Table) -> pa.Table:
        found: list[tuple[int, int, int, int]] = []
        if index.num_rows and asked.num_rows:
            block, wide = _unpacked(index)
            own = Vectors(asked)
            width = block.matrix.shape[1]
            narrow = zip(own.row.tolist(), own.ids.tolist(), own.matrix, floors(own))
            for query_row, query_id, query, floor in narrow:
                fitted = _fitted(query[None, :], width)[0]
                for i, s in zip(*block.search(query_row, fitted, k, floor)):
                    found.append((query_row, query_id, int(i), int(s)))
                if wide:
                    exact = [int(x) for x in query]
                    found += [(query_row, query_id, i, _product(exact, x)) for r, i, x in wide if r != query_row]
            for query_row, query_id, exact in own.wide:
                scores = [(i, _product(exact, [int(x) for x in v])) for r, i, v in zip(block.row, block.ids.tolist(), block.matrix) if r != query_row]
                scores += [(i, _product(exact, x)) for r, i, x in wide if r != query_row]
                found += [(query_row, query_id, i, s) for i, s in sorted(scores, key=lambda p: (-p[1], p[0]))[:k]]
        columns = [pa.array(c, pa.int64()) for c in (zip(*found) if found else ([], [], [], []))]
        return pa.Table.from_arrays(columns, ["query_row", "query_id", "vec_id", "score"])

    found = left.groupBy("block", "tile").cogroup(right.groupBy("block", "tile")).applyInArrow(search, FOUND)
    best = Window.partitionBy("query_row").orderBy(F.col("score").desc(), "vec_id")
    ranked = found.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k)
    out = written_table(spark, ranked.select("query_id", "rank", "vec_id", "score"), "topk-found")
    release(spark, packed)
    return out


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = written_table(spark, usable_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet")), "topk-vectors")
    found = top_k(spark, vectors, vectors.filter("vec_id % 50 = 0"), k=5)
    release(spark, vectors)
    return found


ORACLE = """
WITH v AS (
  SELECT row_number() OVER () AS r, vec_id, list_transform(embedding, lambda x: floor(256 * CAST(x AS DOUBLE))) AS e
  FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (
  SELECT q.r, q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.e, c.e) AS BIGINT) AS score
  FROM v q JOIN v c ON q.r <> c.r WHERE q.vec_id % 50 = 0),
n AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY r ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score
  FROM s)
SELECT * FROM n WHERE rank <= 5
"""
