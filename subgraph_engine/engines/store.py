"""Functions, messages and a store, as a job without a shared memory has them.

A function holds ``threads`` partitions and is one Arrow task in a superstep. It has

* the blocks of its partitions: neighbour lists as gaps of variable length,
* routes: for every own vertex the other functions that read it, by the masked
  intersection of the vertex's partitions with each function's (one per function,
  whichever of its partitions read it),
* one unified array of the vertices it holds, its own and copies of others, shared by
  its partitions: a copy that several of them read is there once.

In a superstep it takes the payloads that other functions have left for it into its
copies, sweeps its partitions (a thread each) over the values of the superstep
before, and leaves changed values of boundary vertices for the functions that read
them: one payload per ordered pair of functions (a key per vertex with
``aggregate=False``), encoded by ``codec``, of ``batch_rows`` items at most. What stays
inside a function needs no message and is visible after the barrier.

Pinned: blocks, routes and arrays stay with their tasks in memory; the store sees
messages and control rows alone. Arrays are written too after every ``COMPACT``-th
superstep, which bounds the lineage and what a lost executor costs. Rotating: a pool of
``max_worker`` workers, each of which takes the next function that nobody has taken,
reads its blocks, array and messages from the store and writes array and messages
back; with ``preload`` a worker that finds none left fetches blocks and array of a
function of the next superstep.

Blocks, routes and arrays are in pieces of bounded size (``PIECE_ARCS``,
``PIECE_VERTICES``), a row each: lists of different vertices are packed, and unpacked in
a superstep, a piece at a time, so only what is packed and the array of a function have
to fit in its task's memory. Partitions, not functions, should grow in number with the graph.
"""

from __future__ import annotations

import json
import threading
import time
from collections import defaultdict
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from queue import Empty, SimpleQueue
from typing import Any

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine import messaging
from subgraph_engine.blocks import ZSTD_LEVEL, pack_neighbours, read_block, unpack_neighbours, varint_encode
from subgraph_engine.engines.base import Engine, explicit_layout
from subgraph_engine.prepare import bit, WORD_BITS
from subgraph_engine.store import ROW, ParquetStore
from subgraph_engine.storage import shared_path, written_table

COMPACT = 8
#: Arcs of a block's piece: all lists of so many vertices.
PIECE_ARCS = 1 << 16
#: Vertices of a piece of an array or of routes.
PIECE_VERTICES = 1 << 15
#: Bytes of an Arrow batch of a function's rows.
BATCH_BYTES = 4 << 20
_SCHEMA = pa.schema([("kind", pa.string()), ("wid", pa.int32()), ("x", pa.int32()), ("y", pa.int32()), ("n", pa.int64()), ("data", pa.list_(pa.binary()))])
Row = tuple[str, int, int, int, int, list[bytes]]


def _table(rows: list[Row]) -> pa.Table:
    """The rows, in batches of about ``BATCH_BYTES`` at most or of one row."""
    names, batches, at, size = _SCHEMA.names, [], 0, 0
    for k, row in enumerate(rows):
        size += sum(map(len, row[5]))
        if size >= BATCH_BYTES or k + 1 == len(rows):
            batches.append(pa.RecordBatch.from_pylist([dict(zip(names, r)) for r in rows[at : k + 1]], _SCHEMA))
            at, size = k + 1, 0
    return pa.Table.from_batches(batches, _SCHEMA)


def _rows(table: pa.Table) -> list[dict[str, Any]]:
    """The rows; their data are views of the table."""
    rows = table.drop_columns("data").to_pylist()
    for row, data in zip(rows, table.column("data")):
        row["data"] = [x.as_buffer() for x in data.values]
    return rows


def _joined(rows: list[dict[str, Any]], place: int, kind: str) -> np.ndarray:
    """One array of what the pieces have at a place of their data."""
    return np.concatenate([np.empty(0, kind), *(np.frombuffer(r["data"][place], kind) for r in rows)])


def encode_arrays(vids: np.ndarray, values: np.ndarray, codec: str) -> bytes:
    """A payload: ids ascending, with their values."""
    if codec == "json":
        return json.dumps([{"vid": v, "value": x} for v, x in zip(vids.tolist(), values.tolist())], separators=(",", ":")).encode()
    ids = pack_neighbours(vids)
    body = len(ids).to_bytes(4, "little") + ids + values.tobytes()
    return zstandard.ZstdCompressor(level=ZSTD_LEVEL).compress(body) if codec == "binary+zstd" else body


def decode_arrays(body: bytes, codec: str, kind: str) -> tuple[np.ndarray, np.ndarray]:
    if codec == "json":
        items = json.loads(bytes(body))
        return np.array([x["vid"] for x in items], np.int64), np.array([x["value"] for x in items], kind)
    body = zstandard.ZstdDecompressor().decompress(body) if codec == "binary+zstd" else body
    n = int.from_bytes(body[:4], "little")
    return unpack_neighbours(body[4 : 4 + n]), np.frombuffer(body[4 + n :], kind)


def _piece(vertex: str, pieces: int):
    """The piece that a vertex is in."""
    return F.pmod(F.xxhash64(vertex), F.lit(pieces)).cast("int").alias("piece")


class Function:
    """One function in one superstep."""

    def __init__(self, program, wid: int, settings: dict[str, Any]):
        self.program, self.wid, self.settings = program, wid, settings
        self.kind = "<i8" if program.value_type == "bigint" else "<f8"

    def load(self, fixed: list[dict], moving: list[dict]) -> None:
        self.blocks = [r for r in fixed if r["kind"] == "block"]
        routes = [r for r in fixed if r["kind"] == "routes"]
        self.route_vid, self.route_wid = _joined(routes, 0, "<i8"), _joined(routes, 1, "<i4")
        held = sorted((r for r in moving if r["kind"] == "partial"), key=lambda r: r["y"])
        self.vids, self.pids = _joined(held, 0, "<i8"), _joined(held, 1, "<i4")
        self.values, self.changed = _joined(held, 2, self.kind), _joined(held, 3, "u1").astype(bool)
        self.static = {c: _joined(held, 4 + k, "<f8") for k, c in enumerate(self.program.static_columns)}
        if (self.vids[1:] < self.vids[:-1]).any():  # before superstep 0 pieces are by hash
            order = np.argsort(self.vids)
            self.vids, self.pids, self.values, self.changed = self.vids[order], self.pids[order], self.values[order], self.changed[order]
            self.static = {c: x[order] for c, x in self.static.items()}
        inner = self.pids >= 0
        if self.settings["superstep"]:  # before superstep 0 all copies are as their owners are
            self.changed &= inner
        for r in moving:
            if r["kind"] == "messages":
                vids, values = decode_arrays(r["data"][0], self.settings["codec"], self.kind)
                at = np.searchsorted(self.vids, vids)
                self.values[at], self.changed[at] = values, True
        self.inner = inner

    def _sweep(self, block: dict, got: np.ndarray, seen: np.ndarray) -> int:
        """Puts what the own vertices of a partition's piece got in their places; the arcs that were read."""
        vids, counts = np.frombuffer(block["data"][0], "<i8"), np.frombuffer(block["data"][1], "<i4")
        src, _ = read_block(vids, counts, block["data"][2])
        own, place = np.searchsorted(self.vids, vids), np.searchsorted(self.vids, src)
        columns = {c: np.frombuffer(x, "<f8") for c, x in zip(self.program.arc_columns, block["data"][3:])}
        if self.settings["active"]:
            lists = np.repeat(np.arange(len(vids)), counts)
            touched = np.zeros(len(vids), bool)
            touched[lists[self.changed[place]]] = True
            keep = touched[lists]
            own, counts, place = own[touched], counts[touched], place[keep]
            columns = {c: x[keep] for c, x in columns.items()}
        if not len(own):
            return 0
        starts = np.concatenate([[0], np.cumsum(counts)[:-1]]).astype(np.int64)
        view = {"src": place, "starts": starts, "own": own, **columns}
        got[own], seen[own] = self.program.sweep(self.values, view, self.settings["totals"]), True
        return len(place)

    def _sweep_partition(self, pieces: list[dict], got: np.ndarray, seen: np.ndarray) -> int:
        """Pieces have different own vertices, so threads write to different places."""
        return sum(self._sweep(piece, got, seen) for piece in pieces)

    def _array(self, changed: np.ndarray) -> list[Row]:
        columns = (self.vids, self.pids, self.values, changed.view(np.uint8), *self.static.values())
        cuts = range(0, len(self.vids), PIECE_VERTICES)
        return [("partial", self.wid, 0, k, len(self.vids[at : at + PIECE_VERTICES]), [x[at : at + PIECE_VERTICES].tobytes() for x in columns]) for k, at in enumerate(cuts)]

    def run(self) -> list[Row]:
        """Sweeps all partitions over the old values; the new array, the payloads and a control row."""
        settings, program = self.settings, self.program
        partitions = defaultdict(list)
        for block in self.blocks:
            partitions[block["x"]].append(block)
        got, seen = np.zeros(len(self.vids), self.kind), np.zeros(len(self.vids), bool)
        with ThreadPoolExecutor(max(1, min(len(partitions), settings["threads"]))) as pool:
            scanned = sum(pool.map(lambda pieces: self._sweep_partition(pieces, got, seen), partitions.values()))
        old = self.values[self.inner]
        static = {c: x[self.inner] for c, x in self.static.items()}
        new = program.settle(old, got[self.inner], seen[self.inner], settings["totals"], static).astype(self.kind)
        self.values[self.inner] = new
        changed = np.zeros(len(self.vids), bool)
        changed[self.inner] = new != old
        sent = self._messages(changed)
        told = {
            "vertices": int(self.inner.sum()), "changed": int(changed.sum()),
            "active": int(seen.sum()) if settings["active"] else int(self.inner.sum()),
            "arcs_scanned": scanned, "messages": sum(r[4] for r in sent),
            "keys": len({(r[1], r[2]) for r in sent}) if settings["aggregate"] else len({r[5][1] for r in sent}),
            "bytes": sum(len(r[5][0]) for r in sent), **program.sums(old, new, static),
        }
        return [*self._array(changed), *sent, ("control", self.wid, 0, 0, 1, [json.dumps(told).encode()])]

    def _messages(self, changed: np.ndarray) -> list[Row]:
        at = np.searchsorted(self.vids, self.route_vid)
        sends = changed[at] | (not self.program.incremental)
        vids, wids, values = self.route_vid[sends], self.route_wid[sends], self.values[at[sends]]
        order = np.lexsort((vids, wids))
        vids, wids, values = vids[order], wids[order], values[order]
        rows: list[Row] = []
        batch, codec = self.settings["batch_rows"] if self.settings["aggregate"] else 1, self.settings["codec"]
        for wid in np.unique(wids).tolist():
            a, b = np.searchsorted(wids, [wid, wid + 1]).tolist()
            for part, k in enumerate(range(a, b, batch)):
                some = slice(k, min(k + batch, b))
                body = encode_arrays(vids[some], values[some], codec)
                rows.append(("messages", wid, self.wid, part, some.stop - k, [body] if batch > 1 else [body, vids[some].tobytes()]))
        return rows


class StoreEngine(Engine):
    """Supersteps of functions that exchange payloads through a store."""

    def prepare(self) -> DataFrame:
        state = super().prepare()
        spark, t = self.spark, max(1, self.request.threads)
        self.functions = -(-self.request.partitions // t)
        self.store = ParquetStore(spark, shared_path(spark, "job-store"))
        wid = lambda pid: F.floor(F.col(pid) / t).cast("int")
        home = state.select("vid", wid("pid").alias("wid"))
        # who reads a vertex: its partitions as a bitmap, masked with each function's
        maps = self.routes.groupBy("vid", F.floor(F.col("dst_pid") / WORD_BITS).cast("int").alias("word")).agg(F.bit_or(bit("dst_pid")).alias("bits"))
        workers = messaging.worker_table(spark, messaging.colocate(self.request.partitions, t))
        targets = written_table(spark, messaging.function_targets(maps, messaging.worker_bitmaps(workers), home), "job-targets")
        fixed = self._packed_blocks(wid).unionByName(self._packed_routes(targets.join(home.withColumnRenamed("wid", "own"), "vid")))
        columns = ["vid", "value", "changed", *self.program.static_columns]
        held = state.select(wid("pid").alias("wid"), "pid", *columns)
        copies = targets.select("vid", "wid").join(state.select(*columns), "vid").select("wid", F.lit(-1).alias("pid"), *columns)
        places = home.select("wid").unionByName(targets.select("wid"))
        self.store.put(-1, fixed.unionByName(self._packed_arrays(held.unionByName(copies), self._pieces(places, "wid", PIECE_VERTICES))))
        self.targets = targets
        self._cached: list[DataFrame] = []
        if self.pinned:
            with explicit_layout(spark):
                self.fixed = self._keep(self._fixed(None).repartitionById(self.functions, "wid"))
                self.state = self.store.get("partial", -1)
        self.step_read = -1
        return state

    def _keep(self, df: DataFrame) -> DataFrame:
        df = df.persist(StorageLevel.MEMORY_AND_DISK)
        self._cached.append(df)
        return df

    def _fixed(self, wids: list[int] | None) -> DataFrame:
        return self.store.get("block", -1, wids).unionByName(self.store.get("routes", -1, wids))

    def _pieces(self, rows: DataFrame, of: str, most: int) -> int:
        """Into how many pieces the largest group is cut, by hash of vertices; a count per group."""
        return max(1, -(-(rows.groupBy(of).count().agg(F.max("count")).first()[0] or 0) // most))

    def _present_functions(self, state: DataFrame) -> int:
        return state.select("wid").distinct().count()

    def _packed_blocks(self, wid) -> DataFrame:
        columns = list(self.program.arc_columns)
        piece = _piece("dst", self._pieces(self.arcs, "pid", PIECE_ARCS))
        arcs = self.arcs.select(piece, wid("pid").alias("wid"), "pid", "src", "dst", *(F.col(c).cast("double").alias(c) for c in columns))

        def pack(table: pa.Table) -> pa.Table:
            table = table.sort_by([("dst", "ascending"), ("src", "ascending")])
            dst, src = table.column("dst").to_numpy(), table.column("src").to_numpy()
            vids, starts, counts = np.unique(dst, return_index=True, return_counts=True)
            gaps = np.diff(src, prepend=0)
            gaps[starts] = src[starts]
            data = [vids.astype("<i8").tobytes(), counts.astype("<i4").tobytes(), varint_encode(gaps)]
            data += [table.column(c).to_numpy().astype("<f8").tobytes() for c in columns]
            return _table([("block", table.column("wid")[0].as_py(), table.column("pid")[0].as_py(), table.column("piece")[0].as_py(), len(src), data)])

        return arcs.groupBy("pid", "piece").applyInArrow(pack, ROW)

    def _packed_routes(self, targets: DataFrame) -> DataFrame:
        def pack(table: pa.Table) -> pa.Table:
            vids, wids = table.column("vid").to_numpy(), table.column("wid").to_numpy()
            order = np.argsort(vids, kind="stable")
            return _table([("routes", table.column("own")[0].as_py(), 0, table.column("piece")[0].as_py(), len(vids), [vids[order].astype("<i8").tobytes(), wids[order].astype("<i4").tobytes()])])

        piece = _piece("vid", self._pieces(targets, "own", PIECE_VERTICES))
        return targets.select("own", "vid", "wid", piece).groupBy("own", "piece").applyInArrow(pack, ROW)

    def _packed_arrays(self, held: DataFrame, pieces: int) -> DataFrame:
        kind = "<i8" if self.program.value_type == "bigint" else "<f8"
        static = list(self.program.static_columns)
        held = held.select(_piece("vid", pieces), "wid", "pid", "vid", "value", "changed", *(F.col(c).cast("double").alias(c) for c in static))

        def pack(table: pa.Table) -> pa.Table:
            table = table.sort_by("vid")
            column = lambda c, t: table.column(c).to_numpy().astype(t).tobytes()
            data = [column("vid", "<i8"), column("pid", "<i4"), column("value", kind), column("changed", np.uint8), *(column(c, "<f8") for c in static)]
            return _table([("partial", table.column("wid")[0].as_py(), 0, table.column("piece")[0].as_py(), table.num_rows, data)])

        return held.groupBy("wid", "piece").applyInArrow(pack, ROW)

    def _ran(self, k: int, fixed: DataFrame, moving: DataFrame) -> DataFrame:
        program, request = self.program, self.request
        settings = {
            "superstep": k, "totals": dict(self.totals), "codec": request.codec, "aggregate": request.aggregate, "batch_rows": request.batch_rows,
            "threads": request.threads, "active": program.incremental and self.activated(k),
        }

        def run(a: pa.Table, b: pa.Table) -> pa.Table:
            moving = _rows(b)
            if not any(r["kind"] == "partial" for r in moving):
                return _table([])
            function = Function(program, moving[0]["wid"], settings)
            function.load(_rows(a), moving)
            return _table(function.run())

        return fixed.groupBy("wid").cogroup(moving.groupBy("wid")).applyInArrow(run, ROW)

    def _messages(self, k: int, wids: list[int] | None = None) -> DataFrame | None:
        return self.store.get("messages", k - 1, wids) if k else None

    def _control(self, controls: DataFrame) -> dict[str, Any]:
        """Sums over the functions' control rows; a function without one is unfinished."""
        names = ["vertices", "changed", "active", "arcs_scanned", "messages", "keys", "bytes", *self.program.totals()]
        schema = ", ".join(f"{n} double" if n in self.program.totals() else f"{n} long" for n in names)
        told = controls.select(F.from_json(F.col("data")[0].cast("string"), schema).alias("c"))
        row = told.agg(F.count(F.lit(1)).alias("done"), *(F.sum(f"c.{n}").alias(n) for n in names)).first()
        counted = {n: row[n] or 0 for n in names} | {"unfinished": self._present - row["done"]}
        self.totals = {n: counted[n] for n in self.program.totals()}
        self.changed_share = counted["changed"] / max(1, counted["vertices"])
        return counted

    def superstep(self, k: int, state: DataFrame) -> tuple[DataFrame, dict[str, Any]]:
        """Pinned: all functions at once."""
        with explicit_layout(self.spark):
            if k == 0:
                self._present = self._present_functions(self.state)
            moving = self.state if k == 0 else self.state.unionByName(self._messages(k))
            out = self._keep(self._ran(k, self.fixed, moving.repartitionById(self.functions, "wid")))
            whole = (k + 1) % COMPACT == 0
            self.store.put(k, out if whole else out.filter("kind <> 'partial'"))
            counted = self._control(self.store.get("control", k))
            self.state = self.store.get("partial", k) if whole else out.filter("kind = 'partial'")
            # the array before is needed no more, blocks are; written arrays need none of what was kept
            for old in self._cached[1:] if whole else self._cached[1:-2]:
                self._cached.remove(old)
                old.unpersist()
        self._final = lambda: self.state
        return self.state, counted

    def rotation(self, workers: int, preload: bool):
        """Supersteps in which each of so many workers takes the next function that nobody has taken."""
        ready: dict[int, DataFrame] = {}
        guard = threading.Lock()
        self._present = self._present_functions(self.store.get("partial", -1))

        def inputs(wid: int) -> DataFrame:
            with guard:
                got = ready.pop(wid, None)
            return got if got is not None else self._fixed([wid])

        def fetch(wid: int) -> None:
            rows = self._fixed([wid]).persist()
            rows.count()
            with guard:
                ready[wid] = rows

        def step(k: int, state: DataFrame) -> tuple[DataFrame, dict[str, Any]]:
            queue: SimpleQueue[int] = SimpleQueue()
            for wid in range(self.functions):
                queue.put(wid)
            ahead: SimpleQueue[int] = SimpleQueue()
            for wid in range(min(workers, self.functions) if preload else 0):
                ahead.put(wid)
            self.order: list[tuple[int, int]] = []

            def work(worker: int) -> None:
                while True:
                    try:
                        wid = queue.get_nowait()
                    except Empty:
                        break
                    self.order.append((worker, wid))
                    began = time.perf_counter()
                    fixed = inputs(wid)
                    moving = self.store.get("partial", k - 1, [wid])
                    moving = moving.unionByName(self._messages(k, [wid])) if k else moving
                    self.store.put(k, self._ran(k, fixed.coalesce(1), moving.coalesce(1)), part=wid)
                    fixed.unpersist()
                    self.worked.append((worker, k, wid, began, time.perf_counter()))
                if preload:
                    try:
                        fetch(ahead.get_nowait())
                    except Empty:
                        pass

            with explicit_layout(self.spark), ThreadPoolExecutor(workers) as pool:
                for job in [pool.submit(work, w) for w in range(workers)]:
                    job.result()
                counted = self._control(self.store.get("control", k))
            if k > 1:
                self.store.drop(k - 2)
            self._final = lambda: self.store.get("partial", k)
            return state, counted

        def stop() -> None:
            for rows in ready.values():
                rows.unpersist()

        self.on_close.append(stop)
        return step

    def values(self, state: DataFrame) -> DataFrame:
        """vid, value of all functions' own vertices."""
        kind, out = ("<i8", "long") if self.program.value_type == "bigint" else ("<f8", "double")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for data in batch.column("data").to_pylist():
                    inner = np.frombuffer(data[1], "<i4") >= 0
                    vids, values = np.frombuffer(data[0], "<i8")[inner], np.frombuffer(data[2], kind)[inner]
                    yield pa.RecordBatch.from_arrays([pa.array(vids), pa.array(values)], ["vid", "value"])

        return self._final().select("data").mapInArrow(run, f"vid long, value {out}")

    def close(self) -> None:
        for df in getattr(self, "_cached", ()):
            df.unpersist()
        super().close()
