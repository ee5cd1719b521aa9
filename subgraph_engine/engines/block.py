"""Supersteps on whole partitions as arrays.

A partition's arcs and the values it reads meet in one task per partition, where
a sweep is a few array operations. Programs that only take minima may sweep to a
fixpoint over the partition's own vertices, which saves supersteps on long paths:
messages then carry what a whole subgraph has found.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.engines.relational import PartitionEngine


class BlockEngine(PartitionEngine):
    """Options of the request: ``local_sweeps`` is 1 (default) or ``fixpoint``."""

    def gather(self, k: int, state: DataFrame, pids: list[int] | None) -> DataFrame:
        program, totals = self.program, dict(self.totals)
        fixpoint = self.request.options.get("local_sweeps", 1) == "fixpoint" and program.local_fixpoint
        kind = pa.int64() if program.value_type == "bigint" else pa.float64()
        columns = program.arc_columns

        def run(arcs: pa.Table, held: pa.Table) -> pa.Table:
            if not arcs.num_rows:
                return pa.table({"pid": pa.array([], pa.int32()), "vid": pa.array([], pa.int64()), "got": pa.array([], kind)})
            arcs = arcs.sort_by("dst")
            vids, values = held.column("src").to_numpy(), held.column("value").to_numpy().copy()
            order = np.argsort(vids)
            vids, values = vids[order], values[order]
            dst, src = arcs.column("dst").to_numpy(), arcs.column("src").to_numpy()
            own, starts = np.unique(dst, return_index=True)
            view = {"src": np.searchsorted(vids, src), "starts": starts, "own": np.searchsorted(vids, own)}
            view |= {c: arcs.column(c).to_numpy() for c in columns}
            got = program.sweep(values, view, totals)
            while fixpoint and not np.array_equal(got, values[view["own"]]):
                values[view["own"]] = got
                got = program.sweep(values, view, totals)
            pid = arcs.column("pid")[0].as_py()
            return pa.table({"pid": pa.array([pid] * len(own), pa.int32()), "vid": pa.array(own), "got": pa.array(got, kind)})

        mirror = self.mirror(state, pids).select("pid", "src", "value")
        arcs = self.wave_arcs(pids).select("pid", "src", "dst", *columns)
        schema = f"pid int, vid long, got {program.value_type}"
        return arcs.groupBy("pid").cogroup(mirror.groupBy("pid")).applyInArrow(run, schema)

    def activated(self, k: int) -> bool:
        """Blocks are swept whole; activation over arrays is with the store engine."""
        if self.request.activate_from is not None or self.request.activate_below is not None:
            raise ValueError("the block engine has no activation; the partition and store engines have")
        return False
