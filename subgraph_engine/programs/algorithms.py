"""Breadth-first search, PageRank, label propagation, components, shortest paths."""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from subgraph_engine.model import UNREACHABLE
from subgraph_engine.programs.core import Program, register


class _Least(Program):
    """Programs that keep the smaller of a vertex's value and what it sees."""

    def __post_init__(self) -> None:
        self.local_fixpoint = True

    def combine(self, seen: DataFrame, keys: list[str]) -> DataFrame:
        return seen.groupBy(*keys).agg(F.min("msg").alias("got"))

    def apply(self, totals: dict[str, Any]) -> Column:
        return F.least("value", F.coalesce("got", F.col("value")))


@register("wcc")
@dataclass
class Components(_Least):
    """The smallest id of the component, whatever the directions."""

    def __post_init__(self) -> None:
        super().__post_init__()
        self.direction = "both"

    def first_value(self) -> Column:
        return F.col("vid")

    def sweep(self, values, arcs, totals):
        return np.minimum(values[arcs["own"]], np.minimum.reduceat(values[arcs["src"]], arcs["starts"]))


@register("bfs")
@dataclass
class Search(_Least):
    """Hops from the nearest of the sources; unreachable vertices keep the largest bigint."""

    sources: tuple[int, ...] = ()
    max_depth: int | None = None

    def first_value(self) -> Column:
        return F.when(F.col("vid").isin(*self.sources), F.lit(0)).otherwise(F.lit(UNREACHABLE)).cast("long")

    def first_changed(self) -> Column:
        return F.col("vid").isin(*self.sources)

    def message(self) -> Column:
        reached = F.col("value") < (UNREACHABLE if self.max_depth is None else self.max_depth)
        return F.when(reached, F.col("value") + 1)

    def sweep(self, values, arcs, totals):
        seen = values[arcs["src"]]
        limit = UNREACHABLE if self.max_depth is None else self.max_depth
        seen = np.where(seen < limit, seen + (seen < limit), UNREACHABLE)
        return np.minimum(values[arcs["own"]], np.minimum.reduceat(seen, arcs["starts"]))


@register("sssp")
@dataclass
class Paths(_Least):
    """Least total weight from the source (weights not negative); unreachable is infinite."""

    source: int = 0

    def __post_init__(self) -> None:
        super().__post_init__()
        self.value_type = "double"
        self.arc_columns = ("weight",)

    def first_value(self) -> Column:
        return F.when(F.col("vid") == self.source, F.lit(0.0)).otherwise(F.lit(float("inf")))

    def first_changed(self) -> Column:
        return F.col("vid") == self.source

    def message(self) -> Column:
        return F.when(F.col("value") < float("inf"), F.col("value") + F.col("weight"))

    def sweep(self, values, arcs, totals):
        return np.minimum(values[arcs["own"]], np.minimum.reduceat(values[arcs["src"]] + arcs["weight"], arcs["starts"]))


@register("cdlp")
@dataclass
class Communities(Program):
    """The most frequent label among the neighbours, the smallest of equals, for a number of rounds.

    On directed graphs both directions vote, so reciprocal arcs vote twice.
    """

    iters: int = 10

    def __post_init__(self) -> None:
        self.direction = "both"

    def first_value(self) -> Column:
        return F.col("vid")

    def combine(self, seen: DataFrame, keys: list[str]) -> DataFrame:
        # a hub's neighbours are counted per label before its labels are compared
        votes = seen.groupBy(*keys, "msg").agg(F.count(F.lit(1)).alias("votes"))
        return votes.groupBy(*keys).agg(F.max_by("msg", F.struct("votes", -F.col("msg"))).alias("got"))

    def apply(self, totals: dict[str, Any]) -> Column:
        return F.coalesce("got", "value")

    def ends(self, superstep: int, metrics: dict[str, Any]) -> bool:
        return superstep + 1 >= self.iters or metrics["changed"] == 0

    def sweep(self, values, arcs, totals):
        sizes = np.diff(np.append(arcs["starts"], len(arcs["src"])))
        dst = np.repeat(np.arange(len(sizes)), sizes)
        label = values[arcs["src"]]
        order = np.lexsort((label, dst))
        dst, label = dst[order], label[order]
        new = np.flatnonzero(np.concatenate([[True], (dst[1:] != dst[:-1]) | (label[1:] != label[:-1])]))
        votes = np.diff(np.append(new, len(dst)))
        best = np.lexsort((label[new], -votes, dst[new]))
        firsts = np.unique(dst[new][best], return_index=True)[1]
        return label[new][best][firsts]


@register("pagerank")
@dataclass
class Ranks(Program):
    """PageRank: damped sums over in-neighbours; the mass of sinks is spread like the restart.

    ``restart``: ids that share the restart evenly (all vertices when empty).
    ``weighted``: shares follow the arcs' weights. ``tol``: stop when the values'
    absolute changes sum to less.
    """

    damping: float = 0.85
    iters: int = 10
    tol: float | None = None
    restart: tuple[int, ...] = ()
    weighted: bool = False
    n_vertices: int = field(default=1, init=False)

    def __post_init__(self) -> None:
        self.value_type, self.incremental = "double", False
        self.arc_columns = ("out_weight", "weight") if self.weighted else ("out_deg",)
        self.static_columns = ("sink", "base")

    def static(self, n_vertices: int) -> dict[str, Column]:
        self.n_vertices = n_vertices
        if self.restart:
            base = F.when(F.col("vid").isin(*self.restart), F.lit(1.0 / len(self.restart))).otherwise(F.lit(0.0))
        else:
            base = F.lit(1.0 / max(1, n_vertices))
        return {"sink": F.col("out_deg") == 0, "base": base}

    def first_value(self) -> Column:
        return F.col("base")

    def message(self) -> Column:
        if self.weighted:
            return F.col("value") * F.col("weight") / F.col("out_weight")
        return F.col("value") / F.col("out_deg")

    def combine(self, seen: DataFrame, keys: list[str]) -> DataFrame:
        return seen.groupBy(*keys).agg(F.sum("msg").alias("got"))

    def apply(self, totals: dict[str, Any]) -> Column:
        lost = F.lit(float(totals.get("lost") or 0.0))
        return (1 - self.damping) * F.col("base") + self.damping * (F.coalesce("got", F.lit(0.0)) + lost * F.col("base"))

    def totals(self) -> dict[str, Column]:
        return {"lost": F.sum(F.when(F.col("sink"), F.col("value")).otherwise(0.0)), "moved": F.sum(F.abs(F.col("value") - F.col("old")))}

    def settle(self, values, got, seen, totals, static):
        lost = float(totals.get("lost") or 0.0)
        return (1 - self.damping) * static["base"] + self.damping * (np.where(seen, got, 0.0) + lost * static["base"])

    def sums(self, old, new, static):
        return {"lost": float(new[static["sink"] > 0].sum()), "moved": float(np.abs(new - old).sum())}

    def ends(self, superstep: int, metrics: dict[str, Any]) -> bool:
        return superstep + 1 >= self.iters or self.tol is not None and (metrics["moved"] or 0.0) < self.tol

    def sweep(self, values, arcs, totals):
        share = arcs["weight"] / arcs["out_weight"] if self.weighted else 1.0 / arcs["out_deg"]
        return np.add.reduceat(values[arcs["src"]] * share, arcs["starts"])
