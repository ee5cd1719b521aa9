"""What a program has to say, and the registry.

A program is the worker logic alone: how values begin, what a vertex sees of a
neighbour, how such messages combine, and how the combination changes a value.
Engines decide where rows are and when they move. ``sweep`` is the same step on
arrays, for engines that hold a whole partition.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_registry: dict[str, type["Program"]] = {}


def register(name: str):
    """Makes a program available to requests under ``name``."""

    def keep(cls: type["Program"]) -> type["Program"]:
        _registry[name.lower()] = cls
        cls.name = name.lower()
        return cls

    return keep


def lookup(name: str) -> type["Program"]:
    try:
        return _registry[name.lower()]
    except KeyError:
        raise ValueError(f"no program is registered as {name!r}; known: {sorted(_registry)}") from None


@dataclass
class Program:
    """Base of all programs; options are its fields."""

    name: str = field(default="", init=False, repr=False)
    #: bigint or double
    value_type: str = field(default="bigint", init=False, repr=False)
    #: along which arcs values travel: ``out`` or ``both``
    direction: str = field(default="out", init=False, repr=False)
    #: whether a vertex may be left out while nothing around it changes
    incremental: bool = field(default=True, init=False, repr=False)
    #: whether values may be swept to a fixpoint inside a partition
    local_fixpoint: bool = field(default=False, init=False, repr=False)
    #: columns of an arc that messages need: out_deg, out_weight, weight
    arc_columns: tuple[str, ...] = field(default=(), init=False, repr=False)
    #: the state's columns that stay as they are, from ``static``
    static_columns: tuple[str, ...] = field(default=(), init=False, repr=False)

    def first_value(self) -> Column:
        """The value before superstep 0, from vid and the static columns."""
        raise NotImplementedError

    def first_changed(self) -> Column:
        """Whether readers of a vertex have something to see in superstep 0."""
        return F.lit(True)

    def static(self, n_vertices: int) -> dict[str, Column]:
        return {}

    def message(self) -> Column:
        """What dst sees of src, from value and the arc's columns; null is nothing."""
        return F.col("value")

    def combine(self, seen: DataFrame, keys: list[str]) -> DataFrame:
        """``keys`` and ``got`` from ``keys`` and ``msg``."""
        raise NotImplementedError

    def apply(self, totals: dict[str, Any]) -> Column:
        """The new value from value and got (null where nothing came)."""
        raise NotImplementedError

    def totals(self) -> dict[str, Column]:
        """Sums over the new state that the next superstep, or the end, depends on."""
        return {}

    def ends(self, superstep: int, metrics: dict[str, Any]) -> bool:
        """Whether this was the last superstep."""
        return metrics["changed"] == 0

    def settle(self, values: np.ndarray, got: np.ndarray, seen: np.ndarray, totals: dict[str, Any], static: dict[str, np.ndarray]) -> np.ndarray:
        """``apply`` on arrays: new values from own values and what ``sweep`` gave where ``seen`` says that it did."""
        return np.where(seen, got, values)

    def sums(self, old: np.ndarray, new: np.ndarray, static: dict[str, np.ndarray]) -> dict[str, float]:
        """``totals`` on arrays, of a part of the vertices."""
        return {}

    def sweep(self, values: np.ndarray, arcs: dict[str, np.ndarray], totals: dict[str, Any]) -> np.ndarray:
        """New values of the vertices that are an arc's dst.

        ``values`` are of all vertices held; ``arcs`` has src and starts (of each
        dst's run, runs are not empty), own (index of each dst), and arc columns.
        """
        raise NotImplementedError
