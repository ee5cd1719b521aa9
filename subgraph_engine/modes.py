"""Which mode a job runs in, its waves, and what each mode reads and writes."""

from __future__ import annotations

from typing import Any


def choose_mode(max_worker: int, p: int, threads: int = 1, strict_partition_rule: bool = False) -> str:
    """``pinned`` when there are workers for all partitions at once, else ``rotating``.

    Workers hold ``threads`` partitions each; the strict rule counts partitions.
    """
    needed = p if strict_partition_rule else -(-p // threads)
    return "pinned" if max_worker >= needed else "rotating"


def waves(p: int, at_once: int) -> list[list[int]]:
    """Partitions in the order they are taken up, so many at once."""
    return [list(range(a, min(a + at_once, p))) for a in range(0, p, at_once)]


def io_model(history: list[dict[str, Any]], block_rows: int, state_rows: int, mode: str) -> list[dict[str, int | str]]:
    """Rows read and written per superstep: blocks, messages and partial results.

    Rotating workers read their blocks in every superstep and, from the second on,
    messages and partial results, and write both. Pinned workers read blocks once
    and only exchange messages.
    """
    rows: list[dict[str, int | str]] = []
    before = 0
    for h in history:
        first = h["superstep"] == 0
        rotating = mode == "rotating"
        rows.append(
            {
                "mode": mode,
                "superstep": h["superstep"],
                "blocks_read": block_rows if rotating or first else 0,
                "messages_read": 0 if first else before,
                "partials_read": state_rows if rotating and not first else 0,
                "messages_written": h["messages"],
                "partials_written": state_rows if rotating else 0,
            }
        )
        before = h["messages"]
    return rows
