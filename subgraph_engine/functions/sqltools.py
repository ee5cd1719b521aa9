"""Small helpers for expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def lowest_bit_index(bits: str) -> Column:
    """Place of the lowest set bit of a non-negative bigint."""
    return F.expr(f"bit_count(({bits} & (-{bits})) - 1)")


def varint_bytes(value: Column) -> Column:
    """Bytes of a non-negative number at seven bits each."""
    size = F.lit(1)
    for k in range(1, 9):
        size = size + F.when(value >= F.lit(1 << 7 * k), 1).otherwise(0)
    return size


def fresh(df: DataFrame, *names: str) -> list[str]:
    """The names, lengthened where the frame already has such a column (whatever its case)."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out
