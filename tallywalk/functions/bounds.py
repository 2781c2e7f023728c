"""Error bounds of the walks, and sizes of all structures under a memory limit."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MIB = 1 << 20
#: Bytes of a counter or a cell besides its registers (one byte each): label, place in the index, numbers.
OVERHEAD = 108
#: Bytes of a cell of the shared-register grid: a register and its share of the label.
SHARED_CELL = 6
METHODS = ("gated", "gated_eager", "recycled", "offset", "cell_grid", "shared_grid")


def size_for(method: str, limit_bytes: int, m: int = 1024, depth: int | None = None) -> int:
    """The largest number of counters, or width of a grid, that the limit allows. m: registers of a counter or cell."""
    if method == "shared_grid":
        return limit_bytes // (SHARED_CELL * (depth or 512))
    if method == "cell_grid":
        return limit_bytes // ((depth or 4) * (m + OVERHEAD))
    if method in METHODS:
        return limit_bytes // (m + OVERHEAD)
    raise ValueError(f"method must be one of {METHODS}")


def bytes_of(method: str, size: int, m: int = 1024, depth: int | None = None) -> int:
    """The modelled bytes of a structure: `size` counters or a grid of that width."""
    if method == "shared_grid":
        return SHARED_CELL * (depth or 512) * size
    return (depth or 4 if method == "cell_grid" else 1) * size * (m + OVERHEAD)


def bound_plain(entries: Column, s: Column, eps: Column) -> Column:
    """Largest absolute error of the offset and the recycled walk (needs s above 4 and eps below 1/2)."""
    return entries * (1 / s + (1 + 1 / s) * eps)


def bound_gated(entries: Column, s: Column, eps: Column, delta: Column) -> Column:
    """Largest absolute error of the gated walks, but for a chance of delta and the counters' own."""
    return entries / s * (1 + eps) + entries * F.greatest((F.ln(1 / delta) - 1) * (1 + eps) / s, eps)
