"""Grid cells and their codes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def axis_cell(v: Column, low: float, high: float, depth: int) -> Column:
    """Index of v among 2^depth equal cells of [low, high]; outside values go to the border cells."""
    n = 1 << depth
    width = (high - low) / n or 1.0
    return F.least(F.greatest(F.floor((v - F.lit(low)) / F.lit(width)), F.lit(0)), F.lit(n - 1)).cast("long")


def morton(ix: Column, iy: Column, depth: int) -> Column:
    """Interleaved bits of two cell indices, x first."""
    code = F.lit(0).cast("long")
    for b in range(depth):
        bit = lambda i: F.shiftright(i, b).bitwiseAND(F.lit(1).cast("long"))  # noqa: B023, E731
        code = code.bitwiseOR(F.shiftleft(bit(ix), 2 * b + 1)).bitwiseOR(F.shiftleft(bit(iy), 2 * b))
    return code


def cell_path(ix: Column, iy: Column, depth: int) -> Column:
    """The quadtree path of a cell: one digit 0-3 for each level."""
    digits = [(F.shiftright(ix, b).bitwiseAND(F.lit(1).cast("long")) * 2 + F.shiftright(iy, b).bitwiseAND(F.lit(1).cast("long"))).cast("string") for b in range(depth - 1, -1, -1)]
    return F.concat_ws("", *digits)
