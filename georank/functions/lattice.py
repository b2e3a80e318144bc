"""Exact integer geometry on a 2**bits lattice: distances, cells and their keys. No floats, so ranks are equal on every engine."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 10
SIDE = 1 << BITS


def col(x) -> Column:
    return F.col(x) if isinstance(x, str) else x


def dist2(ox, oy, qx, qy) -> Column:
    """Squared distance."""
    dx, dy = col(ox) - col(qx), col(oy) - col(qy)
    return dx * dx + dy * dy


def euclid(d2) -> Column:
    """For display only; nothing is ranked by it."""
    return F.sqrt(col(d2).cast("double"))


def side(lvl, bits: int = BITS) -> Column:
    return F.shiftright(F.lit(1 << bits).cast("long"), lvl) if isinstance(lvl, int) else F.expr(f"shiftright({1 << bits}L, {lvl})")


def min_d2(x, y, x0, y0, x1, y1) -> Column:
    """Least squared distance of a point to the closed box."""
    dx = F.greatest(col(x0) - col(x), F.lit(0).cast("long"), col(x) - col(x1))
    dy = F.greatest(col(y0) - col(y), F.lit(0).cast("long"), col(y) - col(y1))
    return dx * dx + dy * dy


def max_d2(x, y, x0, y0, x1, y1) -> Column:
    dx = F.greatest(F.abs(col(x) - col(x0)), F.abs(col(x) - col(x1)))
    dy = F.greatest(F.abs(col(y) - col(y0)), F.abs(col(y) - col(y1)))
    return dx * dx + dy * dy


def box(df, lvl="lvl", cx="cx", cy="cy", bits: int = BITS):
    """Add the closed box x0..y1 of each cell."""
    s = F.expr(f"shiftright({1 << bits}L, {lvl})")
    return df.withColumns({"x0": F.col(cx) * s, "y0": F.col(cy) * s, "x1": F.col(cx) * s + s - 1, "y1": F.col(cy) * s + s - 1})


def quadkey(x, y, bits: int = BITS) -> Column:
    """Interleaved bits of x and y (x lower)."""
    out = F.lit(0).cast("long")
    for i in range(bits):
        bx = F.shiftright(col(x), i).bitwiseAND(F.lit(1).cast("long"))
        by = F.shiftright(col(y), i).bitwiseAND(F.lit(1).cast("long"))
        out = out + F.shiftleft(bx, 2 * i) + F.shiftleft(by, 2 * i + 1)
    return out
