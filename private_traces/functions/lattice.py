"""Cells as Column arithmetic: uniform grids, the leaf lattice, and adaptive cells derived from integer leaves."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from private_traces.config import Bounds

LEVELS = (1, 2, 3, 6)
FINE = 6  # leaves per side of a top cell: every level divides it


def axis(v: Column, low: float, high: float, n: int) -> Column:
    """Which of ``n`` equal parts of [low, high) holds ``v``; readings outside go to the nearest part."""
    return F.greatest(F.lit(0), F.least(F.lit(n - 1), F.floor((v - low) / F.lit(high - low) * n))).cast("int")


def uniform_cell(x: Column, y: Column, b: Bounds, n: int) -> Column:
    """Cell of an n x n grid, numbered n * column + row from 0."""
    return (axis(x, b.x0, b.x1, n) * n + axis(y, b.y0, b.y1, n)).cast("int")


def leaf(x: Column, y: Column, b: Bounds, top_n: int) -> Column:
    """Cell of the finest lattice, 6 * top_n parts a side."""
    return uniform_cell(x, y, b, FINE * top_n)


def leaf_xy(code: Column, top_n: int) -> tuple[Column, Column]:
    side = FINE * top_n
    return F.floor(code / side).cast("int"), (code % side).cast("int")


def top_of(code: Column, top_n: int) -> Column:
    """Top cell of a leaf."""
    gx, gy = leaf_xy(code, top_n)
    return (F.floor(gx / FINE) * top_n + F.floor(gy / FINE)).cast("int")


def grid6_of(code: Column, top_n: int) -> Column:
    """Cell of the 6 x 6 evaluation grid of a leaf (exact: 6 divides the lattice)."""
    gx, gy = leaf_xy(code, top_n)
    return (F.floor(gx / top_n) * 6 + F.floor(gy / top_n)).cast("int")


def adaptive_cell(code: Column, levels, firsts, top_n: int) -> Column:
    """Adaptive cell of a leaf; ``levels`` and ``firsts`` are arrays over top cells (constants or broadcast), or functions of a top cell."""
    of = lambda held, top: held(top) if callable(held) and not isinstance(held, Column) else F.get(held, top)
    gx, gy = leaf_xy(code, top_n)
    top = top_of(code, top_n)
    m = of(levels, top)
    part = lambda g: F.floor((g % FINE) * m / FINE)
    return (of(firsts, top) + part(gx) * m + part(gy)).cast("int")
