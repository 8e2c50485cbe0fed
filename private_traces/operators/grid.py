"""The density-adaptive grid: noisy densities of the top cells, how each is cut, and the cells that result."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from private_traces.config import Bounds
from private_traces.functions.lattice import LEVELS, adaptive_cell
from private_traces.functions.noise import densify, laplace

from . import statistics


def noisy_density(top_density: DataFrame, top_n: int, epsilon: float | None, seed: int, source: str = "md5") -> DataFrame:
    """``top, density`` for every top cell, empty ones too: Laplace noise of scale 1/epsilon, cut off at 0."""
    spark = top_density.sparkSession
    dense = densify(top_density, spark.range(top_n * top_n).select(F.col("id").cast("int").alias("top")), ["top"])
    if epsilon is None:
        return dense
    return dense.select("top", F.greatest(F.lit(0.0), F.col("density") + laplace(1 / epsilon, seed, "grid", "top", source=source)).alias("density"))


def allowed(side: Column) -> Column:
    """The smallest allowed level at or above ``side``; above 3 it is 6."""
    return F.when(side <= 1, 1).when(side <= 2, 2).when(side <= 3, 3).otherwise(6)


def split_factor(density: Column, rule: str, *, mean: Column | None = None, cells_per_top: float = 1.0, cuts: list[float] | None = None, later_epsilon: float = 1.0) -> Column:
    """Sub-cells per side. ``target``: about ``cells_per_top`` cells for an average top cell; ``thresholds``: density cut-offs
    for levels 2, 3, 6; ``noise_guided``: sub-cells whose density stays above the later noise, 6 at most."""
    d = F.round(density, 9)
    if rule == "target":
        return F.coalesce(allowed(F.round(F.sqrt(F.try_divide(d * cells_per_top, mean)), 9)), F.lit(1))
    if rule == "thresholds":
        low, mid, high = (*(cuts or []), *[float("inf")] * 3)[:3]
        return F.when(d >= high, 6).when(d >= mid, 3).when(d >= low, 2).otherwise(1)
    if rule == "noise_guided":
        return allowed(F.round(F.sqrt(d * later_epsilon / cells_per_top), 9))
    raise ValueError(f"unknown split rule: {rule}")


def grid_spec(noisy: DataFrame, rule: str = "target", cells_per_top: float = 1.0, cuts: list[float] | None = None, later_epsilon: float = 1.0) -> DataFrame:
    """``top, density, m, first_cell``: cells are numbered through the top cells in order. The table has N^2 rows."""
    everything = Window.partitionBy(F.lit(0))
    mean = F.avg("density").over(everything)
    cut = noisy.select("top", "density", split_factor(F.col("density"), rule, mean=mean, cells_per_top=cells_per_top, cuts=cuts, later_epsilon=later_epsilon).cast("int").alias("m"))
    before = F.sum(F.col("m") * F.col("m")).over(Window.partitionBy(F.lit(0)).orderBy("top").rowsBetween(Window.unboundedPreceding, -1))
    return cut.withColumn("first_cell", F.coalesce(before, F.lit(0)).cast("int"))


WIDE = 350  # cells above which a table of all pairs is cleaned, normalised and fitted in arrays


@dataclass(frozen=True)
class Grid:
    """A finished grid: levels and first cells of the top cells (N^2 numbers), and where each cell lies."""

    bounds: Bounds
    top_n: int
    levels: tuple[int, ...]
    firsts: tuple[int, ...]

    @property
    def size(self) -> int:
        return self.firsts[-1] + self.levels[-1] ** 2

    def cell_of(self, code: Column) -> Column:
        if len(set(self.levels)) == 1:  # arithmetic in place of two arrays of N^2 numbers
            m = self.levels[0]
            return adaptive_cell(code, lambda top: F.lit(m), lambda top: top * (m * m), self.top_n)
        return statistics.column_of(list(self.levels), list(self.firsts), self.top_n)(code)

    def rectangles(self) -> list[tuple]:
        """(cell, top, sx, sy, x0, x1, y0, y1)."""
        b, out = self.bounds, []
        w, h = (b.x1 - b.x0) / self.top_n, (b.y1 - b.y0) / self.top_n
        for top, (m, first) in enumerate(zip(self.levels, self.firsts)):
            tx, ty = divmod(top, self.top_n)
            for sub in range(m * m):
                sx, sy = divmod(sub, m)
                x, y = b.x0 + (tx + sx / m) * w, b.y0 + (ty + sy / m) * h
                out.append((first + sub, top, sx, sy, x, x + w / m, y, y + h / m))
        return out

    def cells(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rectangles(), "cell int, top int, sx int, sy int, x0 double, x1 double, y0 double, y1 double")

    def neighbour_pairs(self) -> list[tuple[int, int]]:
        """Each cell with itself and the cells that share an edge with it."""
        x0, x1, y0, y1 = np.array([q[4:] for q in self.rectangles()]).T
        eps, out = 1e-9 * max(self.bounds.x1 - self.bounds.x0, self.bounds.y1 - self.bounds.y0), []
        for i in range(len(x0)):
            over_x, over_y = np.minimum(x1[i], x1) - np.maximum(x0[i], x0), np.minimum(y1[i], y1) - np.maximum(y0[i], y0)
            near = (over_x > eps) & (abs(over_y) <= eps) | (over_y > eps) & (abs(over_x) <= eps)
            near[i] = True
            out += [(i, int(j)) for j in np.flatnonzero(near)]
        return out


def build_grid(spec: DataFrame, bounds: Bounds, top_n: int) -> Grid:
    """The N^2 rows of the specification reach the driver; all cell maps are constants from there on."""
    rows = sorted(spec.select("top", "m", "first_cell").collect())
    return Grid(bounds, top_n, tuple(r.m for r in rows), tuple(r.first_cell for r in rows))


def uniform_grid(bounds: Bounds, n: int, top_n: int | None = None) -> Grid:
    """An n x n grid without density: each top cell cut alike where n is a multiple of N, else n itself as N."""
    top = top_n if top_n and n % top_n == 0 and n // top_n in LEVELS else n
    m = n // top
    return Grid(bounds, top, (m,) * top**2, tuple(i * m * m for i in range(top**2)))
