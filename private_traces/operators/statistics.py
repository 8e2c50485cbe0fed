"""What is counted of the real traces: exact, additive, on the leaf lattice or on finished cells.

Every weight depends only on the trace, so statistics on leaves roll up exactly to any adaptive grid.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from private_traces.config import Bounds
from private_traces.functions import lattice


def cell_paths(traces: DataFrame, cell) -> DataFrame:
    """``trace_id, n, cells``: each trace as the cells of its readings; ``cell(x, y)`` gives a Column. No shuffle."""
    return traces.select("trace_id", "n", F.transform("path", lambda p: cell(p["x"], p["y"])).alias("cells"))


def leaf_paths(traces: DataFrame, bounds: Bounds, top_n: int) -> DataFrame:
    return cell_paths(traces, lambda x, y: lattice.leaf(x, y, bounds, top_n))


def grid6_paths(traces: DataFrame, bounds: Bounds) -> DataFrame:
    return cell_paths(traces, lambda x, y: lattice.uniform_cell(x, y, bounds, 6))


def collapsed(paths: DataFrame) -> DataFrame:
    """Repeats of one cell in a row become one; ``n`` follows."""
    kept = F.filter("cells", lambda c, i: F.coalesce(F.get(F.col("cells"), i - 1) != c, F.lit(True)))
    return paths.withColumn("cells", kept).withColumn("n", F.size("cells"))


def density(paths: DataFrame) -> DataFrame:
    """``cell, density``: each reading weighs one over the readings of its trace, so a trace adds 1 in all."""
    each = paths.select("n", F.explode("cells").alias("cell")).groupBy("cell", "n").agg(F.count("*").alias("k"))
    return each.groupBy("cell").agg(F.sum(F.col("k") / F.col("n")).alias("density"))


def density_raw(paths: DataFrame, max_len: int) -> DataFrame:
    """Readings counted plainly, at most ``max_len`` of a trace: sensitivity ``max_len``."""
    return paths.select(F.explode(F.slice("cells", 1, max_len)).alias("cell")).groupBy("cell").agg(F.count("*").cast("double").alias("density"))


def transitions(paths: DataFrame) -> DataFrame:
    """``src, dst, weight``: each move weighs one over the moves of its trace; traces of one reading have none."""
    moves = F.transform(F.slice("cells", F.lit(1), F.col("n") - 1), lambda c, i: F.struct(c.alias("src"), F.get(F.col("cells"), i + 1).alias("dst")))
    each = paths.where("n > 1").select("n", F.inline(moves)).groupBy("src", "dst", "n").agg(F.count("*").alias("k"))
    return each.groupBy("src", "dst").agg(F.sum(F.col("k") / (F.col("n") - 1)).alias("weight"))


def ends(paths: DataFrame) -> DataFrame:
    """``trace_id, n, start_cell, end_cell``."""
    return paths.where("n > 0").select("trace_id", "n", F.get("cells", F.lit(0)).alias("start_cell"), F.get(F.col("cells"), F.col("n") - 1).alias("end_cell"))


def trip_counts(paths: DataFrame) -> DataFrame:
    return ends(paths).groupBy("start_cell", "end_cell").agg(F.count("*").alias("n"))


def length_histogram(paths: DataFrame, max_len: int) -> DataFrame:
    """``start_cell, end_cell, len, n``: traces per number of readings, cut off at ``max_len``."""
    return ends(paths).groupBy("start_cell", "end_cell", F.least("n", F.lit(max_len)).alias("len")).agg(F.count("*").alias("k")).withColumnRenamed("k", "n")


@dataclass
class LeafStatistics:
    """The four statistics of D on the leaf lattice, and the number of traces."""

    top_n: int
    max_len: int
    density: DataFrame
    transitions: DataFrame
    lengths: DataFrame  # also carries the trips: their sum over lengths
    counted: DataFrame | None = None  # what the three are made of, where one pass counts them all

    def roll_up(self, cell_of) -> tuple[DataFrame, DataFrame, DataFrame]:
        """(transitions, trips, length histogram) on the cells that ``cell_of(leaf Column)`` gives. Each leaf table is bounded
        by the lattice, and the map is a Column, so this is one small aggregation each."""
        moved = self.transitions.groupBy(cell_of(F.col("src")).alias("src"), cell_of(F.col("dst")).alias("dst")).agg(F.sum("weight").alias("weight"))
        hist = self.lengths.groupBy(cell_of(F.col("start_cell")).alias("start_cell"), cell_of(F.col("end_cell")).alias("end_cell"), "len").agg(F.sum("n").alias("n"))
        return moved, hist.groupBy("start_cell", "end_cell").agg(F.sum("n").alias("n")), hist

    def top_density(self) -> DataFrame:
        return self.density.groupBy(lattice.top_of(F.col("cell"), self.top_n).alias("top")).agg(F.sum("density").alias("density"))

    def persist(self) -> LeafStatistics:
        for df in self._kept():
            df.persist()
        return self

    def unpersist(self) -> None:
        for df in self._kept():
            df.unpersist()

    def _kept(self) -> tuple[DataFrame, ...]:
        return (self.density, self.transitions, self.lengths) if self.counted is None else (self.counted,)


def leaf_statistics(traces: DataFrame, bounds: Bounds, top_n: int, max_len: int, collapse: bool = False) -> LeafStatistics:
    if not collapse:
        return counted_statistics(traces, bounds, top_n, max_len)
    paths = leaf_paths(traces, bounds, top_n)
    return LeafStatistics(top_n, max_len, density(paths), transitions(collapsed(paths)), length_histogram(paths, max_len))


def counted_statistics(traces: DataFrame, bounds: Bounds, top_n: int, max_len: int, cells: np.ndarray | None = None) -> LeafStatistics:
    """The statistics of the leaves, or of the cells that ``cells`` maps them to, from one pass over the traces in arrays: it counts by
    cells and readings, and the weights are made of the counts."""
    side = lattice.FINE * top_n

    def parts(v: np.ndarray, low: float, high: float) -> np.ndarray:
        return np.clip(np.nan_to_num(np.floor((v - low) / (high - low) * side), nan=0.0), 0, side - 1).astype(np.int64)

    def grouped(kind: int, a: np.ndarray, b: np.ndarray, k: np.ndarray):
        wide, most = int(b.max(initial=0)) + 1, int(k.max(initial=0)) + 1
        key, n = np.unique((a * wide + b) * most + k, return_counts=True)
        a, b, k = key // most // wide, key // most % wide, key % most
        return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in ((np.full(len(key), kind), pa.int32()), (a, pa.int32()), (b, pa.int32()), (k, pa.int32()), (n, pa.int64()))], ["kind", "a", "b", "k", "n"])

    def count(batches):
        for batch in batches:
            size = np.diff(batch.column("xs").offsets.to_numpy()).astype(np.int64)
            x, y = (batch.column(c).flatten().to_numpy() for c in ("xs", "ys"))
            cell = parts(x, bounds.x0, bounds.x1) * side + parts(y, bounds.y0, bounds.y1)
            cell = cell if cells is None else cells[cell]
            size = size[size > 0]
            upto, each = np.cumsum(size), np.repeat(size, size)
            at = np.flatnonzero(np.arange(len(cell)) < np.repeat(upto, size) - 1)
            yield grouped(0, cell, np.zeros_like(cell), each)
            yield grouped(1, cell[at], cell[at + 1], each[at])
            yield grouped(2, cell[upto - size], cell[upto - 1], np.minimum(size, max_len))

    rows = traces.select(F.col("path.x").alias("xs"), F.col("path.y").alias("ys")).mapInArrow(count, "kind int, a int, b int, k int, n long")
    held = rows.groupBy("kind", "a", "b", "k").agg(F.sum("n").alias("n"))
    density = held.where("kind = 0").groupBy(F.col("a").alias("cell")).agg(F.sum(F.col("n") / F.col("k")).alias("density"))
    moved = held.where("kind = 1").groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.sum(F.col("n") / (F.col("k") - 1)).alias("weight"))
    lengths = held.where("kind = 2").select(F.col("a").alias("start_cell"), F.col("b").alias("end_cell"), F.col("k").alias("len"), "n")
    return LeafStatistics(top_n, max_len, density, moved, lengths, held)


def direct_statistics(traces: DataFrame, bounds: Bounds, top_n: int, max_len: int, cell_of, collapse: bool = False):
    """The same three statistics straight from the traces, for options under which leaves do not roll up."""
    paths = leaf_paths(traces, bounds, top_n)
    paths = paths.withColumn("cells", F.transform("cells", cell_of))
    moved = collapsed(paths) if collapse else paths
    return transitions(moved), trip_counts(paths), length_histogram(paths, max_len)


def column_of(levels: list[int], firsts: list[int], top_n: int):
    """The map from leaf to adaptive cell as a function of Columns."""
    a, b = F.array(*[F.lit(x) for x in levels]), F.array(*[F.lit(x) for x in firsts])
    return lambda code: lattice.adaptive_cell(code, a, b, top_n)


def as_column(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x
