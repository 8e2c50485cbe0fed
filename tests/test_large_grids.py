"""Walks of many ends at a time on grids with more cells than a task holds the pairs of."""

import numpy as np

from private_traces.config import Bounds
from private_traces.operators import generator
from private_traces.operators.grid import uniform_grid


def test_walks_by_groups_of_ends_are_those_by_end(spark, monkeypatch):
    rng = np.random.default_rng(6)
    p = rng.dirichlet(np.full(12, 0.3), 12) * (rng.random((12, 12)) < 0.5) + 0.01 * np.eye(12)
    p[3:6, 6:] = 0
    p /= p.sum(axis=1, keepdims=True)
    start, end, n = rng.integers(0, 12, 500), rng.integers(0, 12, 500), rng.integers(1, 9, 500)
    end = np.where(n == 1, start, end)
    want = {}
    for e in range(12):
        own = np.flatnonzero(end == e)
        out, jumped = generator.bridge_paths(p, e, start[own], n[own], generator._uniforms(5, own, int(n[own].max())))
        want |= {int(i): (row[: n[i]].tolist(), bool(j)) for i, row, j in zip(own, out, jumped)}
    trips = spark.createDataFrame([(i, int(start[i]), int(end[i]), int(n[i])) for i in range(500)], "trace_id long, start_cell int, end_cell int, n int")
    moves = spark.createDataFrame([(i, j, float(p[i, j])) for i in range(12) for j in range(12)], "src int, dst int, prob double")
    monkeypatch.setattr(generator, "DENSE", 5)
    found = {r.trace_id: (list(r.cells), r.jumped) for r in generator.walk(trips, moves, 12, 5).collect()}
    assert found == want


def test_neighbours_of_a_large_grid_share_an_edge():
    pairs = set(uniform_grid(Bounds(0.0, 1.0, 0.0, 1.0), 50, 6).neighbour_pairs())
    assert pairs == {(a, b) for a in range(2500) for b in (a, a - 1, a + 1, a - 50, a + 50) if 0 <= b < 2500 and (abs(a % 50 - b % 50) + abs(a // 50 - b // 50) <= 1)}
