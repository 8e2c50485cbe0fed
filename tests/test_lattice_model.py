"""The evaluation in arrays against the DataFrame path."""

import numpy as np
import pytest

from private_traces.config import Bounds, SynthesisConfig, equal_split
from private_traces.operators import generator, lattice_model, metrics, statistics, synopsis, tuning
from private_traces.sources import views

UNIT = Bounds(0.0, 1.0, 0.0, 1.0)
QUARTERS = np.full(4, 0.25)


@pytest.fixture(scope="module")
def sides(spark, sf):
    traces = views.drift_trips(spark, sf).persist()
    real, stats = metrics.RealSide(traces, UNIT), statistics.leaf_statistics(traces, UNIT, 6, 32).persist()
    return real, stats, lattice_model.tables(real, stats)


@pytest.mark.parametrize("changes", [{}, {"test": "ks"}, {"test": "loglik", "split_rule": "thresholds", "cuts": (5.0, 20.0, 60.0)}, {"uniform_grid": 12}, {"split_rule": "noise_guided"}])
def test_the_synopsis_is_the_same_without_noise(sides, changes):
    _, stats, t = sides
    cfg = SynthesisConfig(epsilon=None, seed=1, **changes)
    own, other = lattice_model.synopsis(t, cfg, QUARTERS, np.random.default_rng(0)), synopsis.extract_synopsis(None, UNIT, equal_split(), cfg, stats)
    assert own.grid.levels == other.grid.levels and own.noisy_total == other.noisy_total
    moves, trips = np.zeros((own.grid.size,) * 2), np.zeros(own.grid.size**2)
    for r in other.mobility.collect():
        moves[r.src, r.dst] = r.prob
    for r in other.trips.collect():
        trips[r.start_cell * own.grid.size + r.end_cell] = r.prob
    cdf = {r.start_cell * own.grid.size + r.end_cell: r.cdf for r in generator.length_tables(other.lengths, 32).collect()}
    assert np.allclose(moves, own.mobility, atol=1e-12) and np.allclose(trips, own.trips, atol=1e-12)
    assert len(cdf) == len(own.pairs) and np.allclose([cdf[p] for p in own.pairs.tolist()], own.cdf, atol=1e-9)


def test_the_errors_are_the_same_on_the_same_traces(spark, sides):
    real, _, t = sides
    rng = np.random.default_rng(3)
    model = lattice_model.synopsis(t, SynthesisConfig(seed=1), QUARTERS, rng)
    first, x, y, _ = lattice_model.made(model, 900, rng)
    path = "trace_id long, n int, path array<struct<seq:int,x:double,y:double,ts:timestamp_ntz>>"
    rows = [(i, int(b - a), [(k + 1, float(x[a + k]), float(y[a + k]), None) for k in range(b - a)]) for i, (a, b) in enumerate(zip(first, first[1:]))]
    made = spark.createDataFrame(rows, path).persist()
    own = lattice_model.errors(t, first, x, y, real.total / 900)
    for m in lattice_model.FOUR:
        assert own[m] == pytest.approx(metrics.REGISTRY[m](real, made, real.total / 900).first().value, abs=1e-9)


def test_walks_are_pinned_and_follow_the_conditional_law(sides):
    _, _, t = sides
    rng = np.random.default_rng(5)
    model = lattice_model.synopsis(t, SynthesisConfig(epsilon=None, seed=1, uniform_grid=6), QUARTERS, rng)
    rect = np.array([r[4:] for r in model.grid.rectangles()])
    first, x, y, _ = lattice_model.made(model, 40_000, rng)
    cells = np.array([np.flatnonzero((rect[:, 0] <= a) & (a < rect[:, 1]) & (rect[:, 2] <= b) & (b < rect[:, 3]))[0] for a, b in zip(x[:4000], y[:4000])])
    whole = first[first < 4000]
    assert set((cells[whole[:-1]] * 36 + cells[whole[1:] - 1]).tolist()) <= set(model.pairs.tolist())
    grid6 = np.floor(x * 6).astype(int) * 6 + np.floor(y * 6).astype(int)
    p, three = model.mobility, first[:-1][np.diff(first) == 3]
    (a, b), count = (lambda v: ((int(v[0]) // 36, int(v[0]) % 36), v[1]))(max(zip(*np.unique(grid6[three] * 36 + grid6[three + 2], return_counts=True)), key=lambda v: v[1]))
    mid = grid6[three[(grid6[three] == a) & (grid6[three + 2] == b)] + 1]
    law = p[a] * p[:, b] / (p[a] * p[:, b]).sum()
    assert abs(np.bincount(mid, minlength=36) / count - law).max() < 5 * np.sqrt(0.25 / count)


def test_a_batch_and_a_guided_search(spark, sides):
    real, stats, t = sides
    cfg = SynthesisConfig(seed=7)
    points = tuning.explored(6, 1)
    frame = lattice_model.evaluate_all(real, stats, cfg, points, 300, 7)
    assert frame.count() == 24 and frame.where("value < 0").count() == 0
    bench = lattice_model.Bench(spark, {"a": t})
    one, two = bench.run([("a", cfg, points[0], 7, 300)] * 2)
    assert one == two == lattice_model.one_run(t, cfg, points[0], 7, 300)
    known = [r["trip_error"] for r in bench.run([("a", cfg, w, 7, 300) for w in points], ("trip_error",))]
    ((w, history),) = bench.guide([("a", cfg, points, known, 3, 7, 300)])
    assert len(history) == 9 and [h[1] for h in history].count("guided") == 3 and abs(w.sum() - 1) < 1e-9
    assert history[-1][8] == min(h[7] for h in history) <= min(known)


def test_what_arrays_cannot_do_is_refused(sides):
    for changes in ({"collapse_repeats": True}, {"params_from": "moments"}, {"mechanism": "geometric"}):
        with pytest.raises(ValueError):
            lattice_model.synopsis(sides[2], SynthesisConfig(**changes), QUARTERS, np.random.default_rng(0))
        assert not tuning.in_arrays(SynthesisConfig(**changes))
    assert tuning.in_arrays(SynthesisConfig()) and not tuning.in_arrays(SynthesisConfig(metric="speed_error"))


def test_walks_by_rows_are_those_by_end():
    rng = np.random.default_rng(2)
    p = rng.dirichlet(np.full(12, 0.3), 12)
    p[3:6, 6:] = 0
    p[3:6] /= p[3:6].sum(axis=1, keepdims=True)
    start, end, n = rng.integers(0, 12, 500), rng.integers(0, 12, 500), rng.integers(1, 9, 500)
    end = np.where(n == 1, start, end)
    u = rng.random((500, 9))
    power = [np.eye(12)]
    for _ in range(8):
        power.append(p @ power[-1])
    rows, jump = generator.bridge_rows(p, np.stack(power), start, end, n, u)
    for e in range(12):
        own = np.flatnonzero(end == e)
        out, jumped = generator.bridge_paths(p, e, start[own], n[own], u[own])
        assert (out == rows[own][:, : out.shape[1]]).all() and (jumped == jump[own]).all()


def test_jumps_are_counted(spark):
    walks = spark.createDataFrame([(1, 2, [0, 1], True), (2, 2, [0, 1], False), (3, 1, [0], False)], "trace_id long, n int, cells array<int>, jumped boolean")
    assert {(r.n, r.traces, r.jumped) for r in generator.jumps(walks).collect()} == {(2, 2, 1), (1, 1, 0)}


def test_halving_and_bins_find_what_a_full_look_finds():
    rng = np.random.default_rng(4)
    for size in (1, 2, 5, 8, 77):
        cum = np.cumsum(rng.random((30, size)) * (rng.random((30, size)) < 0.5), axis=1)
        cum = cum[cum[:, -1] > 0]
        row, u = rng.integers(0, len(cum), 3000), rng.random(3000)
        assert (lattice_model._landed(cum, row, u) == np.minimum((cum[row] <= (u * cum[row, -1])[:, None]).sum(axis=1), size - 1)).all()
    low = np.round(rng.random(200) * 0.9, 3)
    axis = lattice_model.Axis(low, low + 0.05, bins=64)
    v = np.r_[rng.random(5000) * 1.4 - 0.2, axis.edges]
    bits = np.unpackbits(np.ascontiguousarray(axis.words[:, axis.interval(v)].T).view(np.uint8), axis=1)[:, :200]
    assert (bits == ((low <= v[:, None]) & (v[:, None] < low + 0.05))).all()


def test_equal_requests_are_run_once():
    class Asked(Exception):
        pass

    class Session:
        sparkContext = property(lambda self: self)
        defaultParallelism = 8
        broadcast = staticmethod(lambda value: value)

        def range(self, start, end, *_):
            raise Asked(end)

    cfg = SynthesisConfig(seed=1)
    with pytest.raises(Asked) as asked:
        lattice_model.Bench(Session(), {}).run([("a", cfg.but(metric=m), QUARTERS, 7, None) for m in lattice_model.FOUR] + [("a", cfg, QUARTERS, 8, None)])
    assert asked.value.args == (2,)


def test_a_full_size_run_holds_a_block_of_traces_at_a_time(monkeypatch):
    rng, cells = np.random.default_rng(8), 36
    model = lattice_model.Model(lattice_model.uniform_grid(UNIT, 6, 6), rng.dirichlet(np.ones(cells), cells), np.full(cells**2, cells**-2.0), np.full(cells**2, 0.2), np.arange(cells**2), np.tile([0.5, 1.0], (cells**2, 1)))
    none = np.zeros(0, np.int64)
    t = lattice_model.Tables(UNIT, 6, 2, np.ones(36), (none,) * 3, (none,) * 4, np.array([[0.0, 1.0, 0.0, 1.0]]), np.array([250.0]), [(0, 1)], np.ones(1), np.ones((36, 36)), np.ones(20), 1.5, 250)
    held, walked, parts = [], lattice_model.walked, []
    monkeypatch.setattr(lattice_model, "synopsis", lambda *_: model)
    monkeypatch.setattr(lattice_model, "walked", lambda m, n, r: held.append(n) or walked(m, n, r))
    monkeypatch.setattr(lattice_model, "BLOCK", 100)
    monkeypatch.setattr(lattice_model, "PART", 30)
    add = lattice_model.Measure.add
    monkeypatch.setattr(lattice_model.Measure, "add", lambda self, xs, ys: parts.append(len(xs[0])) or add(self, xs, ys))
    got = lattice_model.one_run(t, SynthesisConfig(seed=1), QUARTERS, 1, 250)
    assert held == [100, 100, 50] and sum(parts) == 250 and max(parts) == 30 and got["query_error"] == 0
