"""One run of synopsis, generator and metrics in arrays, for many candidate splits at once.

The leaf statistics, the workload and the real answers are bounded by the lattice and the workload, not by the data; they are
taken once, checked, and broadcast. A candidate is one row of a job: its task draws the noise, makes a bounded number of traces and
measures them, so a batch of candidates is one stage without a shuffle. Releases of full size go through the DataFrame path.
"""

from __future__ import annotations

import json
import math
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from private_traces.config import Bounds, SynthesisConfig
from private_traces.functions.lattice import FINE

from . import metrics, statistics
from .grid import Grid, uniform_grid

FOUR = ("query_error", "pattern_support_error", "trip_error", "travel_distance_error")
MOST_ROWS = 6_000_000  # of a leaf table; beyond it the DataFrame path is the way
BLOCK = 500_000  # traces walked at a time
READINGS = 1_000_000  # real readings counted at a time
PART = 32_768  # traces placed and measured at a time
HELD = 128_000_000  # bytes of tables that a model keeps for its next traces
GUIDE = 128  # starting points a row of a table that is used again
TABLE = 4_000  # walkers for which a table of all ends and cells is less work than their rows


@dataclass
class Tables:
    """Leaf statistics and the real side of the four metrics as arrays."""

    bounds: Bounds
    top_n: int
    max_len: int
    density: np.ndarray
    moves: tuple[np.ndarray, np.ndarray, np.ndarray]
    lengths: tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]
    regions: np.ndarray
    region_counts: np.ndarray
    patterns: list[tuple[int, ...]]
    supports: np.ndarray
    trips6: np.ndarray
    histogram: np.ndarray
    longest: float
    total: int


def _columns(df: DataFrame, *names: str) -> tuple[np.ndarray, ...]:
    rows = df.count()
    if rows > MOST_ROWS:
        raise ValueError(f"{rows} rows of a leaf table: use the DataFrame path")
    got = df.select(*names).toArrow()
    return tuple(got.column(c).to_numpy() for c in names)


def tables(real: metrics.RealSide, stats: statistics.LeafStatistics) -> Tables:
    top, mass = _columns(stats.top_density(), "top", "density")
    density = np.zeros(stats.top_n**2)
    density[top] = mass
    regions = real.regions.orderBy("qid").toArrow()
    counts = dict(zip(*_columns(real.region_counts, "qid", "n")))
    mined = real.mined.collect()
    trips6 = np.zeros((36, 36))
    a, b, n = _columns(real.trips, "start_cell", "end_cell", "mass")
    trips6[a, b] = n
    histogram = np.zeros(20)
    at, n = _columns(real.histogram, "bucket", "mass")
    histogram[at] = n
    return Tables(
        real.bounds, stats.top_n, stats.max_len, density, _columns(stats.transitions, "src", "dst", "weight"), _columns(stats.lengths, "start_cell", "end_cell", "len", "n"),
        np.stack([regions.column(c).to_numpy() for c in ("x0", "x1", "y0", "y1")], axis=1), np.array([counts.get(q, 0) for q in regions.column("qid").to_pylist()], float),
        [tuple(map(int, r.pattern.split(">"))) for r in mined], np.array([r.support for r in mined], float), trips6, histogram, real.longest, real.total,
    )


def _keys(t: Tables, first: np.ndarray, x: np.ndarray, y: np.ndarray, low: int, high: int):
    """(kind, key, second key, number) of what ``real_tables`` counts of whole traces, one array each."""
    size, b = np.diff(first), t.bounds
    axis = lambda v, start, end, n: np.clip(np.floor((v - start) / (end - start) * n), 0, n - 1).astype(np.int64)
    cells = lambda n: axis(x, b.x0, b.x1, n) * n + axis(y, b.y0, b.y1, n)
    side = FINE * t.top_n
    leaf, six = cells(side), cells(6)
    each = np.repeat(size, size)
    more = np.arange(len(x)) < np.repeat(first[1:], size) - 1  # readings with another one after them
    top = leaf // side // FINE * t.top_n + leaf % side // FINE
    at = np.flatnonzero(more)
    starts, ends = leaf[first[:-1]], leaf[first[1:] - 1]

    def counted(kind: str, key: np.ndarray, second: np.ndarray):
        wide = int(second.max(initial=0)) + 1
        both, n = np.unique(key * wide + second, return_counts=True)
        return np.full(len(n), KINDS.index(kind)), both // wide, both % wide, n

    yield counted("density", top, each)
    yield counted("moves", leaf[at] * side**2 + leaf[at + 1], each[at])
    yield counted("lengths", starts * side**2 + ends, np.minimum(size, t.max_len))
    code = six + 1
    for k in range(2, high + 1):  # runs of k readings: digits of base 37, none of them 0
        at = at[more[at + k - 2]] if k > 2 else at
        if not len(at):
            break
        code[at] = code[at] * 37 + six[at + k - 1] + 1
        if k >= low:
            yield counted("patterns", code[at], np.zeros(len(at), np.int64))
    order = np.argsort(-size, kind="stable")
    last, most = first[1:][order] - 1, int(size.max(initial=0))
    packed = [last[: np.searchsorted(-size[order], -r, side="left")] - r for r in range(most)]
    found, d = Measure(t, ("query_error", "trip_error")), np.zeros(len(size))
    xs, ys = [x[a] for a in packed], [y[a] for a in packed]
    for r in range(most - 1, 0, -1):
        k = len(xs[r])
        d[:k] += np.sqrt((xs[r - 1][:k] - xs[r]) ** 2 + (ys[r - 1][:k] - ys[r]) ** 2)
    for s in range(0, len(size), PART):
        found.add([a[s : s + PART] for a in xs if len(a) > s], [a[s : s + PART] for a in ys if len(a) > s])
    yield counted("distances", np.rint(d * 1e9).astype(np.int64), np.zeros(len(d), np.int64))
    for kind, n in (("regions", found.hits), ("trips", found.trips)):
        key = np.flatnonzero(n)
        yield np.full(len(key), KINDS.index(kind)), key, np.zeros(len(key), np.int64), n[key]


KINDS = ("density", "moves", "lengths", "patterns", "distances", "regions", "trips")


def real_tables(rows: DataFrame, positions, bounds: Bounds, top_n: int, max_len: int, k: int = 100, low: int = 2, high: int = 8, queries: int = 200, seed: int = 42, buckets: int = 20) -> Tables:
    """What ``tables`` gives of ``RealSide`` and the leaf statistics, from one pass over rows that come sorted by trace.

    ``rows``: ``trace_id`` and what ``positions(first, *columns)`` turns into x and y; each trace whole in one partition and in order. A task
    counts ``READINGS`` at a time, and only whole numbers by key leave it, so no sum depends on how traces are dealt. Kept are the keys
    with their numbers, the distances among them as billionths."""
    if not 2 <= low <= high <= 8:
        raise ValueError("patterns have 2 to 8 cells")
    spark = rows.sparkSession
    regions = metrics.random_regions(spark, bounds, queries, seed).orderBy("qid").toArrow()
    rectangles = np.stack([regions.column(c).to_numpy() for c in ("x0", "x1", "y0", "y1")], axis=1)
    none = np.zeros(0, np.int64)
    empty = Tables(bounds, top_n, max_len, np.zeros(top_n**2), (none,) * 3, (none,) * 4, rectangles, np.zeros(queries), [], np.zeros(0), np.zeros((36, 36)), np.zeros(buckets), 0.0, 0)
    values = [c for c in rows.columns if c != "trace_id"]

    def count(batches):
        held, waiting = [], 0

        def flush(last: bool):
            whole = pa.Table.from_batches(held)
            ids = whole.column("trace_id").to_numpy()
            first = np.r_[0, np.flatnonzero(ids[1:] != ids[:-1]) + 1, len(ids)]
            if not last:  # the last trace may go on
                first = first[:-1]
            held[:] = whole.slice(first[-1]).combine_chunks().to_batches()
            if len(first) > 1:
                x, y = positions(first, *(whole.column(c).to_numpy()[: first[-1]] for c in values))
                for found in _keys(empty, first, x, y, low, high):
                    yield pa.RecordBatch.from_arrays([pa.array(a, t) for a, t in zip(found, (pa.int32(), pa.int64(), pa.int32(), pa.int64()))], ["kind", "a", "b", "n"])

        for batch in batches:
            if batch.num_rows:
                held.append(batch)
                waiting += batch.num_rows
            if waiting >= READINGS:
                yield from flush(False)
                waiting = 0
        if held:
            yield from flush(True)

    sums = rows.mapInArrow(count, "kind int, a long, b int, n long").groupBy("kind", "a", "b").agg(F.sum("n").alias("n")).persist()
    of = lambda kind: sums.where(F.col("kind") == KINDS.index(kind))
    side = (FINE * top_n) ** 2
    density, trips6, hits, histogram = np.zeros(top_n**2), np.zeros(1296), np.zeros(queries), np.zeros(buckets)
    at, mass = _columns(of("density").groupBy("a").agg(F.sum(F.col("n") / F.col("b")).alias("mass")), "a", "mass")
    density[at] = mass
    move, weight = _columns(of("moves").groupBy("a").agg(F.sum(F.col("n") / (F.col("b") - 1)).alias("weight")), "a", "weight")
    ends, length, n = _columns(of("lengths"), "a", "b", "n")
    for kind, into in (("trips", trips6), ("regions", hits)):
        at, found = _columns(of(kind), "a", "n")
        into[at] = found
    digits = F.transform(F.sequence(F.lit(high - 1), F.lit(0), F.lit(-1)), lambda i: (F.floor(F.col("a") / F.pow(F.lit(37), i)) % 37).cast("int"))
    text = F.array_join(F.transform(F.filter(digits, lambda c: c > 0), lambda c: (c - 1).cast("string")), ">")
    mined = of("patterns").select(text.alias("pattern"), F.col("n").alias("support")).orderBy(F.desc("support"), "pattern").limit(k).collect()  # k rows
    d = of("distances").select((F.col("a") / 1e9).alias("d"), "n")
    longest = d.agg(F.coalesce(F.max("d"), F.lit(0.0)).alias("m")).first().m
    width = longest / buckets
    bucket = F.least(F.floor(F.col("d") / width), F.lit(buckets - 1)) if width > 0 else F.lit(0)
    at, found = _columns(d.where(F.col("d") <= longest).groupBy(bucket.cast("int").alias("bucket")).agg(F.sum("n").alias("mass")), "bucket", "mass")
    histogram[at] = found
    sums.unpersist()
    return replace(
        empty, density=density, moves=(move // side, move % side, weight), lengths=(ends // side, ends % side, length, n), region_counts=hits, patterns=[tuple(map(int, r.pattern.split(">"))) for r in mined],
        supports=np.array([r.support for r in mined], float), trips6=trips6.reshape(36, 36), histogram=histogram, longest=longest, total=int(trips6.sum()),
    )


def levelled(masses: np.ndarray, mode: str, want: np.ndarray | None = None) -> np.ndarray:
    """Rows of non-negative masses; ``shift`` takes one constant from each row so that its sum stays."""
    if mode != "shift":
        return np.maximum(masses, 0)
    want = np.maximum(masses.sum(axis=1) if want is None else want, 0)
    down = -np.sort(-masses, axis=1)
    level = (np.cumsum(down, axis=1) - want[:, None]) / np.arange(1, masses.shape[1] + 1)
    last = masses.shape[1] - 1 - (down > level)[:, ::-1].argmax(axis=1)
    out = np.maximum(masses - level[np.arange(len(level)), last][:, None], 0)
    out[want <= 0] = 0
    return out


def split_levels(density: np.ndarray, cfg: SynthesisConfig, later: float) -> np.ndarray:
    d, mean = np.round(density, 9), density.mean()
    if cfg.split_rule == "thresholds":
        low, mid, high = (*cfg.cuts, *[math.inf] * 3)[:3]
        return np.select([d >= high, d >= mid, d >= low], [6, 3, 2], 1)
    if cfg.split_rule == "target":
        side = np.round(np.sqrt(d * cfg.cells_per_top / mean), 9) if mean > 0 else np.ones(len(d))
    else:
        side = np.round(np.sqrt(d * later / cfg.cells_per_top), 9)
    return np.select([side <= 1, side <= 2, side <= 3], [1, 2, 3], 6)


def leaf_map(grid: Grid) -> np.ndarray:
    """The cell of every leaf."""
    side = FINE * grid.top_n
    gx, gy = np.divmod(np.arange(side * side), side)
    top = gx // FINE * grid.top_n + gy // FINE
    m = np.array(grid.levels)[top]
    return np.array(grid.firsts)[top] + gx % FINE * m // FINE * m + gy % FINE * m // FINE


def _beside(rect: np.ndarray, bounds: Bounds) -> np.ndarray:
    """Which cells are the same or share an edge."""
    eps = 1e-9 * max(bounds.x1 - bounds.x0, bounds.y1 - bounds.y0)
    x0, x1, y0, y1 = rect.T
    over_x = np.minimum(x1[:, None], x1) - np.maximum(x0[:, None], x0)
    over_y = np.minimum(y1[:, None], y1) - np.maximum(y0[:, None], y0)
    return np.eye(len(rect), dtype=bool) | (over_x > eps) & (abs(over_y) <= eps) | (over_y > eps) & (abs(over_x) <= eps)


def length_probabilities(mean: np.ndarray, most: int) -> np.ndarray:
    """Probabilities of lengths 1..most under the three laws: (family, pair, length)."""
    length, mean = np.arange(1, most + 1), mean[:, None]
    upper = np.minimum(most, np.maximum(1, np.floor(2 * mean - 1 + 0.5)))
    rate, step = np.maximum(mean - 1, 1e-9), 1 / np.maximum(mean, 1e-9)
    logs = np.array([math.lgamma(k) for k in length])
    raw = np.stack([np.where(length <= upper, 1 / upper, 0), np.exp((length - 1) * np.log(rate) - rate - logs), np.exp(-(length - 1) * step) - np.exp(-length * step)])
    whole = raw.sum(axis=2, keepdims=True)
    return np.divide(raw, whole, out=np.zeros_like(raw), where=whole > 0)


def misfits(hist: np.ndarray, test: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(misfit by family, mean, support) of rows of length counts."""
    most, total = hist.shape[1], hist.sum(axis=1)
    mean = np.divide(hist @ np.arange(1, most + 1), total, out=np.ones(len(hist)), where=total > 0)
    law = length_probabilities(mean, most)
    expected = law * total[:, None]
    if test == "chi2":
        miss = ((hist - expected) ** 2 / np.maximum(expected, 0.5)).sum(axis=2)
    elif test == "loglik":
        miss = -(hist * np.log(np.maximum(np.where(total[:, None] > 0, law, 0), 1e-9))).sum(axis=2)
    else:
        gap = np.abs(np.cumsum(hist - expected, axis=2)).max(axis=2)
        miss = np.divide(gap, total, out=np.zeros_like(gap), where=total > 0)
    return np.round(miss, 9), mean, total


def _fitted(hist: np.ndarray, test: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(family, mean, support) of rows of length counts."""
    miss, mean, total = misfits(hist, test)
    return miss.argmin(axis=0), mean, total


@dataclass
class Model:
    """A synopsis in arrays."""

    grid: Grid
    mobility: np.ndarray
    trips: np.ndarray
    mass: np.ndarray
    pairs: np.ndarray
    cdf: np.ndarray
    held: dict = field(default_factory=dict, repr=False, compare=False)  # what traces of this model need again

    @property
    def noisy_total(self) -> int:
        return max(0, round(float(self.mass[self.trips > 0].sum())))


def synopsis(t: Tables, cfg: SynthesisConfig, w: np.ndarray, rng: np.random.Generator) -> Model:
    """The four noisy statistics, by the same steps as ``extract_synopsis``; options that need the traces are not taken."""
    if cfg.collapse_repeats or cfg.params_from != "histogram" or cfg.fit_on != "noisy" or cfg.noise_on != "count" or cfg.mechanism != "laplace":
        raise ValueError("these settings go through the DataFrame path")
    e = cfg.epsilon
    noise = (lambda shape, share: 0.0) if e is None else (lambda shape, share: rng.laplace(scale=1 / (e * share), size=shape))
    if cfg.uniform_grid is None:
        density = t.density if e is None else np.maximum(0, t.density + noise(t.density.shape, w[0]))
        levels = split_levels(density, cfg, (e or 1.0) * (1 - w[0]))
        grid = Grid(t.bounds, t.top_n, tuple(levels.tolist()), tuple(np.r_[0, np.cumsum(levels**2)[:-1]].tolist()))
    else:
        grid = uniform_grid(t.bounds, cfg.uniform_grid, t.top_n)
        if grid.top_n != t.top_n:
            raise ValueError("this grid does not roll up from the leaves")
    size, cell = grid.size, leaf_map(grid)
    rect = np.array([r[4:] for r in grid.rectangles()])
    moves = np.zeros((size, size))
    moves += np.bincount(cell[t.moves[0]] * size + cell[t.moves[1]], t.moves[2], size * size).reshape(size, size)
    moves = moves if e is None else levelled(moves + noise(moves.shape, w[1]), cfg.clean_up)
    whole = moves.sum(axis=1, keepdims=True)
    even = _beside(rect, t.bounds)
    mobility = np.where(whole > 0, moves / np.where(whole > 0, whole, 1), even / even.sum(axis=1, keepdims=True))
    a, b, length, n = cell[t.lengths[0]], cell[t.lengths[1]], t.lengths[2], t.lengths[3]
    mass = np.bincount(a * size + b, n, size * size)
    if e is not None:
        share = w[2] / 2 if cfg.total == "separate" else w[2]
        want = np.array([t.lengths[3].sum() + noise((), share)]) if cfg.total == "separate" else None
        mass = levelled(mass[None] + noise((1, size * size), share), cfg.clean_up, want)[0]
    trips = mass / mass.sum() if mass.sum() > 0 else np.full(size * size, 1 / size**2)
    pairs = np.flatnonzero(trips > 0)
    place = np.full(size * size, -1)
    place[pairs] = np.arange(len(pairs))
    hist = np.zeros((len(pairs), t.max_len))
    at = place[a * size + b]
    hist += np.bincount(at[at >= 0] * t.max_len + length[at >= 0] - 1, n[at >= 0], hist.size).reshape(hist.shape)
    pool = cfg.pool_share if e is not None else 0.0
    if e is not None:
        hist = np.maximum(0, hist + noise(hist.shape, w[3] * (1 - pool)))
    family, mean, support = _fitted(hist, cfg.test)
    if e is None or pool > 0:
        everything = np.bincount(length - 1, n, t.max_len)[None]
        if e is not None:
            everything = np.maximum(0, everything + noise(everything.shape, w[3] * pool))
        (f0,), (m0,), _ = _fitted(everything, cfg.test)
        weak = support < cfg.min_support
        family, mean = np.where(weak, f0, family), np.where(weak, m0, mean)
    law = length_probabilities(mean, t.max_len)[family, np.arange(len(pairs))]
    cdf = np.cumsum(law, axis=1)
    return Model(grid, mobility, trips, mass, pairs, np.where(law.sum(axis=1, keepdims=True) > 0, np.round(cdf, 12), 1.0))


def drawn(m: Model, n: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    """(place in ``pairs``, number of readings) of ``n`` independent traces, longest first and those of one length by their end: how many
    have which pair and length is one multinomial draw, which is the law of the draws one by one, whose order no metric sees."""
    if "joint" not in m.held:
        law = np.diff(m.cdf, axis=1, prepend=0.0)
        law[:, -1] += np.maximum(0, 1 - m.cdf[:, -1])
        start, end = np.divmod(m.pairs, m.grid.size)
        if law.shape[1] > 1:  # different ends take two readings at least
            apart = start != end
            law[apart, 1] += law[apart, 0]
            law[apart, 0] = 0
        order = np.lexsort((start, end))
        joint = np.ascontiguousarray((m.trips[m.pairs][:, None] * law)[order].T[::-1]).ravel()
        some = np.flatnonzero(joint > 0)
        length, pick = np.divmod(some, len(m.pairs))
        m.held["joint"] = joint[some] / joint[some].sum(), order[pick], law.shape[1] - length
    share, pick, length = m.held["joint"]
    count = rng.multinomial(n, share)
    return np.repeat(pick, count), np.repeat(length, count)


def _landed(cum: np.ndarray, row: np.ndarray, u: np.ndarray) -> np.ndarray:
    """How many of the running sums of a row are at most ``u`` of its last one, by halving; one short of all at most."""
    size = cum.shape[-1]
    flat, base = cum.reshape(-1), row * size
    want, step = u * flat[base + (size - 1)], 1 << (size.bit_length() - 1)
    at = base + (size - step) * (flat[base + (step - 1)] <= want)
    while step > 1:
        step //= 2
        at += step * (flat[at + (step - 1)] <= want)
    at += flat[at] <= want
    return np.minimum(at - base, size - 1)


def _guide(cum: np.ndarray) -> np.ndarray:
    """For rows of running sums that end in 1: how many are at most k / GUIDE, for each k below GUIDE."""
    rows, size = cum.shape
    at = np.minimum(np.ceil(cum * GUIDE), GUIDE).astype(np.int64) + np.arange(rows)[:, None] * (GUIDE + 1)
    found = np.bincount(at.ravel(), minlength=rows * (GUIDE + 1)).reshape(rows, GUIDE + 1)[:, :GUIDE]
    return np.cumsum(found, axis=1).astype(np.uint16 if size < 65536 else np.int64)


def _led(cum: np.ndarray, guide: np.ndarray, row: np.ndarray, u: np.ndarray) -> np.ndarray:
    """What ``_landed`` finds in such rows, from the guide on."""
    flat, base = cum.reshape(-1), row * cum.shape[-1]
    at = base + guide.reshape(-1).take(row * GUIDE + (u * GUIDE).astype(np.int64))
    short = np.flatnonzero(flat.take(at) <= u)
    while len(short):
        at[short] += 1
        short = short[flat.take(at[short]) <= u[short]]
    at -= base
    return at


def _table(m: Model, r: int, reach: np.ndarray, free: np.ndarray) -> np.ndarray:
    """Running sums over the next cell by end and cell with r moves to go, each row up to 1; where the end is out of reach, a free move."""
    cum = np.cumsum(m.mobility[None] * reach[:, None], axis=2)
    out = np.nonzero(cum[:, :, -1] <= 0)
    cum[out] = free[out[1]]
    cum /= cum[:, :, -1:].copy()
    return cum.reshape(-1, m.grid.size)


def walked(m: Model, n: int, rng: np.random.Generator) -> tuple[np.ndarray, list[np.ndarray], int]:
    """(length of each trace, cells, traces that had to jump) of ``n`` traces pinned at both ends by the conditional law, longest first.
    ``cells[r]`` holds the cell with r moves to go of all traces of more than r readings. All of them move at once: where many do, by one
    table of the running sums of every end and cell. Tables are kept for the next traces of the model, and get a guide when used again."""
    size, p = m.grid.size, m.mobility
    pick, length = drawn(m, n, rng)
    start, end = (ends.take(pick) for ends in np.divmod(m.pairs, size))
    most = int(length[0]) if n else 0
    upto = np.searchsorted(-length, -np.arange(most + 1), side="left")
    power = m.held.setdefault("power", [np.eye(size)])
    while len(power) < most:
        power.append(p @ power[-1])
    free, tables = np.cumsum(p, axis=1), m.held.setdefault("tables", {})
    jump = np.zeros(n, bool)
    for r in range(most):  # the traces of r + 1 readings
        own = slice(upto[r + 1], upto[r])
        jump[own] = (power[r].reshape(-1) <= 0).take(start[own] * size + end[own])
    cells: list[np.ndarray] = [start[:0]] * most
    here = start[: upto[most - 1]] if most else start
    for r in range(most - 1, -1, -1):
        cells[r] = here
        if r == 0:
            break
        own, goal = upto[r], end[: upto[r]]
        if r == 1:
            moved = goal.copy()
        elif own >= TABLE or r in tables:
            cum, guide, seen = tables.get(r, (None, None, 0))
            cum = _table(m, r, np.ascontiguousarray(power[r - 1].T), free) if cum is None else cum
            guide = _guide(cum) if guide is None and seen else guide
            row = goal * size
            row += here
            moved = _landed(cum, row, rng.random(own)) if guide is None else _led(cum, guide, row, rng.random(own))
            if (r - 1) * (cum.nbytes + 2 * GUIDE * size**2) <= HELD:  # most traces come by where few moves are to go
                tables[r] = cum, guide, seen + 1
        else:
            cum = np.cumsum(p[here] * power[r - 1].T[goal], axis=1)
            moved = _landed(np.where(cum[:, -1:] > 0, cum, free[here]), np.arange(own), rng.random(own))
        lost = np.flatnonzero(jump[:own])
        if len(lost) and r > 1:  # walk freely until the end
            moved[lost] = _landed(free, here[lost], rng.random(len(lost)))
        here = np.concatenate([moved, start[own : upto[r - 1]]])
    return length, cells, int(jump.sum())


def _parts(cells: list[np.ndarray], step: int):
    """The packed traces, so many at a time."""
    for s in range(0, len(cells[0]) if cells else 0, step):
        yield [c[s : s + step] for c in cells if len(c) > s]


def placed(rect: np.ndarray, cells: list[np.ndarray], rng: np.random.Generator) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """x and y of packed traces: uniform in the rectangle (x0, width, y0, height) of each cell."""
    xs, ys = [], []
    for c in cells:
        for low, side, into in ((rect[0], rect[1], xs), (rect[2], rect[3], ys)):
            v = rng.random(len(c))
            v *= side.take(c)
            v += low.take(c)
            into.append(v)
    return xs, ys


def _rectangles(grid: Grid) -> np.ndarray:
    x0, x1, y0, y1 = np.array([r[4:] for r in grid.rectangles()]).T
    return np.stack([x0, x1 - x0, y0, y1 - y0])


def made(m: Model, n: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(start offset of each trace, x, y, traces that had to jump) of ``n`` traces."""
    length, cells, jumps = walked(m, n, rng)
    xs, ys = placed(_rectangles(m.grid), cells, rng)
    first = np.r_[0, np.cumsum(length)].astype(np.int64)
    x, y = np.empty(first[-1]), np.empty(first[-1])
    for r in range(len(cells)):
        at = first[1 : len(cells[r]) + 1] - 1 - r
        x[at], y[at] = xs[r], ys[r]
    return first, x, y, jumps


def _divergence(a: np.ndarray, b: np.ndarray) -> float:
    if a.sum() <= 0 or b.sum() <= 0:
        return 1.0
    p, q = a.ravel() / a.sum(), b.ravel() / b.sum()
    half = lambda u, v: 0.5 * (u[u > 0] * np.log2(2 * u[u > 0] / (u[u > 0] + v[u > 0]))).sum()
    return max(0.0, float(half(p, q) + half(q, p)))


class Axis:
    """Between which of the sorted edges a number lies: by equal bins, then the few edges inside the bin. The bin of a number rises with
    it, so only edges of its own bin need a look."""

    def __init__(self, low: np.ndarray, high: np.ndarray, bins: int = 4096):
        self.edges = np.unique(np.r_[low, high])
        self.first, self.bins = float(self.edges[0]), bins
        self.scale = bins / max(float(self.edges[-1] - self.edges[0]), 1e-300)
        own = self._bin(self.edges)
        self.base = np.searchsorted(own, np.arange(bins), side="left")
        rank = np.arange(len(own)) - self.base[own]
        self.inner = np.full((int(rank.max()) + 1, bins), np.inf)
        self.inner[rank, own] = self.edges
        start = np.r_[-np.inf, self.edges]
        on = (low <= start[:, None]) & (start[:, None] < high)  # intervals x queries
        self.each = np.packbits(np.pad(on, ((0, 0), (0, -on.shape[1] % 64))), axis=1).view(np.uint64)
        self.words = self.each.T
        self.into = np.where(self.inner[0] < np.inf, ~self.base, self.base)  # few bins hold an edge: those are marked

    def _bin(self, v: np.ndarray) -> np.ndarray:
        at = v - self.first
        at *= self.scale
        return np.clip(at, 0, self.bins - 1, out=at).astype(np.int64)

    def interval(self, v: np.ndarray) -> np.ndarray:
        b = self._bin(v)
        out = self.into.take(b)
        some = np.flatnonzero(out < 0)
        b, v, at = b[some], v[some], ~out[some]
        for edges in self.inner:
            at += v >= edges.take(b)
        out[some] = at
        return out


def _trie(patterns: list[tuple[int, ...]]) -> tuple[np.ndarray, np.ndarray]:
    """(next node by node and cell, node of each pattern): node 0 is no pattern's beginning, node 1 is empty."""
    nodes: dict[tuple[int, ...], int] = {(): 1}
    for q in patterns:
        for k in range(1, len(q) + 1):
            nodes.setdefault(q[:k], len(nodes) + 1)
    step = np.zeros((len(nodes) + 1, 36), np.int64)
    for q, i in nodes.items():
        if q:
            step[nodes[q[:-1]], q[-1]] = i
    return step, np.array([nodes[q] for q in patterns], np.int64)


def _ones(words: np.ndarray) -> np.ndarray:
    """How many rows have which bit set. The halves of the rows are added bit by bit, digit for digit of binary numbers that lie one in
    each place, until few rows are left."""
    digits = [words]
    while len(digits[0]) > 64:
        half = -(-len(digits[0]) // 2)
        added, carry = [], None
        for d in digits:
            a, b = d[:half], d[half:]
            if len(b) < half:
                b = np.concatenate([b, np.zeros_like(a[:1])])
            both, one = a & b, a ^ b
            added.append(one if carry is None else one ^ carry)
            carry = both if carry is None else both | one & carry
        digits = [*added, carry]
    return sum(np.unpackbits(np.ascontiguousarray(d).view(np.uint8), axis=1).sum(axis=0, dtype=np.int64) << k for k, d in enumerate(digits))


class Measure:
    """Counts what the four errors need of synthetic traces, part by part; ``errors`` compares the sums with the real side."""

    def __init__(self, t: Tables, names=FOUR):
        self.t, self.names = t, names
        self.hits, self.trips, self.histogram = np.zeros(len(t.regions), np.int64), np.zeros(1296, np.int64), np.zeros(len(t.histogram), np.int64)
        if "query_error" in names and len(t.regions):
            self.axes = Axis(t.regions[:, 0], t.regions[:, 1]), Axis(t.regions[:, 2], t.regions[:, 3])
        self.step, self.node = _trie(t.patterns)
        self.found = np.zeros(len(self.step), np.int64)
        self.goes_on = np.where(self.step.any(axis=1), np.arange(len(self.step)), 0)  # the node, or 0 where no pattern is longer
        self.two = self.step[self.step[1]].ravel()  # the node of two cells

    def add(self, xs: list[np.ndarray], ys: list[np.ndarray]) -> None:
        """Packed traces: place r holds the reading with r moves to go, traces longest first."""
        if not xs:
            return
        if "query_error" in self.names and len(self.t.regions):
            self._queries(xs, ys)
        if {"pattern_support_error", "trip_error"} & set(self.names):
            b = self.t.bounds

            def axis(v: np.ndarray, low: float, high: float) -> np.ndarray:
                at = v - low
                at /= high - low
                at *= 6
                return np.clip(at, 0, 5, out=at).astype(np.int64)

            cells = [axis(x, b.x0, b.x1) * 6 + axis(y, b.y0, b.y1) for x, y in zip(xs, ys)]
            if "pattern_support_error" in self.names:
                self._patterns(cells)
            if "trip_error" in self.names:
                for r, c in enumerate(cells):  # the traces of r + 1 readings start here
                    own = slice(len(cells[r + 1]) if r + 1 < len(cells) else 0, len(c))
                    self.trips += np.bincount(c[own] * 36 + cells[0][own], minlength=1296)
        if "travel_distance_error" in self.names:
            d = np.zeros(len(xs[0]))
            for r in range(len(xs) - 1, 0, -1):
                k = len(xs[r])
                dx, dy = xs[r - 1][:k] - xs[r], ys[r - 1][:k] - ys[r]
                dx *= dx
                dy *= dy
                dx += dy
                d[:k] += np.sqrt(dx, out=dx)
            d = np.round(d, 9)
            d = d[d <= self.t.longest]
            width = self.t.longest / len(self.histogram)
            at = np.minimum(np.floor(d / width), len(self.histogram) - 1).astype(np.int64) if width > 0 else np.zeros(len(d), np.int64)
            self.histogram += np.bincount(at, minlength=len(self.histogram))

    def _queries(self, xs: list[np.ndarray], ys: list[np.ndarray]) -> None:
        """A bit for each rectangle that a trace meets."""
        ax, ay = self.axes
        met = np.zeros((len(xs[0]), ax.each.shape[1]), np.uint64)
        for x, y in zip(xs, ys):
            here = ax.each.take(ax.interval(x), axis=0)
            here &= ay.each.take(ay.interval(y), axis=0)
            met[: len(x)] |= here
        self.hits += _ones(met)[: len(self.hits)]

    def _patterns(self, cells: list[np.ndarray]) -> None:
        """From every reading on, as long as some pattern begins so."""
        pairs, longer = np.zeros(1296, np.int64), self.goes_on[self.two]
        for r in range(len(cells) - 1, 0, -1):
            pair = cells[r] * 36
            pair += cells[r - 1][: len(pair)]
            pairs += np.bincount(pair, minlength=1296)
            if r == 1:
                break
            node = longer.take(pair)
            alive = np.flatnonzero(node)
            node = node[alive]
            for k in range(r - 2, -1, -1):
                if not len(alive):
                    break
                node = self.step.reshape(-1).take(node * 36 + cells[k][alive])
                self.found += np.bincount(node, minlength=len(self.found))
                node = self.goes_on.take(node)
                on = np.flatnonzero(node)
                node, alive = node[on], alive[on]
        np.add.at(self.found, self.two, pairs)

    def errors(self, scale: float) -> dict[str, float]:
        t, out = self.t, {}
        if "query_error" in self.names:
            floor = np.maximum(t.region_counts, 0.01 * t.total)
            out["query_error"] = float(np.divide(np.abs(t.region_counts - self.hits * scale), floor, out=np.zeros(len(floor)), where=floor > 0).mean())
        if "pattern_support_error" in self.names:
            out["pattern_support_error"] = float((np.abs(t.supports - self.found[self.node] * scale) / t.supports).mean()) if len(t.patterns) else 0.0
        if "trip_error" in self.names:
            out["trip_error"] = _divergence(t.trips6, self.trips)
        if "travel_distance_error" in self.names:
            out["travel_distance_error"] = _divergence(t.histogram, self.histogram)
        return out


def errors(t: Tables, first: np.ndarray, x: np.ndarray, y: np.ndarray, scale: float, names=FOUR) -> dict[str, float]:
    """The four errors of synthetic traces against the real side, as ``metrics.REGISTRY`` defines them."""
    size = np.diff(first)
    order = np.argsort(-size, kind="stable")
    last, most = first[1:][order] - 1, int(size.max(initial=0))
    at = [last[: np.searchsorted(-size[order], -r, side="left")] - r for r in range(most)]
    found = Measure(t, names)
    found.add([x[a] for a in at], [y[a] for a in at])
    return found.errors(scale)


def one_run(t: Tables, cfg: SynthesisConfig, w, seed: int, n: int | None, names=FOUR) -> dict[str, float]:
    """The errors of one candidate; ``n`` None makes the noisy number of traces. ``jumps``: traces whose end was out of reach.

    Traces are walked ``BLOCK`` at a time, placed and measured ``PART`` at a time, so memory does not grow with their number."""
    rng = np.random.default_rng(seed)
    model = synopsis(t, cfg, np.asarray(w, float), rng)
    count = model.noisy_total if n is None else n
    found, rect, jumps = Measure(t, names), _rectangles(model.grid), 0
    for s in range(0, count, BLOCK):
        _, cells, jumped = walked(model, min(BLOCK, count - s), rng)
        jumps += jumped
        for part in _parts(cells, PART):
            found.add(*placed(rect, part, rng))
    return found.errors(t.total / n if n else 1.0) | {"jumps": float(jumps)}


class Bench:
    """Evaluates batches of candidates over one or several real sets, each batch in one job."""

    def __init__(self, spark, sides: dict[str, Tables]):
        self.spark, self.shared = spark, spark.sparkContext.broadcast(sides)

    def run(self, asked: list[tuple[str, SynthesisConfig, np.ndarray, int, int | None]], names=FOUR) -> list[dict[str, float]]:
        """Errors of (side, settings, weights, seed, traces) in the order asked; equal requests are run once (``metric`` is not looked at)."""
        keys = [(side, replace(cfg, metric=""), tuple(map(float, w)), seed, n) for side, cfg, w, seed, n in asked]
        place = {k: i for i, k in enumerate(dict.fromkeys(keys))}
        once = list(place)
        jobs, shared = self.spark.sparkContext.broadcast(once), self.shared

        def evaluate(batches):
            for batch in batches:
                for i in batch.column(0).to_pylist():
                    side, cfg, w, seed, n = jobs.value[i]
                    got = one_run(shared.value[side], cfg, w, seed, n, names)
                    yield pa.RecordBatch.from_pydict({"id": [i] * len(got), "metric": list(got), "value": list(got.values())})

        ids = self.spark.range(0, len(once), 1, max(1, min(len(once), 16 * self.spark.sparkContext.defaultParallelism)))
        out: list[dict[str, float]] = [{} for _ in once]
        for r in ids.mapInArrow(evaluate, "id long, metric string, value double").collect():  # a few numbers a candidate
            out[r.id][r.metric] = r.value
        jobs.unpersist()
        return [out[place[k]] for k in keys]

    def guide(self, asked: list[tuple[str, SynthesisConfig, np.ndarray, list[float], int, int, int | None]]) -> list[tuple[np.ndarray, list[tuple]]]:
        """(winning weights, history) of guided searches from explored points: (side, settings, points, errors, guided steps, seed,
        traces). Each search is one task; steps of one search follow on each other, searches do not."""
        jobs, shared = self.spark.sparkContext.broadcast(asked), self.shared

        def search(batches):
            from .tuning import minimise

            for batch in batches:
                for i in batch.column(0).to_pylist():
                    side, cfg, points, known, guided, seed, n = jobs.value[i]
                    w, history = minimise(lambda w, s: one_run(shared.value[side], cfg, w, s, n, (cfg.metric,))[cfg.metric], len(points), guided, seed, known=(points, known))
                    yield pa.RecordBatch.from_pydict({"id": [i], "found": [json.dumps([list(map(float, w)), history])]})

        ids = self.spark.range(0, len(asked), 1, max(1, len(asked)))
        found = {r.id: json.loads(r.found) for r in ids.mapInArrow(search, "id long, found string").collect()}  # some 200 rows a search
        jobs.unpersist()
        return [(np.array(found[i][0]), [tuple(h) for h in found[i][1]]) for i in range(len(asked))]


def evaluate_tables(spark, t: Tables, cfg: SynthesisConfig, weights: np.ndarray, n: int | None, seed: int, names=FOUR) -> DataFrame:
    """``eval_id, w1..w4, metric, value``: every metric of every candidate, in one job. All share their draws."""
    found = Bench(spark, {"": t}).run([("", cfg, w, seed, n) for w in weights], names)
    rows = [(i, *map(float, w), m, float(v)) for i, (w, got) in enumerate(zip(weights, found)) for m, v in got.items() if m != "jumps"]
    return spark.createDataFrame(rows, "eval_id int, w1 double, w2 double, w3 double, w4 double, metric string, value double").where(F.col("metric").isin(*names))


def evaluate_all(real: metrics.RealSide, stats: statistics.LeafStatistics, cfg: SynthesisConfig, weights: np.ndarray, n: int | None, seed: int, names=FOUR) -> DataFrame:
    """The same from a real side and leaf statistics in tables."""
    return evaluate_tables(real.traces.sparkSession, tables(real, stats), cfg, weights, n, seed, names)
