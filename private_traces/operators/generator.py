"""Synthetic traces from a released synopsis alone: trips, lengths, pinned walks, readings."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from private_traces.config import SynthesisConfig
from private_traces.functions.noise import keyed_numbers, keyed_uniform

from .grid import WIDE
from .lattice_model import length_probabilities
from .synopsis import FAMILIES, ReleasedSynopsis, law_weights

BUCKETS = 4096
DENSE = WIDE  # cells up to which a task holds the chances of all pairs: some 30 MB for 32 moves
WORK = 4_000_000  # numbers of a slice of walks
NEAR = 250_000  # numbers of a slice of a move on larger grids, which stay in the cache
GROUP = 32  # ends walked together on larger grids: some 20 MB for 2,500 cells and 32 moves
ROWS = 100_000  # traces gathered before they are walked


def cdf_intervals(trips: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Each pair's interval [lo, hi) of cumulative probability, in the order of the pairs (per group of ``by``). The table of
    pairs is bounded by the lattice."""
    group = Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0))
    upto = F.sum("prob").over(group.orderBy("start_cell", "end_cell").rowsBetween(Window.unboundedPreceding, 0))
    held = trips.where("prob > 0").select("start_cell", "end_cell", "prob", upto.alias("up"), F.sum("prob").over(group).alias("all"))
    return held.select("start_cell", "end_cell", F.round((F.col("up") - F.col("prob")) / F.col("all"), 12).alias("lo"), F.round(F.col("up") / F.col("all"), 12).alias("hi"))


def _bucket(u: Column) -> Column:
    return F.least(F.lit(BUCKETS - 1), F.floor(u * BUCKETS)).cast("int")


def draw_trips(trips: DataFrame, n: int, seed: int, allocation: str = "random", source: str = "md5") -> DataFrame:
    """``trace_id, start_cell, end_cell`` for ids 0..n-1. ``random``: inverse distribution by an equi-join on the bucket of the
    draw; ``quota``: every pair gets its share of n, remainders by largest fraction."""
    spark = trips.sparkSession
    intervals = cdf_intervals(trips)
    if allocation == "quota":
        return intervals.select("start_cell", "end_cell", F.round(F.col("lo") * n).cast("bigint").alias("a"), F.round(F.col("hi") * n).cast("bigint").alias("b")).where("b > a").select(F.explode(F.sequence(F.col("a"), F.col("b") - 1)).alias("trace_id"), "start_cell", "end_cell")
    ids = spark.range(n).select(F.col("id").alias("trace_id"), keyed_uniform(seed, "draw", "id", source=source).alias("u")).withColumn("b", _bucket(F.col("u")))
    spread = intervals.withColumn("b", F.explode(F.sequence(_bucket(F.col("lo")), _bucket(F.col("hi")))))
    # a pair is listed once per bucket it touches: at most pairs + BUCKETS rows, bounded by the lattice
    met = ids.join(F.broadcast(spread), "b").where("u >= lo and (u < hi or hi >= 0.999999999999)")
    return met.select("trace_id", "start_cell", "end_cell")


def length_tables(laws: DataFrame, max_len: int) -> DataFrame:
    """``start_cell, end_cell, cdf``: cumulative probability of lengths 1..max_len of each pair's law."""
    weights = law_weights(F.col("p1"), F.col("len"), max_len)
    chosen = F.coalesce(*[F.when(F.col("family") == f, weights[f]) for f in FAMILIES])
    each = laws.select("start_cell", "end_cell", "family", "p1", F.explode(F.sequence(F.lit(1), F.lit(max_len))).alias("len")).withColumn("w", F.coalesce(chosen, F.lit(0.0)))
    arrays = each.groupBy("start_cell", "end_cell").agg(F.sort_array(F.collect_list(F.struct("len", "w"))).alias("r"))
    total = F.aggregate("r", F.lit(0.0), lambda a, x: a + x["w"])
    running = F.transform(F.sequence(F.lit(1), F.lit(max_len)), lambda k: F.aggregate(F.slice("r", F.lit(1), k), F.lit(0.0), lambda a, x: a + x["w"]))
    return arrays.select("start_cell", "end_cell", total.alias("t"), running.alias("c")).select("start_cell", "end_cell", F.transform("c", lambda c: F.round(F.coalesce(F.try_divide(c, F.col("t")), F.lit(1.0)), 12)).alias("cdf"))


def draw_lengths(trips: DataFrame, laws: DataFrame, max_len: int, seed: int, source: str = "md5", wide: bool = False) -> DataFrame:
    """``trips`` with ``n``: inverse distribution of the pair's law; at least 1, at least 2 where the ends differ. ``wide``: too many
    pairs to hand every task the distributions of all; a trace meets its law and draws from it in arrays."""
    u = keyed_uniform(seed, "length-draw", "trace_id", source=source)
    least = F.when(F.col("start_cell") == F.col("end_cell"), 1).otherwise(2)
    if wide:
        rank = F.coalesce(*[F.when(F.col("family") == f, i) for i, f in enumerate(FAMILIES)])
        met = trips.join(laws.select("start_cell", "end_cell", rank.alias("law"), "p1"), ["start_cell", "end_cell"], "left")
        kept = T.StructType(trips.schema.fields)
        row = met.select(*kept.names, least.alias("least"), F.coalesce("law", F.lit(-1)).alias("law"), F.coalesce("p1", F.lit(1.0)).alias("p1"), u.alias("u"))
        return row.mapInArrow(lambda b: _lengths(b, kept.names, max_len), T.StructType([*kept.fields, T.StructField("n", T.IntegerType())]))
    met = trips.join(F.broadcast(length_tables(laws, max_len)), ["start_cell", "end_cell"], "left")
    # the draw is bound outside the filter, which would make it again for every length
    below = F.get(F.transform(F.array(u), lambda x: F.size(F.filter("cdf", lambda c: c <= x))), F.lit(0))
    drawn = F.coalesce(F.when(F.col("cdf").isNotNull(), below) + 1, F.lit(2))
    return met.withColumn("n", F.least(F.lit(max_len), F.greatest(least, drawn)).cast("int")).drop("cdf")


def _lengths(batches, names: list[str], max_len: int):
    for batch in batches:
        least, law, mean, u = (batch.column(c).to_numpy() for c in ("least", "law", "p1", "u"))
        cdf = np.cumsum(length_probabilities(mean, max_len)[np.maximum(law, 0), np.arange(len(law))], axis=1)
        cdf = np.where(cdf[:, -1:] > 0, np.round(cdf, 12), 1.0)
        n = np.where(law < 0, 2, (cdf <= u[:, None]).sum(axis=1) + 1)
        n = np.minimum(max_len, np.maximum(least, n)).astype(np.int32)
        yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in names], pa.array(n)], [*names, "n"])


def mobility_arrays(mobility: DataFrame, size: int) -> np.ndarray:
    """The K x K transition matrix; K is bounded by the lattice (36 N^2 cells at most)."""
    p = np.zeros((size, size))
    rows = mobility.where("prob > 0").select("src", "dst", "prob").toArrow()
    p[rows["src"].to_numpy(), rows["dst"].to_numpy()] = rows["prob"].to_numpy()
    return p


def walk_free_end(trips: DataFrame, p: np.ndarray, seed: int, source: str = "md5") -> DataFrame:
    """Free walk for all but the last cell, which is set to the drawn end. Higher-order functions only."""
    cdf = np.round(np.cumsum(p, axis=1), 12)
    table = F.from_json(F.lit("[" + ",".join("[" + ",".join(f"{x:.12g}" for x in row) + "]" for row in cdf) + "]"), "array<array<double>>")
    size = len(p)

    def step(path: Column, k: Column) -> Column:
        u = keyed_uniform(seed, "walk", "trace_id", k, source=source)
        row = F.get(table, F.get(path, F.size(path) - 1))
        return F.concat(path, F.array(F.least(F.lit(size - 1), F.size(F.filter(row, lambda c: c <= u))).cast("int")))

    free = F.aggregate(F.sequence(F.lit(1), F.col("n") - 2), F.array(F.col("start_cell").cast("int")), step)
    one = F.array(F.col("start_cell").cast("int"))
    cells = F.when(F.col("n") == 1, one).when(F.col("n") == 2, F.concat(one, F.array(F.col("end_cell").cast("int")))).otherwise(F.concat(free, F.array(F.col("end_cell").cast("int"))))
    return trips.select("trace_id", "n", cells.alias("cells"))


def backward(p: np.ndarray, end: int, steps: int) -> np.ndarray:
    """beta[r, c]: the chance of being at ``end`` exactly r moves after c."""
    beta = np.zeros((steps + 1, len(p)))
    beta[0, end] = 1
    for r in range(1, steps + 1):
        beta[r] = p @ beta[r - 1]
    return beta


def _uniforms(seed: int, ids: np.ndarray, most: int) -> np.ndarray:
    """One number in (0, 1) per trace and step, from a 64-bit mix of (seed, trace, step)."""
    with np.errstate(over="ignore"):
        x = ids.astype(np.uint64)[:, None] * np.uint64(0x9E3779B97F4A7C15) + np.arange(1, most + 1, dtype=np.uint64)[None, :] * np.uint64(0xBF58476D1CE4E5B9) + np.uint64(seed % (1 << 63))
        for s, m in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            x ^= x >> np.uint64(s)
            x *= np.uint64(m)
        x ^= x >> np.uint64(31)
    return ((x >> np.uint64(11)) + 0.5) / float(1 << 53)


def bridge_paths(p: np.ndarray, end: int, start: np.ndarray, n: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Walks of ``n`` cells from ``start`` to ``end`` by the exact conditional law, all at once, and which had to jump because the
    end cannot be reached in time (those walk freely and jump at the last move)."""
    most = int(n.max())
    beta = backward(p, end, most)
    free = np.cumsum(p, axis=1)
    out = np.full((len(start), most), -1, np.int64)
    out[:, 0] = here = start.copy()
    jump = beta[n - 1, start] <= 0
    for k in range(1, most):
        on = np.flatnonzero(n > k)
        left = n[on] - 1 - k
        w = p[here[on]] * beta[left]
        cum = np.cumsum(w, axis=1)
        tied = ~jump[on] & (cum[:, -1] > 0)
        cum = np.where(tied[:, None], cum, free[here[on]])
        nxt = (cum <= (u[on, k - 1] * cum[:, -1])[:, None]).sum(axis=1)
        here[on] = np.minimum(nxt, len(p) - 1)
        here[on[left == 0]] = end
        out[on, k] = here[on]
    single = n == 1
    out[single, 0] = start[single]
    return out, jump


def bridge_rows(p: np.ndarray, power: np.ndarray, start: np.ndarray, end: np.ndarray, n: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``bridge_paths`` for rows of any ends: ``power[r]`` holds the chances of all pairs over r moves."""
    most = int(n.max())
    free = np.cumsum(p, axis=1)
    out = np.full((len(start), most), -1, np.int64)
    out[:, 0] = here = start.copy()
    jump = power[n - 1, start, end] <= 0
    for k in range(1, most):
        on = np.flatnonzero(n > k)
        left = n[on] - 1 - k
        cum = np.cumsum(p[here[on]] * power[left, :, end[on]], axis=1)
        tied = ~jump[on] & (cum[:, -1] > 0)
        cum[~tied] = free[here[on[~tied]]]
        here[on] = np.minimum((cum <= (u[on, k - 1] * cum[:, -1])[:, None]).sum(axis=1), len(p) - 1)
        here[on[left == 0]] = end[on[left == 0]]
        out[on, k] = here[on]
    return out, jump


def _walk_rows(batches, shared, seed: int):
    p = shared.value
    power = np.eye(len(p))[None]
    for batch in batches:
        for at in range(0, batch.num_rows, max(1, WORK // len(p))):
            part = batch.slice(at, max(1, WORK // len(p)))
            ids, start, end, n = (part.column(c).to_numpy().astype(np.int64) for c in ("trace_id", "start_cell", "end_cell", "n"))
            while len(power) < n.max():
                power = np.concatenate([power, (p @ power[-1])[None]])
            out, jump = bridge_rows(p, power, start, end, n, _uniforms(seed, ids, int(n.max())))
            cells = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(n)], pa.int32()), pa.array(out[out >= 0], pa.int32()))
            yield pa.RecordBatch.from_arrays([part.column("trace_id"), pa.array(n, pa.int32()), cells, pa.array(jump)], ["trace_id", "n", "cells", "jumped"])


def successors(p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(cell, chance) of the cells that can follow each cell, in order, filled up with chance 0."""
    held = p > 0
    order = np.argsort(~held, axis=1, kind="stable")[:, : max(1, int(held.sum(axis=1).max()))]
    return order, np.take_along_axis(p, order, axis=1)


def bridge_group(p: np.ndarray, nxt: np.ndarray, chance: np.ndarray, start: np.ndarray, end: np.ndarray, n: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``bridge_paths`` for rows of a few ends: the chances of all of them are made by one product of matrices a move, and a move looks
    at the cells that can follow only."""
    ends, own = np.unique(end, return_inverse=True)
    most = int(n.max())
    beta = np.zeros((most, len(ends), len(p)))  # a walker's chances lie side by side
    beta[0, np.arange(len(ends)), ends] = 1
    for r in range(1, most):
        np.matmul(beta[r - 1], p.T, out=beta[r])
    flat = beta.reshape(-1)
    out = np.full((len(start), most), -1, np.int64)
    out[:, 0] = here = start.copy()
    jump = beta[n - 1, own, start] <= 0
    for k in range(1, most):
        for on in np.array_split(np.flatnonzero(n > k), max(1, int((n > k).sum()) * nxt.shape[1] // NEAR)):
            left = n[on] - 1 - k
            cum = chance[here[on]]
            cum *= flat.take(nxt[here[on]] + ((left * len(ends) + own[on]) * len(p))[:, None])
            np.cumsum(cum, axis=1, out=cum)
            tied = ~jump[on] & (cum[:, -1] > 0)
            cum[~tied] = np.cumsum(chance[here[on[~tied]]], axis=1)
            spot = np.minimum((cum <= (u[on, k - 1] * cum[:, -1])[:, None]).sum(axis=1), nxt.shape[1] - 1)
            here[on] = nxt[here[on], spot]
            here[on[left == 0]] = end[on[left == 0]]
            out[on, k] = here[on]
    return out, jump


def _walk_groups(batches, shared, seed: int):
    """Rows come sorted by end; ``GROUP`` ends are walked at a time."""
    p = shared.value
    nxt, chance = successors(p)
    held: list[pa.RecordBatch] = []

    def walked(rows: pa.Table):
        ids, start, end, n = (rows.column(c).to_numpy().astype(np.int64) for c in ("trace_id", "start_cell", "end_cell", "n"))
        group = np.cumsum(np.r_[0, np.diff(end) != 0]) // GROUP
        for g in np.split(np.arange(len(ids)), np.flatnonzero(np.diff(group)) + 1):
            out, jump = bridge_group(p, nxt, chance, start[g], end[g], n[g], _uniforms(seed, ids[g], int(n[g].max())))
            cells = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(n[g])], pa.int32()), pa.array(out[out >= 0], pa.int32()))
            yield pa.RecordBatch.from_arrays([pa.array(ids[g]), pa.array(n[g], pa.int32()), cells, pa.array(jump)], ["trace_id", "n", "cells", "jumped"])

    for batch in batches:
        held.append(batch)
        if sum(b.num_rows for b in held) >= ROWS:
            yield from walked(pa.Table.from_batches(held))
            held = []
    if held and sum(b.num_rows for b in held):
        yield from walked(pa.Table.from_batches(held))


def _walk(batches, shared, seed: int, mode: str):
    p = shared.value
    for batch in batches:
        ids, start, end, n = (batch.column(c).to_numpy().astype(np.int64) for c in ("trace_id", "start_cell", "end_cell", "n"))
        cells: list = [None] * len(ids)
        jumped = np.zeros(len(ids), bool)
        for e in np.unique(end):
            own = np.flatnonzero(end == e)
            u = _uniforms(seed, ids[own], int(n[own].max()))
            if mode == "reject":  # free walks, tried again until they end right; after 20 tries the bridge
                out, jump = _rejected(p, int(e), start[own], n[own], seed, ids[own])
            else:
                out, jump = bridge_paths(p, int(e), start[own], n[own], u)
            jumped[own] = jump
            for i, row, k in zip(own.tolist(), out.tolist(), n[own].tolist()):
                cells[i] = row[:k]
        yield pa.RecordBatch.from_arrays([batch.column("trace_id"), pa.array(n, pa.int32()), pa.array(cells, pa.list_(pa.int32())), pa.array(jumped)], ["trace_id", "n", "cells", "jumped"])


def _rejected(p: np.ndarray, end: int, start: np.ndarray, n: np.ndarray, seed: int, ids: np.ndarray):
    out, jump = bridge_paths(p, end, start, n, _uniforms(seed, ids, int(n.max())))
    open_ = np.flatnonzero(n > 1)
    free = np.cumsum(p, axis=1)
    for attempt in range(20):
        if not len(open_):
            break
        u = _uniforms(seed + 7919 * (attempt + 1), ids[open_], int(n.max()))
        here, path = start[open_].copy(), np.full((len(open_), int(n.max())), -1, np.int64)
        path[:, 0] = here
        for k in range(1, path.shape[1]):
            on = n[open_] > k
            nxt = np.minimum((free[here] <= (u[:, k - 1] * free[here, -1])[:, None]).sum(axis=1), len(p) - 1)
            here = np.where(on, nxt, here)
            path[:, k] = np.where(on, here, -1)
        good = here == end
        out[open_[good]] = path[good]
        jump[open_[good]] = False
        open_ = open_[~good]
    return out, jump


def walk(trips: DataFrame, mobility: DataFrame, size: int, seed: int, mode: str = "bridge", source: str = "md5") -> DataFrame:
    """``trace_id, n, cells`` (``jumped`` too for the bridge): walks pinned at both ends.

    Up to ``DENSE`` cells a task holds the chances of all pairs for every number of moves, and rows stay where they are. On larger
    grids rows are dealt by ranges of end cell and trace, and each task makes the chances of its ends, some at a time. Where free walks
    are tried first, rows are dealt by end cell and a salt, so a popular end is shared by many tasks."""
    p = mobility_arrays(mobility, size)
    if mode == "forced_end":
        return walk_free_end(trips, p, seed, source)
    shared = trips.sparkSession.sparkContext.broadcast(p)
    if mode == "bridge" and size <= DENSE:
        return trips.select("trace_id", "start_cell", "end_cell", "n").mapInArrow(lambda b: _walk_rows(b, shared, seed), "trace_id long, n int, cells array<int>, jumped boolean")
    if mode == "bridge":  # ends side by side: a task meets few of them, so few chances are made twice, and a popular end has many tasks
        tasks = 4 * trips.sparkSession.sparkContext.defaultParallelism  # few rows, much work: not left to their size
        near = trips.select("trace_id", "start_cell", "end_cell", "n").repartitionByRange(tasks, F.col("end_cell"), F.xxhash64("trace_id")).sortWithinPartitions("end_cell")
        return near.mapInArrow(lambda b: _walk_groups(b, shared, seed), "trace_id long, n int, cells array<int>, jumped boolean")
    salt = F.pmod(F.xxhash64("trace_id"), F.lit(16))
    dealt = trips.select("trace_id", "start_cell", "end_cell", "n").repartition(F.col("end_cell"), salt)
    return dealt.mapInArrow(lambda b: _walk(b, shared, seed, mode), "trace_id long, n int, cells array<int>, jumped boolean")


def jumps(walks: DataFrame) -> DataFrame:
    """``n, traces, jumped``: per number of readings, how many traces could not reach their end in time and jump to it."""
    return walks.groupBy("n").agg(F.count("*").alias("traces"), F.sum(F.col("jumped").cast("long")).alias("jumped"))


def place_points(walks: DataFrame, cells: DataFrame, seed: int, step_seconds: float | None = None, start: str = "2024-01-01 00:00:00", source: str = "md5") -> DataFrame:
    """``trace_id, seq, x, y, ts``: a uniform point of each cell's rectangle; a fixed sampling step where one is given."""
    long = walks.select("trace_id", F.posexplode("cells").alias("pos", "cell")).join(F.broadcast(cells), "cell")
    at = lambda a, b, s: F.col(a) + (F.col(b) - F.col(a)) * keyed_uniform(seed, s, "trace_id", "pos", source=source)
    ts = F.lit(None).cast("timestamp_ntz") if step_seconds is None else (F.lit(start).cast("timestamp_ntz") + F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), F.col("pos") * F.lit(step_seconds))).cast("timestamp_ntz")
    return long.select("trace_id", (F.col("pos") + 1).cast("int").alias("seq"), at("x0", "x1", "place-x").alias("x"), at("y0", "y1", "place-y").alias("y"), ts.alias("ts"))


def nested(walks: DataFrame, grid, seed: int, source: str = "md5", step_seconds: float | None = None) -> DataFrame:
    """The same readings in nested form without a shuffle: the draws of the source ``md5`` are made and placed in arrays, those of
    others by a constant array of the cells."""
    ts = (lambda i: F.lit(None).cast("timestamp_ntz")) if step_seconds is None else (lambda i: (F.lit("2024-01-01 00:00:00").cast("timestamp_ntz") + F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), i * F.lit(step_seconds))).cast("timestamp_ntz"))

    if source == "md5":
        corners = np.array([row[4:] for row in grid.rectangles()])
        placed = walks.select("trace_id", "n", "cells").mapInArrow(lambda b: _placed(b, corners, seed), "trace_id long, n int, xs array<double>, ys array<double>")
        here = lambda x, i: F.struct((i + 1).cast("int").alias("seq"), x.alias("x"), F.get("ys", i).alias("y"), ts(i).alias("ts"))
        return placed.select("trace_id", "n", F.transform("xs", here).alias("path"))
    rect = F.array(*[F.array(*[F.lit(float(v)) for v in row[4:]]) for row in grid.rectangles()])

    def point(c: Column, i: Column) -> Column:
        q = F.get(rect, c)
        on = lambda a, s: F.get(q, F.lit(a)) + (F.get(q, F.lit(a + 1)) - F.get(q, F.lit(a))) * keyed_uniform(seed, s, "trace_id", i, source=source)
        return F.struct((i + 1).cast("int").alias("seq"), on(0, "place-x").alias("x"), on(2, "place-y").alias("y"), ts(i).alias("ts"))

    return walks.select("trace_id", "n", F.transform("cells", point).alias("path"))


def _placed(batches, corners: np.ndarray, seed: int):
    for batch in batches:
        held = batch.column("cells")
        upto = np.r_[0, np.cumsum(np.diff(held.offsets.to_numpy()), dtype=np.int64)]
        ids = np.repeat(batch.column("trace_id").to_numpy(), np.diff(upto))
        spot = np.arange(len(ids)) - np.repeat(upto[:-1], np.diff(upto))
        q, first = corners[held.flatten().to_numpy()], pa.array(upto, pa.int32())
        at = [pa.ListArray.from_arrays(first, pa.array(q[:, a] + (q[:, a + 1] - q[:, a]) * keyed_numbers(seed, s, ids, spot))) for a, s in ((0, "place-x"), (2, "place-y"))]
        yield pa.RecordBatch.from_arrays([batch.column("trace_id"), batch.column("n"), *at], ["trace_id", "n", "xs", "ys"])


def chained_trips(syn: ReleasedSynopsis, n: int, k: int, seed: int) -> DataFrame:
    """``trace_id, trip, start_cell, end_cell, n``: k trips each; a trip starts where the one before ended."""
    cfg = syn.config
    now = draw_trips(syn.trips, n, seed, source=cfg.noise_source).withColumn("trip", F.lit(0))
    bucket = lambda u: F.least(F.lit(15), F.floor(u * 16)).cast("int")
    per_start = cdf_intervals(syn.trips, ["start_cell"]).withColumn("b", F.explode(F.sequence(bucket(F.col("lo")), bucket(F.col("hi")))))
    done = now
    for j in range(1, k):
        u = now.select("trace_id", F.col("end_cell").alias("start_cell"), keyed_uniform(seed, f"chain{j}", "trace_id", source=cfg.noise_source).alias("u"))
        met = u.withColumn("b", bucket(F.col("u"))).join(F.broadcast(per_start), ["start_cell", "b"], "left").where("lo is null or (u >= lo and u < hi) or (hi >= 0.999999999 and u >= hi)")
        now = met.groupBy("trace_id", "start_cell").agg(F.min("end_cell").alias("e")).select("trace_id", "start_cell", F.coalesce("e", "start_cell").alias("end_cell"), F.lit(j).alias("trip"))
        done = done.unionByName(now)
    ided = done.withColumn("trace", F.col("trace_id")).withColumn("trace_id", F.col("trace_id") * k + F.col("trip"))
    return draw_lengths(ided, syn.lengths, cfg.max_len, seed, cfg.noise_source, syn.grid.size > WIDE)


def out_count(syn: ReleasedSynopsis, exact: int | None = None) -> int:
    """How many traces to make: the noisy count, the exact one (which is sensitive), or a given number."""
    want = syn.config.n_out
    if isinstance(want, int):
        return want
    return exact if want == "exact" and exact is not None else syn.noisy_total


def generate(syn: ReleasedSynopsis, n: int | None = None, seed: int | None = None, step_seconds: float | None = None) -> DataFrame:
    """Synthetic traces in nested form, from the released tables alone."""
    cfg = syn.config
    seed = cfg.seed if seed is None else seed
    n = out_count(syn) if n is None else n
    if cfg.trips_per_trace == 1:
        trips = draw_lengths(draw_trips(syn.trips, n, seed, cfg.allocation, cfg.noise_source), syn.lengths, cfg.max_len, seed, cfg.noise_source, syn.grid.size > WIDE)
        walks = walk(trips, syn.mobility, syn.grid.size, seed, cfg.walk, cfg.noise_source)
        return nested(walks, syn.grid, seed, cfg.noise_source, step_seconds)
    k = cfg.trips_per_trace
    walks = walk(chained_trips(syn, n, k, seed), syn.mobility, syn.grid.size, seed, cfg.walk, cfg.noise_source)
    parts = walks.groupBy(F.floor(F.col("trace_id") / k).alias("trace")).agg(F.sort_array(F.collect_list(F.struct("trace_id", "cells"))).alias("w"))
    # the first cell of a later trip repeats the last cell of the one before
    cells = F.flatten(F.transform("w", lambda w, i: F.when(i == 0, w["cells"]).otherwise(F.slice(w["cells"], F.lit(2), F.greatest(F.size(w["cells"]) - 1, F.lit(0))))))
    joined = parts.select(F.col("trace").alias("trace_id"), cells.alias("cells")).withColumn("n", F.size("cells"))
    return nested(joined, syn.grid, seed, cfg.noise_source, step_seconds)


def synthesise(traces: DataFrame, bounds, weights, cfg: SynthesisConfig, stats=None, seed: int | None = None):
    """(synthetic traces, released synopsis)."""
    from .synopsis import extract_synopsis

    syn = extract_synopsis(traces, bounds, weights, cfg, stats, seed)
    exact = traces.count() if cfg.n_out == "exact" else None
    return generate(syn, out_count(syn, exact), seed), syn
