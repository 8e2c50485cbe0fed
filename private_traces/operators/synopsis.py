"""The private synopsis: grid, mobility, trips and length laws, each with its share of the budget."""

from __future__ import annotations

import math
import uuid
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from private_traces.config import Bounds, SplitWeights, SynthesisConfig
from private_traces.functions.noise import clean_up, densify, integer_noise, keyed_uniform, laplace, to_probabilities

from . import lattice_model, statistics
from .grid import WIDE, Grid, build_grid, grid_spec, noisy_density, uniform_grid
from .ledger import Ledger

FAMILIES = ("uniform", "poisson", "exponential")


def pair_domain(spark: SparkSession, size: int, a: str, b: str) -> DataFrame:
    return spark.range(size * size).select(F.floor(F.col("id") / size).cast("int").alias(a), (F.col("id") % size).cast("int").alias(b))


def mobility_model(transitions: DataFrame, grid: Grid, epsilon: float | None, seed: int, mode: str = "shift", noise_on: str = "count", source: str = "md5") -> DataFrame:
    """``src, dst, weight, prob`` of all pairs; a row without mass moves evenly to the cell and its edge neighbours."""
    spark = transitions.sparkSession
    dense = densify(transitions, pair_domain(spark, grid.size, "src", "dst"), ["src", "dst"])
    if epsilon is not None:
        draw = laplace(1 / epsilon, seed, "move", "src", "dst", source=source)
        if noise_on == "probability":  # the literal reading; a row's denominator is then itself not private
            total = F.sum("weight").over(Window.partitionBy("src"))
            dense = dense.withColumn("weight", F.coalesce(F.try_divide(F.col("weight") + draw, total), F.lit(0.0)))
        else:
            dense = dense.withColumn("weight", F.col("weight") + draw)
        if grid.size <= WIDE:
            dense = clean_up(dense, "weight", ["src"], mode)
    if grid.size > WIDE:
        return _wide_moves(dense, grid, mode if epsilon is not None else None)
    pairs = spark.createDataFrame(grid.neighbour_pairs(), "src int, dst int").withColumn("near", F.lit(1.0))
    probs = to_probabilities(dense, "weight", ["src"]).join(F.broadcast(pairs), ["src", "dst"], "left")
    even = F.coalesce("near", F.lit(0.0)) / F.sum(F.coalesce("near", F.lit(0.0))).over(Window.partitionBy("src"))
    return probs.select("src", "dst", "weight", F.coalesce("prob", even).alias("prob"))


def _wide_moves(dense: DataFrame, grid: Grid, mode: str | None) -> DataFrame:
    """The clean-up and the probabilities of ``mobility_model``, a row of all cells at a time in arrays; ``mode`` None: nothing to clean."""
    beside = np.array(grid.neighbour_pairs())

    def each(rows: pa.Table) -> pa.Table:
        src, dst, w = (rows.column(c).to_numpy() for c in ("src", "dst", "weight"))
        w = w if mode is None else lattice_model.levelled(w[None], mode)[0]
        near = np.isin(dst, beside[beside[:, 0] == src[0], 1])
        prob = w / w.sum() if w.sum() > 0 else near / near.sum()
        return pa.table([rows.column("src"), rows.column("dst"), pa.array(w), pa.array(prob)], ["src", "dst", "weight", "prob"])

    return dense.select("src", "dst", "weight").groupBy("src").applyInArrow(each, "src int, dst int, weight double, prob double")


def _wide_masses(dense: DataFrame, mode: str | None, total: float | None) -> DataFrame:
    """``dense`` with cleaned ``mass`` and ``prob``: the constant that every mass loses, and what is left in all, come from one sort of the
    masses in an array; pairs stay where they are. ``mode`` None: nothing to clean."""

    def levels(batches):
        masses = np.concatenate([np.zeros(0), *(b.column("mass").to_numpy() for b in batches)])
        level = 0.0
        if mode == "shift":
            want = max(0.0, masses.sum() if total is None else total)
            down = np.sort(masses)[::-1]
            steps = (np.cumsum(down) - want) / np.arange(1, len(down) + 1)
            level = float(steps[np.flatnonzero(down > steps)[-1]]) if want > 0 else math.inf
        yield pa.RecordBatch.from_arrays([pa.array([level]), pa.array([np.maximum(0, masses - level).sum()])], ["level", "whole"])

    if mode not in (None, "shift", "clip", "threshold"):
        raise ValueError(f"unknown clean-up: {mode}")
    found = dense.select("mass").repartition(1).mapInArrow(levels, "level double, whole double")
    left = F.greatest(F.lit(0.0), F.col("mass") - F.col("level"))
    return dense.crossJoin(F.broadcast(found)).withColumn("mass", left).select(*dense.columns, F.try_divide("mass", "whole").alias("prob"))


def trip_distribution(counts: DataFrame, grid: Grid, epsilon: float | None, seed: int, mode: str = "shift", total: str = "counts", source: str = "md5", mechanism: str = "laplace") -> DataFrame:
    """``start_cell, end_cell, mass, prob`` of all pairs. ``total="separate"``: half of the share noises the pairs, half the
    number of traces, to which the masses are then levelled."""
    spark = counts.sparkSession
    keys = ["start_cell", "end_cell"]
    dense = densify(counts.select(*keys, F.col("n").cast("double").alias("mass")), pair_domain(spark, grid.size, *keys), keys)
    if epsilon is not None:
        own = epsilon / 2 if total == "separate" else epsilon
        target = None
        if total == "separate":
            exact = counts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).select((F.col("n") + integer_noise(mechanism, own, seed, "total", F.lit(0), source=source)).alias("n")).first().n
            target = F.lit(float(exact))
        dense = dense.withColumn("mass", F.col("mass") + integer_noise(mechanism, own, seed, "trip", *keys, source=source))
        if grid.size <= WIDE:
            dense = clean_up(dense, "mass", [], mode, total=target)
    if grid.size > WIDE:
        found = _wide_masses(dense, mode if epsilon is not None else None, float(exact) if epsilon is not None and total == "separate" else None)
    else:
        found = to_probabilities(dense, "mass", [])
    # without any mass left (few traces, much noise) every pair is as likely as any other
    return found.withColumn("prob", F.coalesce("prob", F.lit(1.0 / grid.size**2)))


def log_factorials(n: int) -> Column:
    """ln k! for k = 0..n as a constant array."""
    return F.array(*[F.lit(math.lgamma(k + 1)) for k in range(n + 1)])


def law_weights(mean: Column, length: Column, max_len: int) -> dict[str, Column]:
    """Unnormalised probability of ``length`` under each candidate law with the given mean, on 1..max_len."""
    upper = F.least(F.lit(max_len), F.greatest(F.lit(1), F.round(2 * mean - 1).cast("int")))
    rate = F.greatest(mean - 1, F.lit(1e-9))
    step = 1 / F.greatest(mean, F.lit(1e-9))
    return {
        "uniform": F.when(length <= upper, 1.0 / upper).otherwise(0.0),
        "poisson": F.exp((length - 1) * F.log(rate) - rate - F.get(log_factorials(max_len), length - 1)),
        "exponential": F.exp(-(length - 1) * step) - F.exp(-length * step),
    }


def noisy_lengths(hist: DataFrame, pairs: DataFrame, epsilon: float | None, max_len: int, seed: int, source: str = "md5", stage: str = "length") -> DataFrame:
    """``start_cell, end_cell, len, n`` on 1..max_len for the given pairs, noised once: a trace changes one bucket by 1."""
    keys = ["start_cell", "end_cell"]
    domain = pairs.select(*keys, F.explode(F.sequence(F.lit(1), F.lit(max_len))).alias("len"))
    dense = densify(hist.select(*keys, F.col("len").cast("int").alias("len"), F.col("n").cast("double").alias("n")), domain, [*keys, "len"])
    if epsilon is None:
        return dense
    return dense.withColumn("n", F.greatest(F.lit(0.0), F.col("n") + laplace(1 / epsilon, seed, stage, *keys, "len", source=source)))


def moment_parameters(hist: DataFrame, pairs: DataFrame, epsilon: float, max_len: int, seed: int, source: str = "md5") -> DataFrame:
    """``start_cell, end_cell, mean`` from one noisy (count, sum of lengths) per pair: joint sensitivity 1 + max_len."""
    keys = ["start_cell", "end_cell"]
    sums = hist.groupBy(*keys).agg(F.sum("n").cast("double").alias("k"), F.sum(F.col("n") * F.col("len")).cast("double").alias("s"))
    scale = (1 + max_len) / epsilon
    dense = densify(sums, pairs.select(*keys), keys)
    k = F.greatest(F.lit(1.0), F.col("k") + laplace(scale, seed, "length-k", *keys, source=source))
    s = F.col("s") + laplace(scale, seed, "length-s", *keys, source=source)
    return dense.select(*keys, F.greatest(F.lit(1.0), F.least(F.lit(float(max_len)), s / k)).alias("mean"))


def range_parameters(noisy: DataFrame, max_len: int) -> DataFrame:
    """``start_cell, end_cell, mean``: the middle of the shortest and longest length whose noisy count reaches 1, which is what a
    uniform law over the range needs; post-processing of the noisy histogram, with bounds 1..max_len where none does."""
    held = F.col("n") >= 1
    low, high = F.coalesce(F.min(F.when(held, F.col("len"))), F.lit(1)), F.coalesce(F.max(F.when(held, F.col("len"))), F.lit(max_len))
    return noisy.groupBy("start_cell", "end_cell").agg(((low + high) / 2).alias("mean"))


def candidates(hist: DataFrame, max_len: int, means: DataFrame | None = None) -> DataFrame:
    """``start_cell, end_cell, len, n, total, mean, <family> expected`` for the three laws."""
    keys = ["start_cell", "end_cell"]
    w = Window.partitionBy(*keys)
    total = F.sum("n").over(w)
    given = hist.withColumn("total", total)
    if means is None:
        given = given.withColumn("mean", F.coalesce(F.try_divide(F.sum(F.col("n") * F.col("len")).over(w), F.col("total")), F.lit(1.0)))
    else:
        given = given.join(means, keys, "left").withColumn("mean", F.coalesce("mean", F.lit(1.0)))
    raw = given.withColumns(law_weights(F.col("mean"), F.col("len"), max_len))
    return raw.withColumns({f: F.col("total") * F.coalesce(F.try_divide(F.col(f), F.sum(f).over(w)), F.lit(0.0)) for f in FAMILIES})


def best_fit(expected: DataFrame, test: str = "chi2") -> DataFrame:
    """``start_cell, end_cell, family, p1, p2, fit, support``: the law with the least misfit; ties in the order of FAMILIES."""
    keys = ["start_cell", "end_cell"]
    if test == "chi2":
        miss = {f: F.sum(F.pow(F.col("n") - F.col(f), 2) / F.greatest(F.col(f), F.lit(0.5))) for f in FAMILIES}
    elif test == "loglik":
        miss = {f: -F.sum(F.col("n") * F.log(F.greatest(F.try_divide(F.col(f), F.col("total")), F.lit(1e-9)))) for f in FAMILIES}
    elif test == "ks":
        up = Window.partitionBy(*keys).orderBy("len").rowsBetween(Window.unboundedPreceding, 0)
        expected = expected.withColumns({f"{f}_gap": F.abs(F.sum(F.col("n") - F.col(f)).over(up)) for f in FAMILIES})
        miss = {f: F.coalesce(F.try_divide(F.max(f"{f}_gap"), F.first("total")), F.lit(0.0)) for f in FAMILIES}
    else:
        raise ValueError(f"unknown test: {test}")
    scored = expected.groupBy(*keys).agg(F.first("mean").alias("mean"), F.first("total").alias("support"), *[F.round(miss[f], 9).alias(f) for f in FAMILIES])
    best = F.array_min(F.array(*[F.struct(F.coalesce(F.col(f), F.lit(0.0)).alias("fit"), F.lit(i).alias("rank")) for i, f in enumerate(FAMILIES)]))
    family = F.get(F.array(*[F.lit(f) for f in FAMILIES]), F.col("b")["rank"])
    return scored.withColumn("b", best).select(*keys, family.alias("family"), F.col("mean").alias("p1"), F.lit(None).cast("double").alias("p2"), F.col("b")["fit"].alias("fit"), "support")


def _wide_fit(noisy: DataFrame, max_len: int, test: str) -> DataFrame:
    """``best_fit`` of the ``candidates`` of whole histograms, many pairs at a time in arrays."""
    names = ["start_cell", "end_cell", "family", "p1", "p2", "fit", "support"]

    def fitted(rows: pa.Table):
        n = rows.column("n").to_numpy().reshape(-1, max_len)
        miss, mean, total = lattice_model.misfits(n, test)
        best = miss.argmin(axis=0)
        ends = [pa.array(rows.column(c).to_numpy()[::max_len]) for c in names[:2]]
        return pa.RecordBatch.from_arrays([*ends, pa.array(FAMILIES).take(pa.array(best)), pa.array(mean), pa.nulls(len(best), pa.float64()), pa.array(miss[best, np.arange(len(best))]), pa.array(total)], names)

    def each(batches):
        held, rows = [], 0
        for batch in batches:
            held.append(batch)
            rows += batch.num_rows
            if rows >= 1000 * max_len:
                table = pa.Table.from_batches(held)
                whole = rows // max_len * max_len
                yield fitted(table.slice(0, whole))
                held, rows = table.slice(whole).to_batches(), rows - whole
        if rows:
            yield fitted(pa.Table.from_batches(held))

    keys = ["start_cell", "end_cell"]
    near = noisy.select(*keys, "len", "n").repartition(*keys).sortWithinPartitions(*keys, "len")
    return near.drop("len").mapInArrow(each, "start_cell int, end_cell int, family string, p1 double, p2 double, fit double, support double")


def length_laws(hist: DataFrame, trips: DataFrame, epsilon: float | None, cfg: SynthesisConfig, seed: int, wide: bool = False) -> DataFrame:
    """The law of every pair with mass; pairs with too little support borrow the law of all pairs together."""
    spark = hist.sparkSession
    pairs = trips.where("prob > 0").select("start_cell", "end_cell")
    pool = cfg.pool_share if epsilon is not None else 0.0
    rest = None if epsilon is None else epsilon * (1 - pool)
    if cfg.params_from == "moments" and rest is not None:
        noisy = noisy_lengths(hist, pairs, rest / 2, cfg.max_len, seed, cfg.noise_source)
        fitted = candidates(noisy, cfg.max_len, moment_parameters(hist, pairs, rest / 2, cfg.max_len, seed, cfg.noise_source))
    else:
        noisy = noisy_lengths(hist, pairs, rest, cfg.max_len, seed, cfg.noise_source)
        fitted = candidates(noisy, cfg.max_len, range_parameters(noisy, cfg.max_len) if cfg.params_from == "range" else None)
    if cfg.fit_on == "true":  # the choice of the law then reads the exact histogram and leaks
        exact = noisy_lengths(hist, pairs, None, cfg.max_len, seed)
        fitted = candidates(exact, cfg.max_len, fitted.groupBy("start_cell", "end_cell").agg(F.first("mean").alias("mean")))
    own = _wide_fit(noisy, cfg.max_len, cfg.test) if wide and cfg.params_from == "histogram" and cfg.fit_on != "true" else best_fit(fitted, cfg.test)
    everything = hist.groupBy("len").agg(F.sum("n").alias("n")).select(F.lit(-1).alias("start_cell"), F.lit(-1).alias("end_cell"), "len", "n")
    one = spark.createDataFrame([(-1, -1)], "start_cell int, end_cell int")
    pooled_noise = None if epsilon is None else epsilon * pool if pool > 0 else None
    pooled = best_fit(candidates(noisy_lengths(everything, one, pooled_noise, cfg.max_len, seed, cfg.noise_source, "pool"), cfg.max_len), cfg.test)
    if epsilon is not None and pool == 0:
        return own
    common = pooled.select(F.col("family").alias("f0"), F.col("p1").alias("m0"), F.col("fit").alias("x0"))
    weak = F.col("support") < cfg.min_support
    return own.crossJoin(F.broadcast(common)).select("start_cell", "end_cell", F.when(weak, F.col("f0")).otherwise(F.col("family")).alias("family"), F.when(weak, F.col("m0")).otherwise(F.col("p1")).alias("p1"), "p2", F.when(weak, F.col("x0")).otherwise(F.col("fit")).alias("fit"), "support")


@dataclass
class ReleasedSynopsis:
    """All that the generator may see: released tables with no lineage to the real traces."""

    grid: Grid
    mobility: DataFrame
    trips: DataFrame
    lengths: DataFrame
    ledger: Ledger
    config: SynthesisConfig
    weights: SplitWeights
    noisy_total: int


def release(df: DataFrame, tag: str) -> DataFrame:
    """Write and read back under ``spark.checkpoint.dir`` (on a local master, a folder of our own where that is unset): no
    lineage stays."""
    import tempfile

    spark = df.sparkSession
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir: executors of a cluster share no local folder")
    root = root or "file://" + tempfile.mkdtemp(prefix="release-")
    path = f"{root.rstrip('/')}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def ledger_of(cfg: SynthesisConfig, w: SplitWeights) -> Ledger:
    """What a run with these settings spends."""
    book = Ledger()
    if cfg.epsilon is None:
        return book.free("everything", "no noise")
    e = cfg.epsilon
    book.spend_sequential("grid", e * w.grid) if cfg.uniform_grid is None else book.free("grid")
    book.spend_sequential("mobility", e * w.mobility)
    if cfg.total == "separate":
        book.spend_sequential("trips", e * w.trips / 2).spend_sequential("total", e * w.trips / 2)
    else:
        book.spend_sequential("trips", e * w.trips)
    pool = cfg.pool_share
    book.spend_parallel("lengths", [e * w.lengths * (1 - pool)])
    if pool > 0:
        book.spend_sequential("length pool", e * w.lengths * pool)
    if cfg.noise_on == "probability":
        book.leak("mobility rows", "divided by exact totals")
    if cfg.fit_on == "true":
        book.leak("length laws", "chosen on the exact histogram")
    if cfg.n_out == "exact":
        book.leak("trace count", "the exact number of traces")
    return book.free("generator")


def audited_ledger(book: Ledger, paths: DataFrame) -> DataFrame:
    """The ledger with the largest share that one trace of ``paths`` has in each statistic in place of the declared sensitivity, and
    the number of traces that the stage reads: exact, for an audit and not for release."""
    each = paths.where("n > 0").select(
        F.aggregate("cells", F.lit(0.0), lambda a, c: a + 1.0 / F.col("n")).alias("grid"),
        F.when(F.col("n") > 1, F.aggregate(F.slice("cells", F.lit(2), F.col("n") - 1), F.lit(0.0), lambda a, c: a + 1.0 / (F.col("n") - 1))).alias("mobility"),
        F.lit(1.0).alias("pair"),  # one start, end and length a trace
    )
    most = lambda c: F.struct(F.coalesce(F.max(c), F.lit(0.0)).alias("s"), F.count(c).alias("traces"))
    seen = each.agg(*[most(c).alias(c) for c in ("grid", "mobility", "pair")])
    met = book.frame(paths.sparkSession).crossJoin(F.broadcast(seen))
    own = F.when(F.col("stage").isin("grid", "mobility"), F.when(F.col("stage") == "grid", F.col("grid")).otherwise(F.col("mobility"))).otherwise(F.col("pair"))
    reads = F.col("composition").isin("sequential", "parallel")
    return met.select("stage", "mechanism", F.when(reads, own["s"]).otherwise(F.col("sensitivity")).alias("sensitivity"), "epsilon", "composition", F.when(reads, own["traces"]).otherwise(F.lit(0).cast("long")).alias("traces"))


def extract_synopsis(traces: DataFrame | None, bounds: Bounds, weights: SplitWeights, cfg: SynthesisConfig, stats: statistics.LeafStatistics | None = None, seed: int | None = None, write: bool = True) -> ReleasedSynopsis:
    """The whole synopsis from traces, or from leaf statistics made before (then the traces are not read again).

    ``write`` False keeps the tables in memory: for the throw-away synopses of a tuning loop."""
    weights.validate()
    seed = cfg.seed if seed is None else seed
    hold = release if write else lambda df, tag: df.persist()
    share = (lambda x: None) if cfg.epsilon is None else (lambda x: cfg.epsilon * x)
    own = None  # statistics made here, kept until the tables are
    if cfg.uniform_grid is None:
        if stats is None:
            stats = own = statistics.leaf_statistics(traces, bounds, cfg.top_n, cfg.max_len, cfg.collapse_repeats).persist()
        noisy = noisy_density(stats.top_density(), cfg.top_n, share(weights.grid), seed, cfg.noise_source)
        later = (cfg.epsilon or 1.0) * (1 - weights.grid)
        grid = build_grid(grid_spec(noisy, cfg.split_rule, cfg.cells_per_top, list(cfg.cuts), later), bounds, cfg.top_n)
    else:
        grid = uniform_grid(bounds, cfg.uniform_grid, cfg.top_n)
    if grid.top_n != cfg.top_n or cfg.collapse_repeats:
        if traces is None:
            raise ValueError("these options need the traces, not leaf statistics")
        if cfg.collapse_repeats:
            moved, counts, hist = statistics.direct_statistics(traces, bounds, grid.top_n, cfg.max_len, grid.cell_of, True)
        else:
            own = statistics.counted_statistics(traces, bounds, grid.top_n, cfg.max_len, lattice_model.leaf_map(grid)).persist()
            moved, counts, hist = own.roll_up(lambda cell: cell)
    else:
        if stats is None:
            stats = own = statistics.leaf_statistics(traces, bounds, cfg.top_n, cfg.max_len, cfg.collapse_repeats).persist()
        moved, counts, hist = stats.roll_up(grid.cell_of)
    mobility = hold(mobility_model(moved, grid, share(weights.mobility), seed, cfg.clean_up, cfg.noise_on, cfg.noise_source).where("prob > 0"), "mobility")
    trips = hold(trip_distribution(counts, grid, share(weights.trips), seed, cfg.clean_up, cfg.total, cfg.noise_source, cfg.mechanism).where("prob > 0"), "trips")
    laws = hold(length_laws(hist, trips, share(weights.lengths), cfg, seed, grid.size > WIDE), "lengths")
    total = trips.agg(F.coalesce(F.sum("mass"), F.lit(0.0)).alias("n")).first().n
    if own is not None:
        own.unpersist()
    return ReleasedSynopsis(grid, mobility, trips, laws, ledger_of(cfg, weights), cfg, weights, max(0, round(total)))


def destination_given_start(trips: DataFrame) -> DataFrame:
    """``start_cell, end_cell, prob``: the likeliest end of each start."""
    row = F.struct(F.col("prob"), (-F.col("end_cell")).alias("e"))
    return trips.groupBy("start_cell").agg(F.max(row).alias("b"), F.sum("prob").alias("s")).select("start_cell", (-F.col("b.e")).alias("end_cell"), F.try_divide(F.col("b.prob"), F.col("s")).alias("prob"))


__all__ = ["ReleasedSynopsis", "best_fit", "candidates", "extract_synopsis", "keyed_uniform", "length_laws", "mobility_model", "moment_parameters", "noisy_lengths", "release", "trip_distribution"]
