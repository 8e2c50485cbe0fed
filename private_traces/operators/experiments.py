"""The experiment workloads on the given tables, as long tables of results."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from private_traces.config import Bounds, SplitWeights, SynthesisConfig, equal_split, prior_split
from private_traces.sources.views import BOUNDS, VIEWS

from . import generator, lattice_model, metrics, statistics, tuning
from .synopsis import destination_given_start, extract_synopsis

FOUR = ("query_error", "pattern_support_error", "trip_error", "travel_distance_error")
GRID = "metric string, epsilon double, dataset string, method string, weights string, trial int, value double"


def runs(real: metrics.RealSide, stats: statistics.LeafStatistics, bounds: Bounds, cfg: SynthesisConfig, weights: SplitWeights, seeds: list[int], names=FOUR, n: int | None = None) -> list[tuple[str, int, float]]:
    """(metric, trial, value) of fresh runs with the given weights, each of the noisy number of traces where ``n`` is not given."""
    out = []
    for trial, s in enumerate(seeds):
        syn = extract_synopsis(real.traces, bounds, weights, cfg, stats, s, write=False)
        made = generator.generate(syn, n, s).persist()
        for m in names:
            out.append((m, trial, float(metrics.REGISTRY[m](real, made, real.total / n if n else 1.0).first().value)))
        for df in (made, syn.mobility, syn.trips, syn.lengths):
            df.unpersist()
    return out


def method_run(spark: SparkSession, sf_dir: str, view: str, weights: SplitWeights, cfg: SynthesisConfig, method: str, trials: int = 1, n: int | None = None) -> DataFrame:
    """One method on one view: every metric of the table, per trial."""
    bounds, traces = BOUNDS[view], VIEWS[view](spark, sf_dir)
    real = metrics.RealSide(traces, bounds)
    stats = statistics.leaf_statistics(real.traces, bounds, cfg.top_n, cfg.max_len).persist()
    found = runs(real, stats, bounds, cfg, weights, [cfg.seed + 101 * t for t in range(trials)], n=n)
    real.release()
    stats.unpersist()
    return spark.createDataFrame([(m, cfg.epsilon, view, method, str(weights.as_tuple()), s, v) for m, s, v in found], GRID)


def _sides(spark: SparkSession, datasets: list[tuple[str, str]], base: SynthesisConfig) -> dict[str, lattice_model.Tables]:
    """The real side of each (view, folder) in arrays."""
    out = {}
    for view, sf_dir in datasets:
        real = metrics.RealSide(VIEWS[view](spark, sf_dir), BOUNDS[view])
        stats = statistics.leaf_statistics(real.traces, BOUNDS[view], base.top_n, base.max_len).persist()
        out[view] = lattice_model.tables(real, stats)
        stats.unpersist()
        real.release()
    return out


def searches(bench: lattice_model.Bench, asked: list[tuple[str, SynthesisConfig, int]], names, explore: int, guided: int, seed: int) -> dict[tuple, tuple]:
    """(view, epsilon, metric) -> (weights, history) for each (view, settings, traces): one job for all random phases, which the metrics
    share, and one for all guided ones."""
    points = tuning.explored(explore, seed)
    found = bench.run([(v, cfg, w, seed, n) for v, cfg, n in asked for w in points], names)
    each = [(v, cfg.but(metric=m), n, [r[m] for r in found[i * explore : (i + 1) * explore]]) for i, (v, cfg, n) in enumerate(asked) for m in names]
    done = bench.guide([(v, cfg, points, known, guided, seed, n) for v, cfg, n, known in each])
    return {(v, cfg.epsilon, cfg.metric): got for (v, cfg, _, _), got in zip(each, done)}


def comparison_grid(spark: SparkSession, datasets: list[tuple[str, str]], epsilons=(0.5, 1.0, 2.0), names=FOUR, explore: int = 100, guided: int = 100, trials: int = 5, n_tune: int = 100_000, base: SynthesisConfig | None = None) -> DataFrame:
    """Every metric, epsilon, dataset (view, folder) and method: equal split, fixed split, tuned for that metric, random search with
    the same number of evaluations, and equal split with the best of as many redraws. All but the last are fresh runs with the
    chosen weights; the last is the least of its own draws."""
    base = base or SynthesisConfig()
    sides = _sides(spark, datasets, base)
    bench = lattice_model.Bench(spark, sides)
    asked = [(v, base.but(epsilon=e), min(n_tune, max(1, sides[v].total))) for v, _ in datasets for e in epsilons]
    tuned = searches(bench, asked, names, explore, guided, base.seed)
    every = tuning.explored(explore + guided, base.seed + 1)
    drawn = bench.run([(v, cfg, w, base.seed, n) for v, cfg, n in asked for w in every], names)
    again = bench.run([(v, cfg, every[0], base.seed + 31 * (t + 1), n) for v, cfg, n in asked for t in range(explore + guided)], names)
    rows, fixed, chosen = [], [], {m: [] for m in names}
    for i, (v, cfg, n) in enumerate(asked):
        own = slice(i * len(every), (i + 1) * len(every))
        for m in names:
            fresh = lambda method, w: [(method, (v, cfg.but(metric=m), w, base.seed + 7_000_000 + t, None), t) for t in range(trials)]  # noqa: B023, E731
            fixed += fresh("equal split", np.array(equal_split().as_tuple())) + fresh("fixed 10/40/40/10 split", np.array(prior_split().as_tuple()))
            chosen[m] += fresh("tuned", tuned[v, cfg.epsilon, m][0]) + fresh("random search", every[int(np.argmin([r[m] for r in drawn[own]]))])
            rows.append((m, cfg.epsilon, v, "equal split, best redraw", str(equal_split().as_tuple()), -1, float(min(r[m] for r in again[own]))))
    # the fixed splits are the same runs for all metrics; chosen ones are measured by their own metric only
    for runs_, measured in ((fixed, names), *((chosen[m], (m,)) for m in names)):
        for (method, (v, cfg, w, _, _), t), got in zip(runs_, bench.run([x for _, x, _ in runs_], measured)):
            rows.append((cfg.metric, cfg.epsilon, v, method, str(tuple(round(float(x), 4) for x in w)), t, float(got[cfg.metric])))
    return spark.createDataFrame(rows, GRID)


def summary(grid: DataFrame) -> DataFrame:
    """Mean and deviation per cell of the comparison."""
    return grid.groupBy("metric", "epsilon", "dataset", "method").agg(F.avg("value").alias("mean"), F.coalesce(F.stddev("value"), F.lit(0.0)).alias("sd"))


def pivoted(grid: DataFrame) -> DataFrame:
    return summary(grid).groupBy("metric", "epsilon").pivot("dataset").agg(F.concat_ws(" / ", F.sort_array(F.collect_list(F.concat_ws(" ", "method", F.format_number("mean", 3))))))


def weight_study(spark: SparkSession, combos: list[tuple[str, str, float]], names=FOUR, explore: int = 100, guided: int = 100, n_tune: int = 100_000, base: SynthesisConfig | None = None) -> DataFrame:
    """The winning weights of each (view, folder, epsilon) and metric."""
    base = base or SynthesisConfig()
    sides = _sides(spark, sorted({(v, d) for v, d, _ in combos}), base)
    asked = [(v, base.but(epsilon=e), min(n_tune, max(1, sides[v].total))) for v, _, e in combos]
    found = searches(lattice_model.Bench(spark, sides), asked, names, explore, guided, base.seed)
    return spark.createDataFrame([(*key, *map(float, w)) for key, (w, _) in found.items()], "dataset string, epsilon double, metric string, w1 double, w2 double, w3 double, w4 double")


def weight_distances(weights: DataFrame) -> DataFrame:
    """L1 distances between the weight vectors of a study (a dozen rows)."""
    a, b = weights.alias("a"), weights.alias("b")
    key = lambda t: F.concat_ws("|", f"{t}.dataset", f"{t}.epsilon", f"{t}.metric")
    return a.join(b, key("a") < key("b")).select(key("a").alias("left"), key("b").alias("right"), sum(F.abs(F.col(f"a.w{i}") - F.col(f"b.w{i}")) for i in range(1, 5)).alias("distance"))


def convergence_study(spark: SparkSession, sf_dir: str, view: str = "subset_trips", explore: int = 100, guided: int = 100, n_tune: int = 100_000, cfg: SynthesisConfig | None = None) -> DataFrame:
    """One tuning run's history, by default for the travel distance error: weights and error per evaluation."""
    cfg = cfg or SynthesisConfig(metric="travel_distance_error")
    sides = _sides(spark, [(view, sf_dir)], cfg)
    found = searches(lattice_model.Bench(spark, sides), [(view, cfg, min(n_tune, max(1, sides[view].total)))], (cfg.metric,), explore, guided, cfg.seed)
    return spark.createDataFrame(next(iter(found.values()))[1], tuning.HISTORY)


def granularity_study(spark: SparkSession, sf_dir: str, view: str = "drift_trips", grids=(None, 3, 6, 12, 50), cfg: SynthesisConfig = SynthesisConfig(), names=("trip_error",)) -> DataFrame:
    """Adaptive grid (None) against uniform ones, too coarse and too fine, and against no noise."""
    bounds, traces = BOUNDS[view], VIEWS[view](spark, sf_dir)
    real = metrics.RealSide(traces, bounds)
    rows = []
    for g in grids:
        for e in (cfg.epsilon, None):
            c = cfg.but(uniform_grid=g, epsilon=e)
            made = generator.generate(extract_synopsis(real.traces, bounds, equal_split(), c), None)  # the noisy number of traces
            rows += [("adaptive" if g is None else f"uniform {g}", e, m, float(metrics.REGISTRY[m](real, made, 1.0).first().value)) for m in names]
    return spark.createDataFrame(rows, "grid string, epsilon double, metric string, value double")


def demand_topk(paths: DataFrame, k: int = 10) -> DataFrame:
    """``start_cell, end_cell, n``: the busiest trips, ties by pair."""
    return statistics.trip_counts(paths).orderBy(F.desc("n"), "start_cell", "end_cell").limit(k)


def demand_by_start(paths: DataFrame) -> DataFrame:
    return statistics.trip_counts(paths).groupBy("start_cell").agg(F.sum("n").alias("n"))


__all__ = ["comparison_grid", "convergence_study", "demand_by_start", "demand_topk", "destination_given_start", "granularity_study", "method_run", "pivoted", "summary", "weight_distances", "weight_study"]
