"""Black-box search for the budget split with the least error: random exploration, then a Gaussian-process guide.

Each evaluation makes a synopsis from leaf statistics computed once, generates, and measures one metric against the
cached real side. The tuning loop compares synthetic with real data many times; in the ``paper`` accounting that is not
charged, and every result says so.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from private_traces.config import Bounds, SplitWeights, SynthesisConfig, equal_split, fresh_seed, prior_split

from . import generator, lattice_model, metrics, statistics
from .grid import uniform_grid
from .ledger import Ledger
from .synopsis import extract_synopsis, ledger_of

FLOOR = 0.005
HISTORY = "eval_id int, phase string, w1 double, w2 double, w3 double, w4 double, trial int, err double, best_so_far double, seconds double"


def sample_weights(n: int, seed: int, space: str = "dirichlet", around: np.ndarray | None = None, concentration: float = 50.0) -> np.ndarray:
    """Rows on the open simplex: ``dirichlet``, or ``box_then_normalise`` (raw numbers in (0, 1) divided by their sum)."""
    rng = np.random.default_rng(seed)
    if around is not None:
        w = rng.dirichlet(np.maximum(concentration * around, 0.05), n)
    elif space == "dirichlet":
        w = rng.dirichlet(np.ones(4), n)
    elif space == "box_then_normalise":
        w = rng.uniform(size=(n, 4))
    else:
        raise ValueError(f"unknown space: {space}")
    w = np.maximum(w, FLOOR)
    return w / w.sum(axis=1, keepdims=True)


def coordinates(w: np.ndarray) -> np.ndarray:
    """Log-ratios to the last weight."""
    return np.log(w[:, :3] / w[:, 3:])


class Surrogate:
    """Gaussian process with a Matern-5/2 kernel, one length scale per coordinate and a nugget, on standardised errors."""

    def fit(self, w: np.ndarray, err: np.ndarray, noise: float = 0.0) -> Surrogate:
        self.z = coordinates(w)
        self.mean, self.sd = float(err.mean()), float(err.std()) or 1.0
        self.y = (err - self.mean) / self.sd
        base = np.maximum(self.z.std(axis=0), 1e-3)
        options = [(s * base, n) for s in (0.5, 1.0, 2.0, 4.0) for n in (1e-3, 1e-2, 1e-1, 0.5)]
        floor = noise / self.sd**2
        best = max(options, key=lambda o: self._likelihood(o[0], o[1] + floor))
        scales, nugget = best
        for i in range(3):  # one round of coordinate refinement
            tries = [np.where(np.arange(3) == i, scales * f, scales) for f in (0.5, 1.0, 2.0)]
            scales = max(tries, key=lambda s: self._likelihood(s, nugget + floor))
        self._likelihood(scales, nugget + floor)
        return self

    def _kernel(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        d = np.sqrt(5 * np.maximum(0, (((a[:, None, :] - b[None, :, :]) / self.scales) ** 2).sum(axis=2)))
        return (1 + d + d * d / 3) * np.exp(-d)

    def _likelihood(self, scales: np.ndarray, nugget: float) -> float:
        self.scales, self.nugget = scales, nugget
        k = self._kernel(self.z, self.z) + (nugget + 1e-8) * np.eye(len(self.z))
        self.chol = np.linalg.cholesky(k)
        self.alpha = np.linalg.solve(self.chol.T, np.linalg.solve(self.chol, self.y))
        return float(-0.5 * self.y @ self.alpha - np.log(np.diag(self.chol)).sum())

    def predict(self, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Posterior mean and standard deviation of the error."""
        k = self._kernel(coordinates(w), self.z)
        v = np.linalg.solve(self.chol, k.T)
        var = np.maximum(1e-12, 1 - (v * v).sum(axis=0))
        return self.mean + self.sd * (k @ self.alpha), self.sd * np.sqrt(var)


def acquisition(model: Surrogate, points: np.ndarray, best: float, kind: str = "ei") -> np.ndarray:
    """Expected improvement, lower confidence bound (negated) or probability of improvement."""
    mu, sd = model.predict(points)
    u = (best - mu) / sd
    cdf = 0.5 * (1 + np.array([math.erf(x / math.sqrt(2)) for x in u]))
    if kind == "ei":
        return (best - mu) * cdf + sd * np.exp(-u * u / 2) / math.sqrt(2 * math.pi)
    if kind == "lcb":
        return 2 * sd - mu
    if kind == "pi":
        return cdf
    raise ValueError(f"unknown acquisition: {kind}")


def next_point(model: Surrogate, tried: np.ndarray, seed: int, kind: str = "ei", candidates: int = 4096, space: str = "dirichlet") -> tuple[np.ndarray, float]:
    """The candidate of largest acquisition: half of them anywhere on the simplex, half around the incumbent. The target is the
    best posterior mean at tried points, which noise misleads less than the best value seen."""
    mu, _ = model.predict(tried)
    incumbent = tried[int(mu.argmin())]
    points = np.concatenate([sample_weights(candidates // 2, seed, space), sample_weights(candidates // 2, seed + 1, around=incumbent)])
    gain = acquisition(model, points, float(mu.min()), kind)
    return points[int(gain.argmax())], float(gain.max())


@dataclass
class TuningResult:
    """The chosen weights, the history, and how privacy was accounted."""

    weights: SplitWeights
    history: list[tuple] = field(default_factory=list)
    accounting: str = "paper"
    finalise: Callable[[], tuple] | None = None

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.history, HISTORY)


def minimise(objective: Callable[[np.ndarray, int], float], explore: int = 100, guided: int = 100, seed: int = 42, *, trials: int = 1, kind: str = "ei", space: str = "dirichlet", start: list[SplitWeights] | None = None, select: str = "posterior", patience: int | None = None, batch: int = 1, record: Callable[[tuple], None] | None = None, random_only: bool = False, known: tuple[np.ndarray, list[float]] | None = None) -> tuple[np.ndarray, list[tuple]]:
    """The search itself over any objective(weights, trial seed). ``batch`` > 1 proposes several points per round, each assumed to
    come out at the predicted mean; ``random_only`` is the ablation without a model; ``known``: explored points and their errors,
    evaluated before in one go."""
    given = [np.array(w.as_tuple()) for w in (start if start is not None else [equal_split(), prior_split()])][: max(1, explore)]
    first = np.concatenate([np.array(given), sample_weights(max(0, explore - len(given)), seed, space)]) if given else sample_weights(explore, seed, space)
    tried: list[np.ndarray] = []
    errors: list[float] = []
    history: list[tuple] = []

    def evaluate(w: np.ndarray, phase: str) -> None:
        began = time.time()
        values = [objective(w, seed + 1000 * t) for t in range(trials)]
        tried.append(w)
        errors.append(float(np.mean(values)))
        row = (len(tried) - 1, phase, *map(float, w), trials, errors[-1], min(errors), time.time() - began)
        history.append(row)
        if record:
            record(row)

    for w in first if known is None else ():
        evaluate(w, "explore")
    for w, err in zip(*known) if known is not None else ():
        tried.append(w)
        errors.append(err)
        history.append((len(tried) - 1, "explore", *map(float, w), trials, err, min(errors), 0.0))
        if record:
            record(history[-1])
    stale, step = 0, 0
    while step < guided:
        if random_only:
            evaluate(sample_weights(1, seed + 77 + step, space)[0], "random")
            step += 1
            continue
        points, values = list(tried), list(errors)
        gain = 0.0
        for _ in range(min(batch, guided - step)):
            model = Surrogate().fit(np.array(points), np.array(values))
            w, gain = next_point(model, np.array(points), seed + 31 * (step + 1), kind, space=space)
            points.append(w)
            values.append(float(model.predict(w[None])[0][0]))
        before = min(errors)
        for w in points[len(tried) :]:
            evaluate(w, "guided")
            step += 1
        stale = 0 if min(errors) < before else stale + 1
        if patience and stale >= patience and gain < 1e-3 * max(1e-12, abs(before)):
            break
    points = np.array(tried)
    if select == "observed" or random_only or len(points) < 3:
        return points[int(np.argmin(errors))], history
    mu, _ = Surrogate().fit(points, np.array(errors)).predict(points)
    return points[int(mu.argmin())], history


def objective_of(real: metrics.RealSide, stats: statistics.LeafStatistics, bounds: Bounds, cfg: SynthesisConfig, metric: str, n_tune: int, fresh: bool = False) -> Callable[[np.ndarray, int], float]:
    """weights -> error of one run. With ``fresh`` False all candidates share their draws (common random numbers), so they
    differ in scale only; counts of the ``n_tune`` synthetic traces are scaled to the real number."""
    count = [0]

    def run(w: np.ndarray, seed: int) -> float:
        count[0] += 1
        syn = extract_synopsis(real.traces, bounds, SplitWeights.of(w), cfg, stats, seed + (7919 * count[0] if fresh else 0), write=False)
        n = min(n_tune, max(1, real.total))
        made = generator.generate(syn, n, seed)
        value = float(metrics.REGISTRY[metric](real, made, real.total / n).first().value)
        for df in (syn.mobility, syn.trips, syn.lengths):
            df.unpersist()
        return value

    return run


def explored(explore: int, seed: int, space: str = "dirichlet") -> np.ndarray:
    """The points of the random phase: both fixed splits first."""
    given = np.array([w.as_tuple() for w in (equal_split(), prior_split())][: max(1, explore)])
    return np.concatenate([given, sample_weights(max(0, explore - len(given)), seed, space)])


def in_arrays(cfg: SynthesisConfig) -> bool:
    """Whether runs with these settings can be evaluated in arrays."""
    plain = not cfg.collapse_repeats and (cfg.params_from, cfg.fit_on, cfg.noise_on, cfg.mechanism, cfg.walk, cfg.allocation, cfg.trips_per_trace) == ("histogram", "noisy", "count", "laplace", "bridge", "random", 1)
    return plain and cfg.metric in lattice_model.FOUR and cfg.split_rule in ("target", "thresholds", "noise_guided") and (cfg.uniform_grid is None or uniform_grid(Bounds(0, 1, 0, 1), cfg.uniform_grid, cfg.top_n).top_n == cfg.top_n)


ACCOUNTINGS = ("paper", "public_proxy", "private_selection", "charged")


def spent(cfg: SynthesisConfig, evaluations: int, accounting: str, look_epsilon: float = 0.01) -> float:
    """Epsilon a tuned release costs: ``paper`` does not charge the loop; ``public_proxy`` tunes on traces that are not private;
    ``private_selection`` picks the best of a geometric number of private candidates by private scores, at three times one
    candidate and its score; ``charged`` adds a noised look per evaluation."""
    e = cfg.epsilon or 0.0
    return {"paper": e, "public_proxy": e, "private_selection": 3 * (e + look_epsilon), "charged": e + evaluations * look_epsilon}[accounting]


def charged_ledger(cfg: SynthesisConfig, weights: SplitWeights, evaluations: int, accounting: str, look_epsilon: float = 0.01) -> Ledger:
    """The ledger of a tuned release, its tuning included."""
    book = ledger_of(cfg, weights)
    if cfg.epsilon is None:
        return book
    if accounting == "paper":
        return book.leak("tuning", f"{evaluations} exact looks, not charged")
    if accounting == "charged":
        return book.spend_sequential("tuning", evaluations * look_epsilon)
    if accounting == "private_selection":
        return book.spend_sequential("tuning", spent(cfg, evaluations, accounting, look_epsilon) - cfg.epsilon, mechanism="selection")
    return book.free("tuning", "public traces")


def noised(plain: Callable[[np.ndarray, int], float], epsilon: float, most: float) -> Callable[[np.ndarray, int], float]:
    """The error, clipped to 0..``most``, which bounds its sensitivity, with Laplace noise from secret bits."""
    rng = np.random.default_rng(fresh_seed())
    return lambda w, s: min(max(plain(w, s), 0.0), most) + float(rng.laplace(scale=most / epsilon))


def tune(traces: DataFrame, bounds: Bounds, cfg: SynthesisConfig, n_tune: int = 100_000, accounting: str = "paper", proxy: DataFrame | None = None, look_epsilon: float = 0.01, sensitivity: float | None = None, **search) -> TuningResult:
    """Tune the split for ``cfg.metric``, then finalise with the winning weights.

    ``charged`` and ``private_selection`` see errors with Laplace noise of ``sensitivity / look_epsilon``; a metric that is not in
    ``metrics.SENSITIVITY`` needs a ``sensitivity``, to which its values are clipped. The final release draws noise that no
    evaluation used, but for ``private_selection``: there the release is the chosen candidate itself, as its bound requires, and
    the number of candidates is a geometric draw from secret bits with mean ``cfg.explore``, without a cap."""
    if accounting not in ACCOUNTINGS:
        raise ValueError(f"unknown accounting: {accounting}")
    if accounting == "public_proxy" and proxy is None:
        raise ValueError("public_proxy needs a proxy: the private traces are not public")
    most = metrics.SENSITIVITY.get(cfg.metric) if sensitivity is None else sensitivity
    if accounting in ("charged", "private_selection") and most is None:
        raise ValueError(f"{cfg.metric} has no bound: give a sensitivity, to which its values are clipped")
    real = metrics.RealSide(proxy if accounting == "public_proxy" else traces, bounds)
    stats = statistics.leaf_statistics(real.traces, bounds, cfg.top_n, cfg.max_len, cfg.collapse_repeats).persist()
    final_seed, bench = fresh_seed(), None
    if in_arrays(cfg) and accounting != "private_selection":  # there the release must be the very synopsis that was scored
        bench, n = lattice_model.Bench(traces.sparkSession, {"": lattice_model.tables(real, stats)}), min(n_tune, max(1, real.total))
        plain = lambda w, s: bench.run([("", cfg, w, s, n)], (cfg.metric,))[0][cfg.metric]
    else:
        plain = objective_of(real, stats, bounds, cfg, cfg.metric, n_tune)
    if accounting == "private_selection":
        score, space = noised(plain, look_epsilon, most), search.get("space", "dirichlet")
        rounds = int(np.random.default_rng(fresh_seed()).geometric(1 / max(1, cfg.explore)))
        history, best_seen = [], math.inf
        for i, v in enumerate(sample_weights(rounds, fresh_seed(), space)):
            began, s = time.time(), fresh_seed()
            err = score(v, s)
            if err < best_seen:
                w, best_seen, final_seed = v, err, s
            history.append((i, "selection", *map(float, v), 1, err, best_seen, time.time() - began))
    else:
        run = noised(plain, look_epsilon, most) if accounting == "charged" else plain
        if bench is not None and accounting != "charged" and cfg.trials == 1 and not {"start", "space"} & set(search):  # the random phase in one job
            points = explored(cfg.explore, cfg.seed)
            search["known"] = points, [r[cfg.metric] for r in bench.run([("", cfg, w, cfg.seed, n) for w in points], (cfg.metric,))]
        w, history = minimise(run, cfg.explore, cfg.guided, cfg.seed, trials=cfg.trials, **search)
    best = SplitWeights.of(w)
    looks = len(history) * (1 if accounting == "private_selection" else cfg.trials)

    def finalise():
        syn = extract_synopsis(traces, bounds, best, cfg, seed=final_seed)
        syn.ledger = charged_ledger(cfg, best, looks, accounting, look_epsilon)
        return generator.generate(syn, seed=fresh_seed()), syn

    real.release()
    stats.unpersist()
    return TuningResult(best, history, accounting, finalise)


def history_sink(spark: SparkSession, path: str) -> Callable[[tuple], None]:
    """Append each evaluation to a folder that can be followed as a stream."""

    def record(row: tuple) -> None:
        spark.createDataFrame([row], HISTORY).write.mode("append").parquet(path)

    return record


def history_stream(spark: SparkSession, path: str) -> DataFrame:
    return spark.readStream.schema(HISTORY).parquet(path)


def progress(history: DataFrame, planned: int) -> DataFrame:
    """``done, total, fraction, best``."""
    return history.agg(F.count("*").alias("done"), F.lit(planned).cast("long").alias("total"), (F.count("*") / planned).alias("fraction"), F.min("err").alias("best"))
