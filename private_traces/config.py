"""Settings of a synthesis run and the shares of the privacy budget."""

from __future__ import annotations

import json
import secrets
from dataclasses import asdict, dataclass, field, replace


@dataclass(frozen=True)
class Bounds:
    """The public rectangle that readings live in; never taken from the data."""

    x0: float
    x1: float
    y0: float
    y1: float


@dataclass(frozen=True)
class SplitWeights:
    """Shares of epsilon for grid, mobility, trips and lengths: each in (0, 1), together 1."""

    grid: float
    mobility: float
    trips: float
    lengths: float

    def validate(self) -> SplitWeights:
        w = self.as_tuple()
        if any(not 0 < x < 1 for x in w) or abs(sum(w) - 1) > 1e-9:
            raise ValueError(f"shares must lie in (0, 1) and sum to 1: {w}")
        return self

    def as_tuple(self) -> tuple[float, float, float, float]:
        return self.grid, self.mobility, self.trips, self.lengths

    @classmethod
    def of(cls, raw) -> SplitWeights:
        """Raw positive numbers divided by their sum."""
        total = float(sum(raw))
        return cls(*(float(x) / total for x in raw)).validate()


def equal_split() -> SplitWeights:
    return SplitWeights(0.25, 0.25, 0.25, 0.25)


def prior_split(weights: SplitWeights = SplitWeights(0.1, 0.4, 0.4, 0.1)) -> SplitWeights:
    """A fixed split given by the caller. The default is a placeholder of ours, reported as "fixed 10/40/40/10 split"."""
    return weights.validate()


def fresh_seed() -> int:
    """128 secret bits."""
    return secrets.randbits(128)


@dataclass(frozen=True)
class SynthesisConfig:
    """What a run takes. ``epsilon`` None means no noise (the upper bound on utility).

    All noise is a function of ``seed``: who knows it can take the noise off again. Where none is given, one of 128 secret bits is
    drawn; it is left out of JSON, reports and ``repr``. A fixed seed is for tests and oracles. ``cuts``: the densities of the
    split rule ``thresholds``. ``mechanism``: ``laplace``, or ``geometric`` for the integer counts of trips and lengths."""

    epsilon: float | None = 1.0
    metric: str = "trip_error"
    top_n: int = 6
    trials: int = 1
    explore: int = 100
    guided: int = 100
    seed: int | None = field(default=None, repr=False, compare=False)
    max_len: int = 32
    split_rule: str = "target"
    cells_per_top: float = 1.0
    clean_up: str = "shift"
    total: str = "counts"
    noise_on: str = "count"
    test: str = "chi2"
    fit_on: str = "noisy"
    params_from: str = "histogram"
    min_support: float = 20.0
    pool_share: float = 0.5
    uniform_grid: int | None = None
    collapse_repeats: bool = False
    walk: str = "bridge"
    allocation: str = "random"
    n_out: str | int = "noisy"
    trips_per_trace: int = 1
    noise_source: str = "md5"
    cuts: tuple[float, ...] = ()
    mechanism: str = "laplace"

    def __post_init__(self):
        if self.seed is None:
            object.__setattr__(self, "seed", fresh_seed())
        if self.split_rule == "thresholds" and not self.cuts:
            raise ValueError("the split rule thresholds needs cuts")
        if self.mechanism not in ("laplace", "geometric"):
            raise ValueError(f"unknown mechanism: {self.mechanism}")

    def to_json(self) -> str:
        """The settings without the seed."""
        return json.dumps({k: v for k, v in asdict(self).items() if k != "seed"}, sort_keys=True)

    @classmethod
    def from_json(cls, text: str) -> SynthesisConfig:
        """The settings again, with a fresh seed."""
        given = json.loads(text)
        return cls(**given | {"cuts": tuple(given.get("cuts", ()))})

    def but(self, **changes) -> SynthesisConfig:
        return replace(self, **changes)
