"""What a release may not give away, and what tuning costs."""

import json
import math

import numpy as np
import pytest

from private_traces.config import Bounds, SynthesisConfig, equal_split
from private_traces.functions import noise
from private_traces.operators import experiments, metrics, report, statistics, synopsis, tuning
from private_traces.sources import views

UNIT = Bounds(0.0, 1.0, 0.0, 1.0)


@pytest.fixture(scope="module")
def drift(spark, sf):
    return views.drift_trips(spark, sf).persist()


def test_no_seed_is_public(spark):
    a, b = SynthesisConfig(), SynthesisConfig()
    assert a.seed != b.seed and a == b and max(a.seed, b.seed) > 1 << 100
    shown = a.to_json() + repr(a) + str([tuple(r) for r in report.inputs(spark, a).collect()])
    assert str(a.seed) not in shown and "seed" not in json.loads(a.to_json())
    again = SynthesisConfig.from_json(a.but(cuts=(1.0, 2.0, 3.0), split_rule="thresholds").to_json())
    assert again.cuts == (1.0, 2.0, 3.0) and again.seed != a.seed
    with pytest.raises(ValueError):
        SynthesisConfig(split_rule="thresholds")


def test_two_releases_without_a_seed_differ(drift):
    made = [synopsis.extract_synopsis(drift, UNIT, equal_split(), SynthesisConfig(top_n=2)).trips.orderBy("start_cell", "end_cell").collect() for _ in range(2)]
    assert made[0] != made[1]


def test_thresholds_split_and_geometric_counts(drift):
    cfg = SynthesisConfig(top_n=3, split_rule="thresholds", cuts=(1.0, 1e9, 1e9), mechanism="geometric", clean_up="clip")
    syn = synopsis.extract_synopsis(drift, UNIT, equal_split(), cfg)
    assert set(syn.grid.levels) - {1} and syn.trips.where("abs(mass - round(mass)) > 1e-9").count() == 0


def test_leaks_are_in_the_ledger():
    for changes in ({"noise_on": "probability"}, {"fit_on": "true"}, {"n_out": "exact"}):
        assert math.isinf(synopsis.ledger_of(SynthesisConfig(**changes), equal_split()).total)
    cfg, w = SynthesisConfig(epsilon=1.0), equal_split()
    total = {a: tuning.charged_ledger(cfg, w, 50, a, 0.02).total for a in tuning.ACCOUNTINGS}
    assert math.isinf(total["paper"]) and total["public_proxy"] == pytest.approx(1.0)
    assert total["charged"] == pytest.approx(2.0) and total["private_selection"] == pytest.approx(3.06)


def test_the_final_release_uses_noise_of_its_own(drift, monkeypatch):
    used = []
    plain = synopsis.extract_synopsis
    monkeypatch.setattr(tuning, "extract_synopsis", lambda t, b, w, c, stats=None, seed=None, write=True: (used.append((seed, tuple(np.round(w.as_tuple(), 9)))), plain(t, b, w, c, stats, seed, write))[1])
    cfg = SynthesisConfig(top_n=2, explore=2, guided=0)
    found = tuning.tune(drift, UNIT, cfg, 100)
    found.finalise()
    assert used[-1][0] not in {s for s, _ in used[:-1]}
    used.clear()
    found = tuning.tune(drift, UNIT, cfg, 100, "private_selection", look_epsilon=0.5)
    _, syn = found.finalise()
    assert used[-1] in used[:-1] and syn.ledger.total == pytest.approx(4.5) and found.history[-1][8] == min(h[7] for h in found.history)


def test_tuning_refuses_what_it_cannot_account_for(drift):
    cfg = SynthesisConfig(metric="query_error")
    for bad in ({"accounting": "public_proxy"}, {"accounting": "charged"}, {"accounting": "private_selection"}, {"accounting": "none"}):
        with pytest.raises(ValueError):
            tuning.tune(drift, UNIT, cfg, 100, **bad)


def test_runs_of_collapsed_paths(drift):
    real = metrics.RealSide(drift, UNIT)
    cfg = SynthesisConfig(top_n=2, collapse_repeats=True)
    stats = statistics.leaf_statistics(drift, UNIT, 2, 32, True)
    assert 0 <= tuning.objective_of(real, stats, UNIT, cfg, "trip_error", 100)(np.full(4, 0.25), 1) <= 1
    assert [t for _, t, _ in experiments.runs(real, stats, UNIT, cfg, equal_split(), [5, 6], ("trip_error",), 100)] == [0, 1]
    real.release()


def test_sparse_noise_draws_a_binomial_number(spark):
    none = spark.createDataFrame([(0, 1000.0)], "k long, m double")
    counts = [noise.sparse_noise(none, 40, "k", "m", 1.0, 2.0, s, "t").where("k != 0").count() for s in range(60)]
    p = 0.5 * math.exp(-2.0)
    assert abs(np.mean(counts) - 39 * p) < 4 * math.sqrt(39 * p * (1 - p) / 60) and min(counts) < max(counts)
