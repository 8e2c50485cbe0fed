"""The registered granularity study compares every grid of the operator's default."""

from private_traces.operators import experiments
from private_traces.plans import catalog


def test_too_coarse_and_too_detailed_grids_are_compared(spark, sf, monkeypatch):
    seen = []
    monkeypatch.setattr(experiments, "extract_synopsis", lambda traces, bounds, weights, cfg: seen.append((cfg.uniform_grid, cfg.epsilon)) or traces)
    monkeypatch.setattr(experiments.generator, "generate", lambda traces, n: traces)
    rows = catalog.QUERIES["granularity_study"](spark, sf).collect()
    assert seen == [(g, e) for g in (None, 3, 6, 12, 50) for e in (1.0, None)] and "uniform 50" in {r.grid for r in rows}
