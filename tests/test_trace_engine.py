"""Worked examples, invariants and audits of the trace engine on small inputs."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from private_traces.config import Bounds, SplitWeights, SynthesisConfig, equal_split, prior_split
from private_traces.functions import lattice, noise
from private_traces.operators import experiments, generator, grid, ledger, metrics, relational, report, statistics, synopsis, tuning
from private_traces.sources import views
from private_traces.streaming import sessions

UNIT = Bounds(0, 1, 0, 1)
CFG = SynthesisConfig(seed=42)


@pytest.fixture(scope="module")
def drift(spark, sf):
    return views.drift_trips(spark, sf).persist()


@pytest.fixture(scope="module")
def syn(drift):
    return synopsis.extract_synopsis(drift, UNIT, equal_split(), CFG)


def test_weights_must_lie_on_the_open_simplex():
    assert equal_split().validate() and prior_split()
    for bad in ((0.5, 0.5, 0.0, 0.0), (0.3, 0.3, 0.3, 0.3), (1.2, -0.2, 0.0, 0.0)):
        with pytest.raises(ValueError):
            SplitWeights(*bad).validate()
    assert abs(sum(SplitWeights.of([3, 1, 1, 5]).as_tuple()) - 1) < 1e-12
    assert SynthesisConfig.from_json(CFG.but(epsilon=2.0).to_json()).epsilon == 2.0


def test_worked_grid(spark):
    """Densities low, medium, medium, high on 2 x 2 top cells: 1 + 4 + 4 + 9 cells, numbered through."""
    dens = spark.createDataFrame([(0, 1.0), (1, 5.0), (2, 5.0), (3, 20.0)], "top int, density double")
    spec = grid.grid_spec(dens, "thresholds", cuts=[3, 10, 100])
    g = grid.build_grid(spec, UNIT, 2)
    assert g.levels == (1, 2, 2, 3) and g.size == 18 and g.firsts == (0, 1, 5, 9)
    assert [r[0] + 1 for r in g.rectangles()] == list(range(1, 19))
    near = g.neighbour_pairs()
    assert all((b, a) in near for a, b in near) and len({a for a, b in near if a == b}) == 18


def test_worked_histogram(spark):
    """Ten traces of length 2, five of 3 and a decaying tail: counts as given, and the decaying law wins."""
    rows = [(0, 1, 2, 10), (0, 1, 3, 5), (0, 1, 4, 2), (0, 1, 5, 1)]
    hist = spark.createDataFrame(rows, "start_cell int, end_cell int, len int, n bigint")
    pairs = hist.select("start_cell", "end_cell").distinct()
    dense = synopsis.noisy_lengths(hist, pairs, None, 8, 1)
    assert {r.len: r.n for r in dense.collect()} == {1: 0, 2: 10, 3: 5, 4: 2, 5: 1, 6: 0, 7: 0, 8: 0}
    start = spark.createDataFrame([(0, 1, k, int(1000 * 0.5**k)) for k in range(1, 9)], "start_cell int, end_cell int, len int, n bigint")
    for test in ("chi2", "ks", "loglik"):
        best = synopsis.best_fit(synopsis.candidates(synopsis.noisy_lengths(start, pairs, None, 8, 1), 8), test).first()
        assert best.family == "exponential", test
    flat = spark.createDataFrame([(0, 1, k, 50 if k <= 5 else 0) for k in range(1, 9)], "start_cell int, end_cell int, len int, n bigint")
    assert synopsis.best_fit(synopsis.candidates(synopsis.noisy_lengths(flat, pairs, None, 8, 1), 8)).first().family == "uniform"


def test_every_raw_statistic_has_its_declared_sensitivity(spark, drift):
    ids = [r.trace_id for r in drift.orderBy(F.desc("n"), "trace_id").limit(2).collect()] + [r.trace_id for r in drift.where("n = 1").limit(1).collect()]
    for own in ids:
        less = ledger.neighbours(drift, own)
        for f, keys, v in ((statistics.density, ["cell"], "density"), (statistics.transitions, ["src", "dst"], "weight"), (statistics.trip_counts, ["start_cell", "end_cell"], "n"), (lambda p: statistics.length_histogram(p, 32), ["start_cell", "end_cell", "len"], "n")):
            a, b = (f(statistics.leaf_paths(d, UNIT, 6)).withColumnRenamed(v, name) for d, name in ((drift, "a"), (less, "b")))
            change = a.join(b, keys, "full").agg(F.sum(F.abs(F.coalesce("a", F.lit(0)) - F.coalesce("b", F.lit(0)))).alias("d")).first().d
            assert change <= 1 + 1e-6, (own, keys, change)


def test_noise_laws(spark):
    draws = np.array([r.d for r in spark.range(20000).select(noise.laplace(2.0, 1, "t", "id").alias("d")).collect()])
    assert abs(draws.mean()) < 0.1 and abs(np.abs(draws).mean() - 2) < 0.1
    geo = np.array([r.d for r in spark.range(20000).select(noise.geometric(0.5, 1, "t", "id").alias("d")).collect()])
    q = math.exp(-0.5)
    assert abs(geo.mean()) < 0.15 and abs(geo.var() - 2 * q / (1 - q) ** 2) < 0.8
    fast = np.array([r.d for r in spark.range(20000).select(noise.keyed_uniform(1, "t", "id", source="xxhash64").alias("d")).collect()])
    assert abs(fast.mean() - 0.5) < 0.01 and 0 < fast.min() and fast.max() < 1


def test_clean_up(spark):
    df = spark.createDataFrame([("a", i, float(v)) for i, v in enumerate([5, 3, -1, -2, 0.5])], "g string, k int, m double")
    for mode in ("clip", "shift", "threshold"):
        out = [r.m for r in noise.clean_up(df, "m", ["g"], mode, threshold=1.0).orderBy("k").collect()]
        assert min(out) >= 0
        if mode == "shift":
            assert abs(sum(out) - 5.5) < 1e-9
    assert noise.to_probabilities(noise.clean_up(df, "m", [], "shift"), "m", []).agg(F.sum("prob")).first()[0] == pytest.approx(1)


def test_sparse_noise_has_the_size_of_dense_noise(spark):
    stats = spark.createDataFrame([(i, 50.0) for i in range(20)], "k bigint, m double")
    out = noise.sparse_noise(stats, 100_000, "k", "m", 2.0, 10.0, 3, "s")
    want = 100_000 * 0.5 * math.exp(-5)
    assert abs(out.where("k >= 20").count() - want) < 5 * math.sqrt(want) and out.where("k < 20").count() == 20
    assert out.agg(F.min("m")).first()[0] >= 10


def test_empty_cells_and_pairs_are_noised_and_released_tables_repeat(spark, drift):
    stats = statistics.leaf_statistics(drift, UNIT, 6, 32)
    noisy = grid.noisy_density(stats.top_density(), 6, 0.25, 42)
    assert noisy.count() == 36
    again = grid.noisy_density(statistics.leaf_statistics(drift.repartition(7), UNIT, 6, 32).top_density(), 6, 0.25, 42)
    assert {(r.top, round(r.density, 6)) for r in noisy.collect()} == {(r.top, round(r.density, 6)) for r in again.collect()}
    g = grid.build_grid(grid.grid_spec(noisy), UNIT, 6)
    moved, trips, _ = stats.roll_up(g.cell_of)
    assert synopsis.mobility_model(moved, g, 0.25, 42).count() == g.size**2
    for row in synopsis.mobility_model(moved, g, 0.25, 42).groupBy("src").agg(F.sum("prob").alias("p")).collect():
        assert row.p == pytest.approx(1)
    assert synopsis.trip_distribution(trips, g, 0.25, 42).agg(F.sum("prob")).first()[0] == pytest.approx(1)


def test_roll_up_is_exact_for_every_level(spark, drift):
    stats = statistics.leaf_statistics(drift, UNIT, 6, 32)
    levels = [lattice.LEVELS[i % 4] for i in range(36)]
    firsts = np.cumsum([0, *[m * m for m in levels]])[:-1].tolist()
    cell_of = statistics.column_of(levels, firsts, 6)
    for rolled, direct, keys, v in zip(stats.roll_up(cell_of), statistics.direct_statistics(drift, UNIT, 6, 32, cell_of), (["src", "dst"], ["start_cell", "end_cell"], ["start_cell", "end_cell", "len"]), ("weight", "n", "n")):
        a, b = ({tuple(r[k] for k in keys): round(float(r[v]), 6) for r in d.collect()} for d in (rolled, direct))
        assert a == b


def test_ledger_adds_up_to_epsilon(spark):
    for cfg in (CFG, CFG.but(total="separate"), CFG.but(pool_share=0.0)):
        assert synopsis.ledger_of(cfg, prior_split()).total == pytest.approx(cfg.epsilon)
    assert synopsis.ledger_of(CFG.but(epsilon=None), equal_split()).total == 0
    assert ledger.Ledger().spend_parallel("x", [0.1, 0.3]).spend_sequential("y", 0.2).total == pytest.approx(0.5)


@pytest.mark.parametrize("mode", ["bridge", "forced_end", "reject"])
def test_walks_keep_their_ends(spark, syn, mode):
    trips = generator.draw_lengths(generator.draw_trips(syn.trips, 400, 1), syn.lengths, 32, 1).persist()
    rows = generator.walk(trips, syn.mobility, syn.grid.size, 1, mode).join(trips.drop("n"), "trace_id").collect()
    assert len(rows) == 400
    for r in rows:
        assert r.cells[0] == r.start_cell and r.cells[-1] == r.end_cell and len(r.cells) == r.n and 1 <= r.n <= 32
        assert all(0 <= c < syn.grid.size for c in r.cells)


def test_bridge_follows_the_conditional_law():
    p = np.array([[0.5, 0.3, 0.2], [0.1, 0.6, 0.3], [0.4, 0.4, 0.2]])
    n, size = 4, 60000
    u = generator._uniforms(3, np.arange(size), n)
    out, jump = generator.bridge_paths(p, 2, np.zeros(size, np.int64), np.full(size, n), u)
    assert not jump.any()
    law = {(a, b): p[0, a] * p[a, b] * p[b, 2] for a in range(3) for b in range(3)}
    total = sum(law.values())
    for (a, b), w in law.items():
        seen = ((out[:, 1] == a) & (out[:, 2] == b)).mean()
        assert abs(seen - w / total) < 0.01


def test_unreachable_ends_jump():
    p = np.eye(3)
    out, jump = generator.bridge_paths(p, 2, np.array([0]), np.array([3]), np.full((1, 3), 0.5))
    assert jump.all() and out[0].tolist() == [0, 0, 2]


def test_generation_reads_no_real_data_and_copies_no_trace(spark, drift, syn):
    made = generator.generate(syn, 500).persist()
    plan = made._jdf.queryExecution().toString()
    assert "lineitem" not in plan and made.count() == 500
    cells = {r.cell: r for r in syn.grid.cells(spark).collect()}
    assert made.select(F.inline("path")).where("x < 0 or x > 1 or y < 0 or y > 1").count() == 0 and cells
    key = lambda d: d.select(F.transform("path", lambda p: F.concat_ws(",", F.round(p["x"], 6), F.round(p["y"], 6))).alias("k"))
    assert key(made).join(key(drift), "k", "left_semi").count() == 0
    assert made.where("n != size(path)").count() == 0


def test_multi_trip_chains(spark, sf):
    long = views.user_long(spark, sf)
    cfg = CFG.but(trips_per_trace=3, top_n=3, max_len=64, epsilon=5.0)
    s = synopsis.extract_synopsis(long, views.BOUNDS["user_long"], equal_split(), cfg)
    trips = generator.chained_trips(s, 50, 3, 1).collect()
    by = {(r.trace, r.trip): r for r in trips}
    assert len(by) == 150 and all(by[t, j].end_cell == by[t, j + 1].start_cell for t in range(50) for j in range(2))
    assert generator.generate(s, 50).count() == 50


def test_draws_follow_the_distribution(spark, syn):
    n = 4000
    got = {(r.start_cell, r.end_cell): r["count"] for r in generator.draw_trips(syn.trips, n, 9).groupBy("start_cell", "end_cell").count().collect()}
    assert sum(got.values()) == n
    top = syn.trips.orderBy(F.desc("prob")).limit(5).collect()
    for r in top:
        assert abs(got.get((r.start_cell, r.end_cell), 0) / n - r.prob) < 5 * math.sqrt(r.prob / n) + 1e-3
    assert generator.draw_trips(syn.trips, n, 9, "quota").count() == n


def test_metrics_are_zero_for_equal_sets_and_bounded(spark, drift):
    real = metrics.RealSide(drift, UNIT)
    report_ = {r.metric: r.value for r in metrics.error_report(real, drift).collect()}
    for name, value in report_.items():
        want = 1.0 if name in ("pattern_jaccard", "pattern_f1") else None if name == "next_cell_accuracy" else 0.0
        assert want is None or value == pytest.approx(want, abs=1e-9), name
    empty = {r.metric: r.value for r in metrics.error_report(real, drift.limit(0), ["trip_error", "travel_distance_error", "query_error"]).collect()}
    assert empty["trip_error"] == 1.0 and empty["travel_distance_error"] == 1.0 and 0 < empty["query_error"] <= 1


def test_jsd_is_symmetric(spark):
    a = spark.createDataFrame([(1, 3.0), (2, 1.0)], "k int, mass double")
    b = spark.createDataFrame([(2, 1.0), (3, 5.0)], "k int, mass double")
    x, y = metrics.jsd(a, b, ["k"]).first().value, metrics.jsd(b, a, ["k"]).first().value
    assert x == pytest.approx(y) and 0 < x < 1


def test_distance_edges_and_sanity_bound(spark):
    d = spark.createDataFrame([(1, 10.0), (2, 0.0), (3, 12.0)], "trace_id bigint, d double")
    assert {r.bucket: r.n for r in metrics.distance_histogram(d, 10.0).collect()} == {19: 1, 0: 1}
    assert {r.bucket: r.n for r in metrics.distance_histogram(d, 10.0, overflow="extra").collect()} == {19: 1, 0: 1, 20: 1}
    real = spark.createDataFrame([(0, 0)], "qid int, n bigint").limit(0)
    other = spark.createDataFrame([(0, 3)], "qid int, n bigint")
    assert metrics.relative_gap(real, other, other.select("qid"), ["qid"], 0.01 * 100).first().value == 3.0


def test_reading_and_segment_modes(spark):
    rows = [(1, 1, 0.0, 0.5), (1, 2, 1.0, 0.5), (2, 1, 0.1, 0.1)]
    traces = views.nest(spark.createDataFrame(rows, "trace_id bigint, seq int, x double, y double"))
    q = spark.createDataFrame([(0, 0.4, 0.6, 0.4, 0.6), (1, 0.0, 0.2, 0.0, 0.2)], "qid int, x0 double, x1 double, y0 double, y1 double")
    assert {r.qid: r.n for r in metrics.query_counts(traces, q).collect()} == {1: 1}
    assert {r.qid: r.n for r in metrics.query_counts(traces, q, "segment").collect()} == {0: 1, 1: 1}


def test_gapped_patterns(spark):
    paths = spark.createDataFrame([(1, 3, [1, 2, 3]), (2, 2, [1, 3]), (3, 2, [3, 1])], "trace_id bigint, n int, cells array<int>")
    got = metrics.gapped_supports(paths, spark.createDataFrame([("1>3",)], "pattern string")).first()
    assert got.support == 2
    assert {r.pattern: r.support for r in metrics.pattern_supports(paths).collect()} == {"1>2": 1, "2>3": 1, "1>2>3": 1, "1>3": 1, "3>1": 1}


def test_surrogate_finds_a_known_minimum():
    goal = np.array([0.1, 0.2, 0.6, 0.1])
    w, history = tuning.minimise(lambda w, s: float(((w - goal) ** 2).sum()), 30, 30, seed=1)
    assert ((w - goal) ** 2).sum() < 0.01 and len(history) == 60
    first = min(h[7] for h in history[:30])
    assert min(h[7] for h in history) <= first
    _, random_only = tuning.minimise(lambda w, s: float(((w - goal) ** 2).sum()), 5, 5, seed=1, random_only=True)
    assert {h[1] for h in random_only} == {"explore", "random"}
    for kind in ("ei", "lcb", "pi"):
        tuning.minimise(lambda w, s: float(w[0]), 6, 2, seed=2, kind=kind, batch=2, space="box_then_normalise")


def test_tuned_is_no_worse_than_the_fixed_splits_where_it_looked(spark, drift):
    real = metrics.RealSide(drift, UNIT)
    stats = statistics.leaf_statistics(drift, UNIT, 6, 32).persist()
    run = tuning.objective_of(real, stats, UNIT, CFG.but(top_n=6), "trip_error", 300)
    w, history = tuning.minimise(run, 3, 1, seed=42, select="observed")
    assert min(h[7] for h in history) <= history[0][7] and abs(w.sum() - 1) < 1e-9
    frame = tuning.TuningResult(SplitWeights.of(w), history).frame(spark)
    assert tuning.progress(frame, 4).first().fraction == 1.0
    assert tuning.spent(CFG, 200, "paper") == 1.0 and tuning.spent(CFG, 200, "charged") == 3.0


def test_less_noise_helps_trips(spark, sf):
    d = views.drift_trips(spark, "/root/testdata/sf0.01")
    real = metrics.RealSide(d, UNIT)
    stats = statistics.leaf_statistics(d, UNIT, 6, 32).persist()
    value = lambda e: np.mean([v for _, _, v in experiments.runs(real, stats, UNIT, CFG.but(epsilon=e), equal_split(), [1, 2], ("trip_error",), 5000)])
    assert value(0.5) > value(2.0)


def test_history_can_be_followed_as_a_stream(spark, tmp_path):
    sink = tuning.history_sink(spark, str(tmp_path / "h"))
    for i in range(3):
        sink((i, "explore", 0.25, 0.25, 0.25, 0.25, 1, 0.1 * i, 0.0, 0.1))
    q = tuning.history_stream(spark, str(tmp_path / "h")).writeStream.format("memory").queryName("hist").trigger(availableNow=True).start()
    q.awaitTermination(60)
    assert spark.table("hist").count() == 3


def test_streamed_sessions_match_batch(spark, sf, tmp_path):
    ev = views.table(spark, sf, "events")
    ev.repartitionByRange(2, "event_id").sortWithinPartitions("event_id").write.parquet(str(tmp_path / "e"))
    q = sessions.stream_sessions(sessions.read_events(spark, str(tmp_path / "e"))).writeStream.format("memory").queryName("sess").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    batch = {(r.user_id, r.first_ts): r.n for r in sessions.batch_sessions(ev).collect()}
    stream = {(r.user_id, r.first_ts): r.n for r in spark.table("sess").collect()}
    assert stream and all(batch[k] == n for k, n in stream.items()) and len(stream) >= len(batch) - ev.select("user_id").distinct().count()
    assert sessions.late_rows(ev).count() == 0 and sessions.density_windows(ev).count() > 0


def test_reports_and_relational_helpers(spark, drift, tmp_path):
    half = drift.where("trace_id % 2 = 0")
    assert report.heatmap(drift, half, UNIT).agg(F.sum("n_real")).first()[0] == drift.agg(F.sum("n")).first()[0]
    assert report.inputs(spark, CFG).count() == len(CFG.__dataclass_fields__)
    relational.export(half, str(tmp_path / "csv"), "csv")
    good, bad = relational.read_upload(spark, str(tmp_path / "csv"))
    assert good.count() == half.agg(F.sum("n")).first()[0] and bad.count() == 0
    relational.write_paths(half, str(tmp_path / "p"), 4)
    assert spark.read.parquet(str(tmp_path / "p")).count() == half.count()
    assert 0 < relational.sample_traces(drift, 0.5).count() < drift.count()
    a = spark.createDataFrame([(1, 5), (1, 9), (2, 1)], "k int, t int")
    b = spark.createDataFrame([(1, 4, "x"), (1, 8, "y")], "k int, u int, v string")
    assert {(r.k, r.t): r.asof_v for r in relational.as_of(a, b, "k", "t", "u", ["v"]).collect()} == {(1, 5): "x", (1, 9): "y", (2, 1): None}


def test_bad_readings_are_dropped(spark):
    rows = [(1, 1, 0.5, 0.5), (1, 2, None, 0.5), (None, 1, 0.1, 0.1), (1, 3, float("nan"), 0.1), (2, 1, 7.0, -3.0)]
    t = views.nest(spark.createDataFrame(rows, "trace_id bigint, seq int, x double, y double"))
    assert {r.trace_id: r.n for r in t.collect()} == {1: 1, 2: 1}
    cells = statistics.grid6_paths(t, UNIT).where("trace_id = 2").first().cells
    assert cells == [30]


def test_scan_reads_only_what_it_needs(spark, sf):
    plan = views.order_trips(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "l_comment" not in plan and "l_extendedprice" in plan


def test_data_source_samples_a_released_synopsis(spark, syn, tmp_path):
    from private_traces.sources import synthetic

    syn.trips.write.parquet(str(tmp_path / "trips"))
    synthetic.register(spark)
    got = spark.read.format("synthetic_trips").option("synopsis", str(tmp_path / "trips")).option("n", 300).load()
    assert got.count() == 300 and got.join(syn.trips, ["start_cell", "end_cell"], "left_anti").count() == 0


def test_tuned_queries_are_whole(spark, sf, drift, monkeypatch):
    """Registered runs search with 100 + 100 evaluations of up to 100,000 traces; the evaluations themselves are replaced here."""
    from private_traces.operators import lattice_model
    from private_traces.plans import catalog

    guided, evaluated = [], []

    class Told(lattice_model.Bench):
        def run(self, asked, names=lattice_model.FOUR):
            evaluated.extend(asked)
            return [{m: float(w[2]) for m in names} for _, _, w, _, _ in asked]

        def guide(self, asked):
            guided.extend(asked)
            return [(points[0], [(i, "explore", *map(float, w), 1, e, e, 0.0) for i, (w, e) in enumerate(zip(points, known))]) for _, _, points, known, *_ in asked]

    monkeypatch.setattr(lattice_model, "Bench", Told)
    rows = {name: catalog.QUERIES[name](spark, sf).count() for name in ("tuned_history", "convergence_run", "comparison_table", "weight_table")}
    sizes = {"drift_trips": drift.count(), "subset_trips": views.subset_trips(spark, sf).count()}
    assert {(len(points), len(known), steps, n == sizes[v]) for v, _, points, known, steps, _, n in guided} == {(100, 100, 100, True)}
    assert len(guided) == 1 + 1 + 2 * 3 * 4 + 3 * 4 and rows == {"tuned_history": 100, "convergence_run": 100, "comparison_table": 2 * 3 * 4 * (4 * 5 + 1), "weight_table": 12}
    assert len(evaluated) == 100 * (1 + 1 + 6 + 3) + 6 * 200 * 2 + 24 * 4 * 5 and {n for *_, n in evaluated} <= {*sizes.values(), None}
    steps = []
    monkeypatch.setattr(tuning, "minimise", lambda run, explore, guided, seed, known=None, **more: (steps.append((explore, guided, len(known[0]))), (np.full(4, 0.25), [(0, "explore", 0.25, 0.25, 0.25, 0.25, 1, 0.1, 0.1, 0.0)]))[1])
    made = catalog.QUERIES["tuned_release"](spark, sf).select("trace_id").distinct().count()
    cells = 110  # the final release draws noise of its own: the noisy total is a sum over pairs of cells with scale 4
    assert abs(made - drift.count()) < 6 * 4 * 2**0.5 * cells and steps == [(100, 100, 100)]


def test_generation_queries_make_a_full_size_table(spark, sf, drift):
    from private_traces.plans import catalog

    want = {view: catalog._synopsis(spark, sf, view, cfg=c).noisy_total for view, c in (("drift_trips", CFG), ("user_long", CFG.but(trips_per_trace=3, top_n=3, max_len=128)))}
    assert abs(want["drift_trips"] - drift.count()) < 0.2 * drift.count() and want["drift_trips"] != 2000
    for name in ("draw_trips_quota", "draw_trips_release", "draw_lengths", "walk_bridge", "walk_forced_end", "walk_reject", "synth_points", "synthetic_release", "synth_multi_trip"):
        made = catalog.QUERIES[name](spark, sf).select("trace_id").distinct().count()
        assert made == want["user_long" if name == "synth_multi_trip" else "drift_trips"], name
