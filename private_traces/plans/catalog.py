"""Every registered query of the trace engine with its DuckDB oracle.

Noise in the oracles is the same keyed draw (md5), so private tables compare value by value.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from private_traces.config import SynthesisConfig, equal_split, prior_split
from private_traces.functions import lattice, noise
from private_traces.operators import bulk, experiments, generator, grid, lattice_model, ledger, metrics, relational, report, statistics, synopsis, tuning
from private_traces.sources import views
from private_traces.streaming import sessions

from . import oracle_sql as sql

CFG = SynthesisConfig(seed=42)  # fixed for the oracles
DISTANCE = CFG.but(metric="travel_distance_error")
DRIFT = views.BOUNDS["drift_trips"]
QUERIES: dict = {}
ORACLES: dict = {}


def query(oracle: str | None = None):
    """Register a query under its function's name."""

    def add(fn):
        QUERIES[fn.__name__] = fn
        if oracle:
            ORACLES[fn.__name__] = oracle
        return fn

    return add


def r6(*names: str):
    return [F.round(n, 6).alias(n) for n in names]


def _leaves(spark, sf_dir):
    return statistics.leaf_paths(views.drift_trips(spark, sf_dir), DRIFT, CFG.top_n)


def _stats(spark, sf_dir):
    return statistics.leaf_statistics(views.drift_trips(spark, sf_dir), DRIFT, CFG.top_n, CFG.max_len)


def _grid6(spark, sf_dir, view="drift_trips"):
    return statistics.grid6_paths(views.VIEWS[view](spark, sf_dir), views.BOUNDS[view])


def _half(df: DataFrame) -> DataFrame:
    """The deterministic stand-in for a synthetic set: traces of even id."""
    return df.where(F.col("trace_id") % 2 == 0)


def _noisy_grid(spark, sf_dir) -> tuple[statistics.LeafStatistics, grid.Grid]:
    stats = _stats(spark, sf_dir)
    spec = grid.grid_spec(grid.noisy_density(stats.top_density(), CFG.top_n, 0.25, CFG.seed))
    return stats, grid.build_grid(spec, DRIFT, CFG.top_n)


# ---- views ----

for _name, _view in views.VIEWS.items():
    QUERIES[f"trace_{_name}"] = lambda spark, sf_dir, v=_view: views.points(v(spark, sf_dir)).select("trace_id", "seq", *r6("x", "y"), "ts")
    ORACLES[f"trace_{_name}"] = sql.view(_name) + f"SELECT trace_id, seq, round(x, 6) AS x, round(y, 6) AS y, ts FROM {_name}"


@query("SELECT vec_id AS trace_id, round(embedding[1]::DOUBLE, 6) AS x, round(embedding[2]::DOUBLE, 6) AS y FROM embeddings")
def trace_point_cloud(spark, sf_dir):
    return views.point_cloud(spark, sf_dir).select("trace_id", F.inline("path")).select("trace_id", *r6("x", "y"))


@query(sql.SYMBOLS + "SELECT conv_id AS trace_id, turn_no AS seq, cell FROM symbols")
def trace_symbols(spark, sf_dir):
    return views.symbol_paths(spark, sf_dir).select("trace_id", F.posexplode("cells").alias("seq", "cell")).select("trace_id", (F.col("seq") + 1).cast("long").alias("seq"), "cell")


@query(sql.view("drift_trips") + "SELECT n, count(*) AS traces FROM (SELECT trace_id, count(*) AS n FROM drift_trips GROUP BY 1) GROUP BY 1")
def trace_lengths(spark, sf_dir):
    return views.drift_trips(spark, sf_dir).groupBy(F.col("n").cast("long").alias("n")).agg(F.count("*").alias("traces"))


# ---- grids and statistics ----


def _uniform(n: int):
    def run(spark, sf_dir):
        paths = statistics.cell_paths(views.drift_trips(spark, sf_dir), lambda x, y: lattice.uniform_cell(x, y, DRIFT, n))
        return metrics.visits(paths).withColumnRenamed("place", "cell")

    return run


for _n in (3, 6, 50):
    QUERIES[f"cell_uniform{_n}"] = _uniform(_n)
    ORACLES[f"cell_uniform{_n}"] = sql.view("drift_trips") + f"SELECT {sql.cell('x', 'y', _n)} AS cell, count(*) AS n FROM drift_trips GROUP BY 1"


@query(sql.LEAF + "SELECT top, round(sum(1.0 / n), 6) AS density FROM leaf GROUP BY top")
def density_normalised(spark, sf_dir):
    return _stats(spark, sf_dir).top_density().select("top", *r6("density"))


@query(sql.LEAF + "SELECT top, count(*)::DOUBLE AS density FROM leaf WHERE seq <= 4 GROUP BY top")
def density_raw(spark, sf_dir):
    found = statistics.density_raw(_leaves(spark, sf_dir), 4)
    return found.groupBy(lattice.top_of(F.col("cell"), CFG.top_n).alias("top")).agg(F.sum("density").alias("density"))


@query(sql.NOISY_GRID + "SELECT top, round(density, 6) AS density FROM noisy")
def density_noisy(spark, sf_dir):
    return grid.noisy_density(_stats(spark, sf_dir).top_density(), CFG.top_n, 0.25, CFG.seed).select("top", *r6("density"))


@query(sql.NOISY_GRID + "SELECT top, m, first_cell FROM spec")
def grid_split(spark, sf_dir):
    return grid.grid_spec(grid.noisy_density(_stats(spark, sf_dir).top_density(), CFG.top_n, 0.25, CFG.seed)).select("top", "m", "first_cell")


@query(sql.NOISY_GRID + """SELECT top, CASE WHEN density >= 600 THEN 6 WHEN density >= 300 THEN 3 WHEN density >= 100 THEN 2 ELSE 1 END AS m FROM (SELECT top, round(density, 9) AS density FROM noisy)""")
def grid_split_thresholds(spark, sf_dir):
    return grid.grid_spec(grid.noisy_density(_stats(spark, sf_dir).top_density(), CFG.top_n, 0.25, CFG.seed), "thresholds", cuts=[100, 300, 600]).select("top", "m")


@query(sql.NOISY_GRID + f"SELECT top, {sql.allowed('round(sqrt(round(density, 9) * 0.75), 9)')} AS m FROM noisy")
def grid_split_noise_guided(spark, sf_dir):
    return grid.grid_spec(grid.noisy_density(_stats(spark, sf_dir).top_density(), CFG.top_n, 0.25, CFG.seed), "noise_guided", later_epsilon=0.75).select("top", "m")


@query(sql.NOISY_GRID + """SELECT first_cell + s AS cell, top, round((top // 6 + (s // m) / m) / 6.0, 6) AS x0, round((top // 6 + (s // m + 1) / m) / 6.0, 6) AS x1,
  round((top % 6 + (s % m) / m) / 6.0, 6) AS y0, round((top % 6 + (s % m + 1) / m) / 6.0, 6) AS y1 FROM spec, unnest(range(0, m * m)) AS t(s)""")
def grid_cells(spark, sf_dir):
    return _noisy_grid(spark, sf_dir)[1].cells(spark).select("cell", "top", *r6("x0", "x1", "y0", "y1"))


@query(sql.ADAPTIVE + "SELECT cell, count(*) AS n FROM adaptive GROUP BY 1")
def cell_adaptive(spark, sf_dir):
    _, g = _noisy_grid(spark, sf_dir)
    paths = _leaves(spark, sf_dir).withColumn("cells", F.transform("cells", g.cell_of))
    return metrics.visits(paths).withColumnRenamed("place", "cell")


@query(sql.GRID6 + "SELECT src, dst, round(sum(1.0 / (n - 1)), 6) AS weight FROM moves GROUP BY 1, 2")
def transitions_weighted(spark, sf_dir):
    return statistics.transitions(_grid6(spark, sf_dir)).select("src", "dst", *r6("weight"))


@query(sql.GRID6 + """, kept AS (SELECT trace_id, seq, cell FROM (SELECT *, lag(cell) OVER (PARTITION BY trace_id ORDER BY seq) AS was FROM cells6) WHERE was IS NULL OR was <> cell),
sized AS (SELECT *, count(*) OVER (PARTITION BY trace_id) AS n, lead(cell) OVER (PARTITION BY trace_id ORDER BY seq) AS nxt FROM kept)
SELECT cell AS src, nxt AS dst, round(sum(1.0 / (n - 1)), 6) AS weight FROM sized WHERE nxt IS NOT NULL GROUP BY 1, 2""")
def transitions_collapsed(spark, sf_dir):
    return statistics.transitions(statistics.collapsed(_grid6(spark, sf_dir))).select("src", "dst", *r6("weight"))


@query(sql.MOBILITY + "SELECT src, dst, round(prob, 6) AS prob FROM mobility")
def mobility_noisy(spark, sf_dir):
    stats, g = _noisy_grid(spark, sf_dir)
    return synopsis.mobility_model(stats.roll_up(g.cell_of)[0], g, 0.25, CFG.seed, "clip").select("src", "dst", *r6("prob"))


@query(sql.mobility_shifted("weight + draw") + "SELECT src, dst, round(prob, 6) AS prob FROM mobility")
def mobility_shifted(spark, sf_dir):
    """The mobility model with the default clean-up."""
    stats, g = _noisy_grid(spark, sf_dir)
    return synopsis.mobility_model(stats.roll_up(g.cell_of)[0], g, 0.25, CFG.seed).select("src", "dst", *r6("prob"))


@query(sql.mobility_shifted("coalesce((weight + draw) / nullif(sum(weight) OVER (PARTITION BY src), 0), 0)") + "SELECT src, dst, round(prob, 6) AS prob FROM mobility")
def mobility_on_probabilities(spark, sf_dir):
    stats, g = _noisy_grid(spark, sf_dir)
    return synopsis.mobility_model(stats.roll_up(g.cell_of)[0], g, 0.25, CFG.seed, noise_on="probability").select("src", "dst", *r6("prob"))


@query(sql.GRID6 + "SELECT start_cell, end_cell, count(*) AS n FROM trips6 GROUP BY 1, 2")
def trip_counts(spark, sf_dir):
    return statistics.trip_counts(_grid6(spark, sf_dir))


@query(sql.GRID6 + "SELECT start_cell, end_cell, round(count(*) / sum(count(*)) OVER (), 6) AS prob FROM trips6 GROUP BY 1, 2")
def trip_distribution(spark, sf_dir):
    return noise.to_probabilities(statistics.trip_counts(_grid6(spark, sf_dir)).withColumn("mass", F.col("n").cast("double")), "mass", []).select("start_cell", "end_cell", *r6("prob"))


@query(sql.TRIPS + "SELECT start_cell, end_cell, round(mass, 6) AS mass, round(prob, 6) AS prob FROM noisy_trips")
def trip_distribution_noisy(spark, sf_dir):
    stats, g = _noisy_grid(spark, sf_dir)
    return synopsis.trip_distribution(stats.roll_up(g.cell_of)[1], g, 0.25, CFG.seed).select("start_cell", "end_cell", *r6("mass", "prob"))


@query(sql.TRIPS_SEPARATE + "SELECT start_cell, end_cell, round(mass, 6) AS mass, round(prob, 6) AS prob FROM noisy_trips")
def trip_distribution_separate_total(spark, sf_dir):
    stats, g = _noisy_grid(spark, sf_dir)
    return synopsis.trip_distribution(stats.roll_up(g.cell_of)[1], g, 0.25, CFG.seed, total="separate").select("start_cell", "end_cell", *r6("mass", "prob"))


@query(sql.GRID6 + "SELECT start_cell, end_cell, least(n, 32)::INTEGER AS len, count(*) AS n FROM trips6 GROUP BY 1, 2, 3")
def length_histogram(spark, sf_dir):
    return statistics.length_histogram(_grid6(spark, sf_dir), 32)


def _laws(spark, sf_dir):
    hist = statistics.length_histogram(_grid6(spark, sf_dir), 32)
    pairs = hist.select("start_cell", "end_cell").distinct()
    return synopsis.candidates(synopsis.noisy_lengths(hist, pairs, 0.25, 32, CFG.seed), 32)


@query(sql.LAWS + "SELECT start_cell, end_cell, len, round(n, 6) AS n, round(mean, 6) AS mean, round(uniform, 6) AS uniform, round(poisson, 6) AS poisson, round(exponential, 6) AS exponential FROM expected")
def length_candidates(spark, sf_dir):
    return _laws(spark, sf_dir).select("start_cell", "end_cell", "len", *r6("n", "mean", *synopsis.FAMILIES))


@query(sql.LAWS + sql.BEST)
def length_best_fit(spark, sf_dir):
    return synopsis.best_fit(_laws(spark, sf_dir)).select("start_cell", "end_cell", "family", *r6("p1"))


@query(sql.LAWS + sql.BEST_KS)
def length_best_fit_ks(spark, sf_dir):
    return synopsis.best_fit(_laws(spark, sf_dir), "ks").select("start_cell", "end_cell", "family", *r6("p1"))


@query(sql.LAWS + sql.BEST_LOGLIK)
def length_best_fit_loglik(spark, sf_dir):
    return synopsis.best_fit(_laws(spark, sf_dir), "loglik").select("start_cell", "end_cell", "family", *r6("p1"))


@query(sql.MOMENTS)
def length_moments(spark, sf_dir):
    hist = statistics.length_histogram(_grid6(spark, sf_dir), 32)
    return synopsis.moment_parameters(hist, hist.select("start_cell", "end_cell").distinct(), 0.25, 32, CFG.seed).select("start_cell", "end_cell", *r6("mean"))


@query(sql.ADAPTIVE + """, p AS (SELECT *, lead(cell) OVER (PARTITION BY trace_id ORDER BY seq) AS nxt FROM adaptive)
SELECT cell AS src, nxt AS dst, round(sum(1.0 / (n - 1)), 6) AS weight FROM p WHERE nxt IS NOT NULL GROUP BY 1, 2""")
def leaf_rollup(spark, sf_dir):
    """Transitions rolled up from leaves; the oracle counts them directly on the adaptive cells."""
    stats, g = _noisy_grid(spark, sf_dir)
    return stats.roll_up(g.cell_of)[0].select("src", "dst", *r6("weight"))


@query(sql.LEDGER)
def budget_ledger(spark, sf_dir):
    """What a release of the drift view spends, with the sensitivity that its traces reach and how many of them each stage reads."""
    return synopsis.audited_ledger(synopsis.ledger_of(CFG, equal_split()), _leaves(spark, sf_dir)).select("stage", "mechanism", *r6("sensitivity"), "epsilon", "composition", "traces")


@query(f"SELECT o_orderkey AS key, round({sql.laplace(2.0, 'test', 'o_orderkey')}, 6) AS draw FROM orders")
def noise_laplace(spark, sf_dir):
    """A draw for each order."""
    return views.table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("key"), noise.laplace(2.0, CFG.seed, "test", "o_orderkey").alias("draw")).select("key", *r6("draw"))


@query(f"SELECT o_orderkey AS key, (floor(ln({sql.uniform('test+', 'o_orderkey')}) / -0.5) - floor(ln({sql.uniform('test-', 'o_orderkey')}) / -0.5))::BIGINT AS draw FROM orders")
def noise_geometric(spark, sf_dir):
    """A draw for each order."""
    return views.table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("key"), noise.geometric(0.5, CFG.seed, "test", "o_orderkey").alias("draw"))


@query()
def noise_sparse(spark, sf_dir):
    counts = statistics.trip_counts(_leaves(spark, sf_dir)).select((F.col("start_cell").cast("bigint") * 1296 + F.col("end_cell")).alias("pair"), F.col("n").cast("double").alias("mass"))
    return noise.sparse_noise(counts, 1296 * 1296, "pair", "mass", 4.0, 30.0, CFG.seed, "sparse").select("pair", *r6("mass"))


# ---- generation ----


def _synopsis(spark, sf_dir, view="drift_trips", cfg=CFG, weights=None):
    return synopsis.extract_synopsis(views.VIEWS[view](spark, sf_dir), views.BOUNDS[view], weights or equal_split(), cfg)


@query(sql.TRIPS + sql.DRAWN + "SELECT trace_id, start_cell, end_cell FROM drawn")
def draw_trips(spark, sf_dir):
    stats, g = _noisy_grid(spark, sf_dir)
    trips = synopsis.trip_distribution(stats.roll_up(g.cell_of)[1], g, 0.25, CFG.seed)
    return generator.draw_trips(trips, 2000, CFG.seed)


@query(sql.QUOTA)
def draw_trips_quota(spark, sf_dir):
    syn = _synopsis(spark, sf_dir)
    return generator.draw_trips(syn.trips, syn.noisy_total, CFG.seed, "quota")


@query(sql.RELEASE_DRAWS)
def draw_trips_release(spark, sf_dir):
    """As many draws as a release has; ``draw_trips`` makes the 2,000 that its SQL makes."""
    syn = _synopsis(spark, sf_dir)
    return generator.draw_trips(syn.trips, syn.noisy_total, CFG.seed)


def _drawn(spark, sf_dir):
    syn = _synopsis(spark, sf_dir)
    return syn, generator.draw_lengths(generator.draw_trips(syn.trips, syn.noisy_total, CFG.seed), syn.lengths, CFG.max_len, CFG.seed)


@query()
def draw_lengths(spark, sf_dir):
    return _drawn(spark, sf_dir)[1].select("trace_id", "start_cell", "end_cell", "n")


def _walks(mode):
    def run(spark, sf_dir):
        syn, trips = _drawn(spark, sf_dir)
        return generator.walk(trips, syn.mobility, syn.grid.size, CFG.seed, mode).select("trace_id", "n", F.array_join(F.col("cells").cast("array<string>"), ">").alias("cells"))

    return run


for _mode in ("bridge", "forced_end", "reject"):
    QUERIES[f"walk_{_mode}"] = _walks(_mode)


@query()
def walk_jumps(spark, sf_dir):
    """How many traces of a release could not reach their end in time."""
    syn, trips = _drawn(spark, sf_dir)
    return generator.jumps(generator.walk(trips, syn.mobility, syn.grid.size, CFG.seed))


@query()
def synth_points(spark, sf_dir):
    syn, trips = _drawn(spark, sf_dir)
    walks = generator.walk(trips, syn.mobility, syn.grid.size, CFG.seed)
    return generator.place_points(walks, syn.grid.cells(spark), CFG.seed, 15.6).select("trace_id", "seq", *r6("x", "y"), "ts")


@query()
def synth_multi_trip(spark, sf_dir):
    syn = _synopsis(spark, sf_dir, "user_long", CFG.but(trips_per_trace=3, top_n=3, max_len=128))
    return views.points(generator.generate(syn)).select("trace_id", "seq", *r6("x", "y"))


@query()
def synthetic_release(spark, sf_dir):
    """The whole output of the engine: every reading of a full-size synthetic table."""
    return views.points(generator.generate(_synopsis(spark, sf_dir))).select("trace_id", "seq", *r6("x", "y"))


# ---- metrics against the half set ----


@query(sql.TABLE_REGIONS)
def random_regions(spark, sf_dir):
    """A workload over the extent of the readings of the ``order_trips`` view."""
    lines = views.table(spark, sf_dir, "lineitem").where("l_extendedprice is not null and l_quantity is not null")
    return metrics.regions_over(lines, "l_extendedprice", "l_quantity").select("qid", *r6("x0", "x1", "y0", "y1"))


@query(sql.view("drift_trips") + sql.REGIONS.replace("WITH", ",", 1) + "SELECT qid, count(DISTINCT trace_id) AS n FROM drift_trips JOIN regions ON x >= x0 AND x < x1 AND y >= y0 AND y < y1 GROUP BY 1")
def query_counts(spark, sf_dir):
    return metrics.query_counts(views.drift_trips(spark, sf_dir), metrics.random_regions(spark, DRIFT))


@query(ORACLES["query_counts"])
def query_counts_range_join(spark, sf_dir):
    return metrics.query_counts_long(views.drift_trips(spark, sf_dir), metrics.random_regions(spark, DRIFT), DRIFT)


@query(sql.SEGMENTS)
def query_counts_segment(spark, sf_dir):
    return metrics.query_counts(views.drift_trips(spark, sf_dir), metrics.random_regions(spark, DRIFT), "segment")


def _value(df: DataFrame) -> DataFrame:
    return df.select("metric", *r6("value"))


@query(sql.view("drift_trips") + sql.REGIONS.replace("WITH", ",", 1).rstrip() + sql.QUERY_ERROR)
def query_error(spark, sf_dir):
    d = views.drift_trips(spark, sf_dir)
    return _value(metrics.query_error(d, _half(d), metrics.random_regions(spark, DRIFT)))


@query(sql.PATTERNS + "SELECT pattern, support FROM supports ORDER BY support DESC, pattern LIMIT 100")
def pattern_topk(spark, sf_dir):
    return metrics.top_patterns(_grid6(spark, sf_dir))


@query(ORACLES["pattern_topk"])
def pattern_topk_by_prefix(spark, sf_dir):
    return metrics.top_patterns_by_prefix(_grid6(spark, sf_dir))


@query(sql.PATTERNS + "SELECT start_cell, pattern, support FROM (SELECT split_part(pattern, '>', 1)::INTEGER AS start_cell, pattern, support, row_number() OVER (PARTITION BY split_part(pattern, '>', 1) ORDER BY support DESC, pattern) AS k FROM supports) WHERE k <= 3")
def pattern_topk_per_start(spark, sf_dir):
    s = metrics.pattern_supports(_grid6(spark, sf_dir)).withColumn("start_cell", F.split_part("pattern", F.lit(">"), F.lit(1)).cast("int"))
    w = Window.partitionBy("start_cell").orderBy(F.desc("support"), "pattern")
    return s.withColumn("k", F.row_number().over(w)).where("k <= 3").select("start_cell", "pattern", "support")


@query(sql.PATTERNS + "SELECT pattern, count(DISTINCT trace_id) AS support FROM grams GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 100")
def pattern_topk_traces(spark, sf_dir):
    return metrics.top_patterns(_grid6(spark, sf_dir), count="traces")


@query(sql.GAPPED)
def pattern_gapped(spark, sf_dir):
    paths = _grid6(spark, sf_dir)
    return metrics.gapped_supports(paths, metrics.top_patterns(paths))


@query(sql.SYMBOLS + sql.grams("symbols", "conv_id", "turn_no") + "SELECT pattern, count(*) AS support FROM grams GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 100")
def pattern_topk_symbols(spark, sf_dir):
    return metrics.top_patterns(views.symbol_paths(spark, sf_dir))


@query(sql.PATTERNS + """, mined AS (SELECT * FROM supports ORDER BY support DESC, pattern LIMIT 100), other AS (SELECT pattern, count(*) AS s FROM grams WHERE trace_id % 2 = 0 GROUP BY 1)
SELECT 'pattern_support_error' AS metric, round(avg(abs(support - coalesce(s, 0)) / support), 6) AS value FROM mined LEFT JOIN other USING (pattern)""")
def pattern_support_error(spark, sf_dir):
    d = _grid6(spark, sf_dir)
    return _value(metrics.pattern_support_error(d, _half(d)))


@query(sql.PATTERNS + """, a AS (SELECT pattern FROM supports ORDER BY support DESC, pattern LIMIT 100), b AS (SELECT pattern FROM (SELECT pattern, count(*) AS s FROM grams WHERE trace_id % 2 = 0 GROUP BY 1) ORDER BY s DESC, pattern LIMIT 100),
k AS (SELECT count(*) FILTER (WHERE a.pattern IS NOT NULL AND b.pattern IS NOT NULL) AS i, count(*) AS u, count(a.pattern) AS na, count(b.pattern) AS nb FROM a FULL JOIN b ON a.pattern = b.pattern)
SELECT 'pattern_jaccard' AS metric, round(i / u, 6) AS value FROM k UNION ALL SELECT 'pattern_f1', round(2 * i / (na + nb), 6) FROM k""")
def pattern_jaccard_f1(spark, sf_dir):
    d = _grid6(spark, sf_dir)
    return _value(metrics.pattern_set_similarity(d, _half(d)))


@query(sql.PATTERNS + """, half AS (SELECT pattern, count(*) AS support FROM grams WHERE trace_id % 2 = 0 GROUP BY 1), chosen AS ((SELECT pattern FROM supports ORDER BY support DESC, pattern LIMIT 100) UNION (SELECT pattern FROM half ORDER BY support DESC, pattern LIMIT 100))
SELECT 'pattern_frequency_error' AS metric, round(avg(abs(coalesce(a.support, 0) / (SELECT sum(support) FROM supports) - coalesce(b.support, 0) / (SELECT sum(support) FROM half))), 6) AS value FROM chosen LEFT JOIN supports a USING (pattern) LEFT JOIN half b USING (pattern)""")
def pattern_frequency_error(spark, sf_dir):
    d = _grid6(spark, sf_dir)
    return _value(metrics.pattern_frequency_error(d, _half(d)))


@query(sql.GRID6 + ", p AS (SELECT start_cell, end_cell, count(*)::DOUBLE AS m FROM trips6 GROUP BY 1, 2), q AS (SELECT start_cell, end_cell, count(*)::DOUBLE AS m FROM trips6 WHERE trace_id % 2 = 0 GROUP BY 1, 2) " + sql.jsd("trip_error", "p.start_cell = q.start_cell AND p.end_cell = q.end_cell"))
def trip_error(spark, sf_dir):
    d = _grid6(spark, sf_dir)
    return _value(metrics.trip_error(d, _half(d)))


@query(sql.DISTANCES + "SELECT trace_id, d FROM dist")
def travel_distances(spark, sf_dir):
    return metrics.distances(views.drift_trips(spark, sf_dir))


@query(sql.DISTANCES + "SELECT bucket, count(*) AS n FROM hist GROUP BY 1")
def travel_distance_hist(spark, sf_dir):
    d = metrics.distances(views.drift_trips(spark, sf_dir))
    return metrics.distance_histogram(d, d.agg(F.max("d").alias("m")).first().m)


@query(sql.DISTANCES + ", p AS (SELECT bucket, count(*)::DOUBLE AS m FROM hist GROUP BY 1), q AS (SELECT bucket, count(*)::DOUBLE AS m FROM hist WHERE trace_id % 2 = 0 GROUP BY 1) " + sql.jsd("travel_distance_error", "p.bucket = q.bucket"))
def travel_distance_error(spark, sf_dir):
    d = views.drift_trips(spark, sf_dir)
    return _value(metrics.travel_distance_error(d, _half(d)))


@query(sql.GRID6 + """, a AS (SELECT cell, count(*) AS n FROM cells6 GROUP BY 1), b AS (SELECT cell, count(*) AS n FROM cells6 WHERE trace_id % 2 = 0 GROUP BY 1)
SELECT 'visit_count_error' AS metric, round(avg(abs(coalesce(a.n, 0) - coalesce(b.n, 0)) / greatest(coalesce(a.n, 0), 0.01 * (SELECT count(DISTINCT trace_id) FROM cells6))), 6) AS value FROM a FULL JOIN b ON a.cell = b.cell""")
def visit_count_error(spark, sf_dir):
    d = _grid6(spark, sf_dir)
    return _value(metrics.visit_count_error(d, _half(d)))


@query(sql.RANKING)
def popularity_ranking_error(spark, sf_dir):
    d = _grid6(spark, sf_dir)
    return _value(metrics.popularity_ranking_error(d, _half(d)))


def _area(x, y):
    return lattice.uniform_cell(x, y, DRIFT, 6)


@query(sql.TRAVEL + """, p AS (SELECT a, b, count(*) / (SELECT count(DISTINCT day) FROM ab) AS v FROM ab GROUP BY 1, 2), q AS (SELECT a, b, count(*) / (SELECT count(DISTINCT day) FROM ab WHERE trace_id % 2 = 0) AS v FROM ab WHERE trace_id % 2 = 0 GROUP BY 1, 2)
SELECT 'daily_trips_error' AS metric, round(avg(abs(p.v - coalesce(q.v, 0)) / p.v), 6) AS value FROM p LEFT JOIN q USING (a, b)""")
def daily_trips_error(spark, sf_dir):
    d = views.drift_trips(spark, sf_dir)
    return _value(metrics.daily_trips_error(d, _half(d), _area))


@query(sql.TRAVEL + """, p AS (SELECT a, avg(v) AS v FROM steps WHERE v IS NOT NULL GROUP BY 1), q AS (SELECT a, avg(v) AS v FROM steps WHERE v IS NOT NULL AND trace_id % 2 = 0 GROUP BY 1)
SELECT 'speed_error' AS metric, round(avg(CASE WHEN p.v = 0 THEN (CASE WHEN coalesce(q.v, 0) > 0 THEN 1.0 ELSE 0 END) ELSE abs(p.v - coalesce(q.v, 0)) / p.v END), 6) AS value FROM p LEFT JOIN q USING (a)""")
def speed_error(spark, sf_dir):
    d = views.drift_trips(spark, sf_dir)
    return _value(metrics.speed_error(d, _half(d), _area))


@query(sql.TRAVEL + """, p AS (SELECT a, b, avg(secs) AS v FROM ab GROUP BY 1, 2), q AS (SELECT a, b, avg(secs) AS v FROM ab WHERE trace_id % 2 = 0 GROUP BY 1, 2)
SELECT 'travel_time_error' AS metric, round(avg(CASE WHEN p.v = 0 THEN (CASE WHEN coalesce(q.v, 0) > 0 THEN 1.0 ELSE 0 END) ELSE abs(p.v - coalesce(q.v, 0)) / p.v END), 6) AS value FROM p LEFT JOIN q USING (a, b)""")
def travel_time_error(spark, sf_dir):
    d = views.drift_trips(spark, sf_dir)
    return _value(metrics.travel_time_error(d, _half(d), _area))


@query(sql.VISIT_CHANGE)
def visit_change_error(spark, sf_dir):
    ev = views.table(spark, sf_dir, "events").withColumn("day", F.col("ts").cast("date"))
    by = lambda d: d.groupBy(F.col("event_type").alias("category"), "day").agg(F.count("*").alias("n"))
    return _value(metrics.visit_change_error(by(ev), by(ev.where("user_id % 2 = 0")), "2024-01-02"))


@query(sql.GRID6 + """, w AS (SELECT src, dst, round(sum(1.0 / (n - 1)), 9) AS w FROM moves WHERE trace_id % 2 = 0 GROUP BY 1, 2), g AS (SELECT src, arg_max(dst, (w, -dst)) AS guess FROM w GROUP BY 1)
SELECT 'next_cell_accuracy' AS metric, round(count(*) FILTER (WHERE dst = guess) / count(*), 6) AS value FROM moves LEFT JOIN g USING (src)""")
def next_cell_accuracy(spark, sf_dir):
    d = _grid6(spark, sf_dir)
    return _value(metrics.next_cell_accuracy(d, _half(d)))


@query()
def combined_metric(spark, sf_dir):
    d = views.drift_trips(spark, sf_dir)
    return _value(metrics.combine({"trip_error": 0.5, "query_error": 0.5})(metrics.RealSide(d, DRIFT), _half(d), 1.0))


@query()
def error_report(spark, sf_dir):
    d = views.drift_trips(spark, sf_dir)
    return _value(metrics.error_report(metrics.RealSide(d, DRIFT), _half(d)))


# ---- reports ----


@query(sql.HEATMAP)
def heatmap10(spark, sf_dir):
    d = views.drift_trips(spark, sf_dir)
    return report.heatmap(d, _half(d), DRIFT)


@query(sql.GRID6 + "SELECT start_cell, end_cell, count(*) AS n_real, count(*) FILTER (WHERE trace_id % 2 = 0) AS n_syn FROM trips6 GROUP BY 1, 2")
def trip_table(spark, sf_dir):
    d = _grid6(spark, sf_dir)
    return report.trip_table(d, _half(d))


@query(sql.DISTANCES + "SELECT bucket, count(*) AS n_real, count(*) FILTER (WHERE trace_id % 2 = 0) AS n_syn FROM hist GROUP BY 1")
def distance_histograms(spark, sf_dir):
    d = views.drift_trips(spark, sf_dir)
    return report.distance_histograms(d, _half(d))


# ---- relational operators ----


@query(sql.GRID6 + "SELECT coalesce(start_cell, -1) AS start_cell, coalesce(end_cell, -1) AS end_cell, count(*) AS n FROM trips6 GROUP BY ROLLUP (trips6.start_cell, trips6.end_cell)")
def trip_rollup(spark, sf_dir):
    return statistics.ends(_grid6(spark, sf_dir)).rollup("start_cell", "end_cell").agg(F.count("*").alias("n")).na.fill(-1)


@query(sql.GRID6 + "SELECT coalesce(start_cell, -1) AS start_cell, coalesce(end_cell, -1) AS end_cell, count(*) AS n FROM trips6 GROUP BY GROUPING SETS ((trips6.start_cell), (trips6.end_cell), (trips6.start_cell, trips6.end_cell), ())")
def trip_grouping_sets(spark, sf_dir):
    return statistics.ends(_grid6(spark, sf_dir)).groupingSets([["start_cell"], ["end_cell"], ["start_cell", "end_cell"], []], "start_cell", "end_cell").agg(F.count("*").alias("n")).na.fill(-1)


@query(sql.TRAVEL + "SELECT coalesce(day::VARCHAR, 'all') AS day, coalesce(a, -1) AS a, coalesce(b, -1) AS b, count(*) AS n FROM ab GROUP BY CUBE (ab.day, ab.a, ab.b)")
def trip_cube(spark, sf_dir):
    return metrics.area_trips(views.drift_trips(spark, sf_dir), _area).cube("day", "a", "b").agg(F.count("*").alias("n")).select(F.coalesce(F.col("day").cast("string"), F.lit("all")).alias("day"), "a", "b", "n").na.fill(-1)


@query(sql.SESSIONS)
def sessions_batch(spark, sf_dir):
    return sessions.batch_sessions(views.table(spark, sf_dir, "events"))


@query(sql.ASOF)
def asof_resample(spark, sf_dir):
    return relational.resample(views.user_long(spark, sf_dir), 6).select("trace_id", "at", *r6("x", "y"))


@query(sql.GRID6 + "SELECT start_cell, end_cell, count(*) AS n FROM trips6 GROUP BY 1, 2 ORDER BY n DESC, start_cell, end_cell LIMIT 10")
def demand_topk(spark, sf_dir):
    return experiments.demand_topk(_grid6(spark, sf_dir))


@query(sql.GRID6 + "SELECT start_cell, count(*) AS n FROM trips6 GROUP BY 1")
def demand_by_start(spark, sf_dir):
    return experiments.demand_by_start(_grid6(spark, sf_dir))


@query(sql.TRIPS + "SELECT start_cell, arg_max(end_cell, (prob, -end_cell)) AS end_cell, round(max(prob) / sum(prob), 6) AS prob FROM noisy_trips WHERE prob > 0 GROUP BY 1")
def destination_given_start(spark, sf_dir):
    stats, g = _noisy_grid(spark, sf_dir)
    trips = synopsis.trip_distribution(stats.roll_up(g.cell_of)[1], g, 0.25, CFG.seed).where("prob > 0")
    return synopsis.destination_given_start(trips).select("start_cell", "end_cell", *r6("prob"))


@query(sql.view("drift_trips") + "SELECT trace_id, seq FROM drift_trips WHERE x >= 0.2 AND x < 0.4 AND y >= 0.2 AND y < 0.4")
def area_filter(spark, sf_dir):
    return relational.inside(views.points(views.drift_trips(spark, sf_dir)), 0.2, 0.4, 0.2, 0.4).select("trace_id", "seq")


@query("SELECT l_suppkey AS place, count(DISTINCT l_orderkey) AS traces, count(*) AS visits FROM lineitem GROUP BY 1")
def supplier_visits(spark, sf_dir):
    return views.table(spark, sf_dir, "lineitem").groupBy(F.col("l_suppkey").alias("place")).agg(F.count_distinct("l_orderkey").alias("traces"), F.count("*").alias("visits"))


@query("SELECT n_nationkey AS area, event_type AS category, count(*) AS n FROM events e JOIN customer c ON c.c_custkey = e.user_id + 1 JOIN nation n ON n.n_nationkey = c.c_nationkey GROUP BY 1, 2")
def area_category_visits(spark, sf_dir):
    t = lambda n: views.table(spark, sf_dir, n)
    return t("events").join(t("customer"), F.col("c_custkey") == F.col("user_id") + 1).join(t("nation"), F.col("n_nationkey") == F.col("c_nationkey")).groupBy(F.col("n_nationkey").alias("area"), F.col("event_type").alias("category")).agg(F.count("*").alias("n"))


# ---- methods and experiments (statistical: rows only) ----


@query()
def equal_split_run(spark, sf_dir):
    return _value(experiments.method_run(spark, sf_dir, "drift_trips", equal_split(), CFG, "equal split"))


@query()
def prior_split_run(spark, sf_dir):
    return _value(experiments.method_run(spark, sf_dir, "drift_trips", prior_split(), CFG, "fixed 10/40/40/10 split"))


@query()
def no_noise_run(spark, sf_dir):
    return _value(experiments.method_run(spark, sf_dir, "drift_trips", equal_split(), CFG.but(epsilon=None), "no noise"))


@query()
def granularity_study(spark, sf_dir):
    return experiments.granularity_study(spark, sf_dir)


@query()
def tune_small(spark, sf_dir):
    """A reduced run (4 random, 3 guided evaluations) of the tuned method on the small view."""
    return experiments.convergence_study(spark, sf_dir, explore=4, guided=3, n_tune=2000, cfg=DISTANCE).select("eval_id", "phase", *r6("w1", "w2", "w3", "w4", "err", "best_so_far"))


@query()
def tuned_history(spark, sf_dir):
    """The tuned method as proposed: 100 random and 100 guided evaluations on the whole drift view."""
    return experiments.convergence_study(spark, sf_dir, "drift_trips", cfg=DISTANCE).select("eval_id", "phase", *r6("w1", "w2", "w3", "w4", "err", "best_so_far"))


@query()
def convergence_run(spark, sf_dir):
    """The same 100 and 100 evaluations on the small view."""
    return experiments.convergence_study(spark, sf_dir, cfg=DISTANCE).select("eval_id", "phase", *r6("w1", "w2", "w3", "w4", "err", "best_so_far"))


@query()
def tuned_release(spark, sf_dir):
    """What the tuned method is for: the full-size synthetic table made with the winning weights."""
    made, _ = tuning.tune(views.drift_trips(spark, sf_dir), DRIFT, CFG).finalise()  # noise of its own: the rows differ each time
    return views.points(made).select("trace_id", "seq", *r6("x", "y"))


@query()
def comparison_table(spark, sf_dir):
    """Four errors, three epsilons, the whole and the small drift view, five methods; tuned ones with 100 and 100 evaluations."""
    return experiments.comparison_grid(spark, [("drift_trips", sf_dir), ("subset_trips", sf_dir)], base=CFG).select("metric", "epsilon", "dataset", "method", "weights", "trial", *r6("value"))


@query()
def weight_table(spark, sf_dir):
    """Winning weights of four errors where epsilon changes on one view, and where the view changes at one epsilon."""
    combos = [("drift_trips", sf_dir, 0.5), ("drift_trips", sf_dir, 1.0), ("subset_trips", sf_dir, 1.0)]
    return experiments.weight_study(spark, combos, base=CFG).select("dataset", "epsilon", "metric", *r6("w1", "w2", "w3", "w4"))


@query()
def bulk_metrics(spark, sf_dir):
    """A hundred random splits on adaptive grids, each with its own full-size synthetic set and all four errors, in one job."""
    t = lattice_model.real_tables(views.drift_steps(spark, sf_dir), views.drift_positions, DRIFT, CFG.top_n, CFG.max_len)
    found = lattice_model.evaluate_tables(spark, t, CFG, tuning.explored(100, CFG.seed), None, CFG.seed)
    return found.select("eval_id", "metric", *r6("w1", "w2", "w3", "w4", "value"))


@query(sql.BULK)
def bulk_exploration(spark, sf_dir):
    """Forty candidate splits on a uniform 6 x 6 grid, evaluated in one job."""
    g = grid.uniform_grid(DRIFT, 6, 6)
    found = bulk.trip_errors(statistics.trip_counts(_grid6(spark, sf_dir)), g, sql.bulk_weights(), 1.0, CFG.seed)
    return found.select("eval_id", *r6("value"))


__all__ = ["ORACLES", "QUERIES", "ledger", "tuning"]
