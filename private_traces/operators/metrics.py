"""Error metrics between a real and a synthetic trace set, each a one-row frame ``metric, value``.

The real side of every metric is a small table that does not change while weights are tuned; ``RealSide`` makes each
once. Traces come in nested form, so no metric needs a shuffle of readings.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from private_traces.config import Bounds
from private_traces.functions.noise import keyed_uniform

from . import statistics


def one(spark: SparkSession, name: str, value: float | None) -> DataFrame:
    return spark.createDataFrame([(name, value)], "metric string, value double")


def named(df: DataFrame, name: str) -> DataFrame:
    """A one-row frame (metric, value) from a frame with the single column ``value``."""
    return df.select(F.lit(name).alias("metric"), F.col("value").cast("double").alias("value"))


def jsd(p: DataFrame, q: DataFrame, keys: list[str], base: float = 2.0) -> DataFrame:
    """Jensen-Shannon divergence of two tables (keys, mass), each normalised; a side without mass gives 1."""
    total = lambda d, c: F.coalesce(F.sum(c).over(Window.partitionBy(F.lit(0))), F.lit(0.0))
    a = p.select(*keys, F.col("mass").cast("double").alias("p"))
    b = q.select(*keys, F.col("mass").cast("double").alias("q"))
    both = a.join(b, keys, "full").select(F.coalesce("p", F.lit(0.0)).alias("p"), F.coalesce("q", F.lit(0.0)).alias("q"))
    sums = both.agg(F.coalesce(F.sum("p"), F.lit(0.0)).alias("sp"), F.coalesce(F.sum("q"), F.lit(0.0)).alias("sq"))
    term = lambda x, y: F.when(x > 0, 0.5 * x * F.log(2 * x / (x + y)) / F.lit(math.log(base))).otherwise(0.0)
    x, y = F.try_divide(F.col("p"), F.col("sp")), F.try_divide(F.col("q"), F.col("sq"))
    each = both.crossJoin(F.broadcast(sums)).agg(F.sum(term(x, y) + term(y, x)).alias("value"), F.max("sp").alias("sp"), F.max("sq").alias("sq"))
    return each.select(F.when((F.coalesce("sp", F.lit(0.0)) <= 0) | (F.coalesce("sq", F.lit(0.0)) <= 0), 1.0).otherwise(F.greatest(F.lit(0.0), F.col("value"))).alias("value"))


# ---- regions ----


def _regions(spark: SparkSession, x: tuple[Column, Column], y: tuple[Column, Column], n: int, seed: int, least: float, extent: DataFrame | None = None) -> DataFrame:
    u = lambda i: F.round(keyed_uniform(seed, "region", F.concat_ws("-", F.col("id").cast("string"), F.lit(str(i)))), 9)

    def side(i: int, low: Column, high: Column) -> tuple[Column, Column]:
        a, c = F.least(u(i), u(i + 1)), F.greatest(u(i), u(i + 1))
        start = F.least(a, F.lit(1 - least))
        return low + start * (high - low), low + F.greatest(c, start + least) * (high - low)

    (x0, x1), (y0, y1) = side(1, *x), side(3, *y)
    ids = spark.range(n) if extent is None else spark.range(n).crossJoin(F.broadcast(extent))
    return ids.select(F.col("id").cast("int").alias("qid"), x0.alias("x0"), x1.alias("x1"), y0.alias("y0"), y1.alias("y1"))


def random_regions(spark: SparkSession, b: Bounds, n: int = 200, seed: int = 42, least: float = 0.05) -> DataFrame:
    """``qid, x0, x1, y0, y1``: two uniform corners, sorted; a side shorter than ``least`` of the range grows to it."""
    return _regions(spark, (F.lit(b.x0), F.lit(b.x1)), (F.lit(b.y0), F.lit(b.y1)), n, seed, least)


def regions_over(rows: DataFrame, x: str, y: str, n: int = 200, seed: int = 42, least: float = 0.05) -> DataFrame:
    """The same over the extent of the columns ``x`` and ``y``, which is not private; without rows the sides are null."""
    extent = rows.agg(F.min(x).alias("lx"), F.max(x).alias("hx"), F.min(y).alias("ly"), F.max(y).alias("hy"))
    return _regions(rows.sparkSession, (F.col("lx"), F.col("hx")), (F.col("ly"), F.col("hy")), n, seed, least, extent)


def query_counts(traces: DataFrame, queries: DataFrame, mode: str = "reading") -> DataFrame:
    """``qid, n``: traces that pass through each rectangle. The workload (a few hundred rows) is broadcast as one array; each
    trace is tested against it in place, so only one row per (trace, hit) reaches the count, which combines before the shuffle."""
    held = queries.agg(F.collect_list(F.struct("qid", "x0", "x1", "y0", "y1")).alias("qs"))
    inside = lambda p, q: (p["x"] >= q["x0"]) & (p["x"] < q["x1"]) & (p["y"] >= q["y0"]) & (p["y"] < q["y1"])
    if mode == "reading":
        hit = lambda q: F.exists("path", lambda p: inside(p, q))
    elif mode == "segment":
        hit = lambda q: F.exists("path", lambda p: inside(p, q)) | F.exists(_segments(), lambda s: _crosses(s, q))
    else:
        raise ValueError(f"unknown mode: {mode}")
    met = traces.crossJoin(F.broadcast(held)).select(F.explode(F.filter("qs", hit)["qid"]).alias("qid"))
    return met.groupBy("qid").agg(F.count("*").alias("n"))


def _segments() -> Column:
    return F.transform(F.slice("path", F.lit(1), F.greatest(F.size("path") - 1, F.lit(0))), lambda p, i: F.struct(p["x"].alias("ax"), p["y"].alias("ay"), F.get(F.col("path"), i + 1)["x"].alias("bx"), F.get(F.col("path"), i + 1)["y"].alias("by")))


def _crosses(s: Column, q: Column) -> Column:
    """Whether a segment meets a rectangle: its parameter interval inside both slabs is not empty."""

    def slab(a: Column, b: Column, low: Column, high: Column) -> tuple[Column, Column]:
        d = b - a
        t0, t1 = F.try_divide(low - a, d), F.try_divide(high - a, d)
        still = F.when((a >= low) & (a < high), 0.0).otherwise(2.0)
        return F.coalesce(F.least(t0, t1), still), F.when(d == 0, F.when((a >= low) & (a < high), 1.0).otherwise(-1.0)).otherwise(F.greatest(t0, t1))

    (x0, x1), (y0, y1) = slab(s["ax"], s["bx"], q["x0"], q["x1"]), slab(s["ay"], s["by"], q["y0"], q["y1"])
    return F.greatest(x0, y0, F.lit(0.0)) <= F.least(x1, y1, F.lit(1.0))


def query_counts_long(traces: DataFrame, queries: DataFrame, b: Bounds, bins: int = 16) -> DataFrame:
    """The same counts as a range join: readings and rectangles meet by bin of x, then the rectangle is checked."""
    from private_traces.functions.lattice import axis

    spread = queries.withColumn("bin", F.explode(F.sequence(axis(F.col("x0"), b.x0, b.x1, bins), axis(F.col("x1"), b.x0, b.x1, bins))))
    long = traces.select("trace_id", F.inline("path")).select("trace_id", "x", "y", axis(F.col("x"), b.x0, b.x1, bins).alias("bin"))
    met = long.join(F.broadcast(spread), "bin").where("x >= x0 and x < x1 and y >= y0 and y < y1")
    return met.select("qid", "trace_id").distinct().groupBy("qid").agg(F.count("*").alias("n"))


def relative_gap(real: DataFrame, other: DataFrame, domain: DataFrame, keys: list[str], floor: Column | float, scale: float = 1.0) -> DataFrame:
    """Mean over ``domain`` of |real - other| / max(real, floor); absent counts are 0; ``scale`` multiplies the other side."""
    met = domain.join(real.select(*keys, F.col("n").alias("a")), keys, "left").join(other.select(*keys, F.col("n").alias("b")), keys, "left")
    a, b = F.coalesce("a", F.lit(0)).cast("double"), F.coalesce("b", F.lit(0)).cast("double") * scale
    least = F.lit(float(floor)) if isinstance(floor, (int, float)) else floor
    return met.agg(F.avg(F.coalesce(F.try_divide(F.abs(a - b), F.greatest(a, least)), F.lit(0.0))).alias("value"))


def query_error(real: DataFrame, synth: DataFrame, queries: DataFrame, bound: float = 0.01, mode: str = "reading", scale: float = 1.0) -> DataFrame:
    total = real.count()
    return named(relative_gap(query_counts(real, queries, mode), query_counts(synth, queries, mode), queries.select("qid"), ["qid"], bound * total, scale), "query_error")


# ---- patterns ----


def _runs_of(k: int) -> Column:
    """Every run of k of the ``cells``, as text."""
    starts = F.sequence(F.lit(1), F.greatest(F.size("cells") - (k - 1), F.lit(1)))
    texts = F.transform(starts, lambda i: F.array_join(F.slice("cells", i, F.lit(k)).cast("array<string>"), ">"))
    return F.when(F.size("cells") >= k, texts).otherwise(F.array().cast("array<string>"))


def ngrams(paths: DataFrame, low: int = 2, high: int = 8) -> DataFrame:
    """``pattern``: every run of ``low`` to ``high`` cells of every trace, as text; one row per occurrence."""
    return paths.select("trace_id", F.concat(*[_runs_of(k) for k in range(low, high + 1)]).alias("g"))


def pattern_supports(paths: DataFrame, low: int = 2, high: int = 8, count: str = "occurrences", only: DataFrame | None = None) -> DataFrame:
    """``pattern, support``: occurrences, or traces that have the pattern. ``only``: restrict to these before the shuffle."""
    grams = ngrams(paths, low, high)
    each = grams.select(F.explode("g" if count == "occurrences" else F.array_distinct("g")).alias("pattern"))
    if only is not None:
        each = each.join(F.broadcast(only.select("pattern")), "pattern", "left_semi")
    return each.groupBy("pattern").agg(F.count("*").alias("support"))


def gapped_supports(paths: DataFrame, patterns: DataFrame) -> DataFrame:
    """Traces that hold a pattern's cells in order with others between; patterns (k rows) are broadcast as one array."""
    held = patterns.agg(F.collect_list(F.struct("pattern", F.split("pattern", ">").cast("array<int>").alias("want"))).alias("ps"))
    reach = lambda want: F.aggregate("cells", F.lit(0), lambda k, c: F.when(F.get(want, k) == c, k + 1).otherwise(k))
    met = paths.crossJoin(F.broadcast(held)).select(F.explode(F.filter("ps", lambda p: reach(p["want"]) == F.size(p["want"]))["pattern"]).alias("pattern"))
    return met.groupBy("pattern").agg(F.count("*").alias("support"))


def top_patterns(paths: DataFrame, k: int = 100, low: int = 2, high: int = 8, count: str = "occurrences") -> DataFrame:
    """The k patterns of largest support, ties by text."""
    return pattern_supports(paths, low, high, count).orderBy(F.desc("support"), "pattern").limit(k)


def top_patterns_by_prefix(paths: DataFrame, k: int = 100, low: int = 2, high: int = 8) -> DataFrame:
    """The same, grown level by level. A pattern occurs no more often than its prefix and its text sorts after it, so a prefix that is
    not among the k best so far starts none of the k best: each level counts the runs of at most k prefixes. The paths are read once,
    equal ones as one row with their number."""
    weighed = paths.where(F.size("cells") >= low).groupBy("cells").agg(F.count("*").alias("w")).persist()
    best: list[tuple[str, int]] = []
    for size in range(low, high + 1):
        grams = weighed.where(F.size("cells") >= size).select("w", F.explode(_runs_of(size)).alias("pattern"))
        if size > low:
            alive = [p for p, _ in best if p.count(">") == size - 2]
            if not alive:
                break
            grams = grams.where(F.substring_index("pattern", ">", size - 1).isin(alive))
        found = grams.groupBy("pattern").agg(F.sum("w").alias("support")).orderBy(F.desc("support"), "pattern").limit(k).collect()  # k rows
        best = sorted([*best, *((r.pattern, r.support) for r in found)], key=lambda r: (-r[1], r[0]))[:k]
    weighed.unpersist()
    return paths.sparkSession.createDataFrame(best, "pattern string, support long").orderBy(F.desc("support"), "pattern")


def pattern_support_error(real: DataFrame, synth: DataFrame, k: int = 100, low: int = 2, high: int = 8, count: str = "occurrences", scale: float = 1.0, mined: DataFrame | None = None) -> DataFrame:
    """Mean relative gap in support of the real side's top k (divided by the number mined)."""
    mined = top_patterns(real, k, low, high, count) if mined is None else mined
    other = pattern_supports(synth, low, high, count, mined)
    met = mined.join(other.withColumnRenamed("support", "s"), "pattern", "left")
    gap = F.abs(F.col("support") - F.coalesce("s", F.lit(0)) * scale) / F.col("support")
    return named(met.agg(F.coalesce(F.avg(gap), F.lit(0.0)).alias("value")), "pattern_support_error")


def pattern_set_similarity(real: DataFrame, synth: DataFrame, k: int = 100) -> DataFrame:
    """Jaccard and F1 of the two top-k sets, two rows."""
    a, b = top_patterns(real, k).select("pattern"), top_patterns(synth, k).select("pattern")
    n = a.join(b, "pattern", "full").agg(F.count("*").alias("u")).crossJoin(a.join(b, "pattern", "left_semi").agg(F.count("*").alias("i"))).crossJoin(a.agg(F.count("*").alias("na"))).crossJoin(b.agg(F.count("*").alias("nb")))
    ratio = lambda x, y: F.coalesce(F.try_divide(x, y), F.lit(1.0))
    return n.select(F.inline(F.array(F.struct(F.lit("pattern_jaccard").alias("metric"), ratio(F.col("i"), F.col("u")).alias("value")), F.struct(F.lit("pattern_f1").alias("metric"), ratio(2 * F.col("i"), F.col("na") + F.col("nb")).alias("value")))))


def pattern_frequency_error(real: DataFrame, synth: DataFrame, k: int = 100) -> DataFrame:
    """Mean gap in relative frequency over the patterns of either top-k set."""
    a, b = pattern_supports(real), pattern_supports(synth)
    share = lambda d, c: d.crossJoin(F.broadcast(d.agg(F.sum("support").alias("all")))).select("pattern", (F.col("support") / F.col("all")).alias(c))
    chosen = top_patterns(real, k).select("pattern").union(top_patterns(synth, k).select("pattern")).distinct()
    met = chosen.join(share(a, "a"), "pattern", "left").join(share(b, "b"), "pattern", "left")
    return named(met.agg(F.coalesce(F.avg(F.abs(F.coalesce("a", F.lit(0.0)) - F.coalesce("b", F.lit(0.0)))), F.lit(0.0)).alias("value")), "pattern_frequency_error")


# ---- trips and distances ----


def trip_error(real: DataFrame, synth: DataFrame, base: float = 2.0) -> DataFrame:
    """Divergence of the start-to-end distributions. Both sides as cell paths on the evaluation grid."""
    mass = lambda p: statistics.trip_counts(p).withColumnRenamed("n", "mass")
    return named(jsd(mass(real), mass(synth), ["start_cell", "end_cell"], base), "trip_error")


def distances(traces: DataFrame) -> DataFrame:
    """``trace_id, d``: the sum of straight steps, rounded to nine decimals."""
    step = F.transform(_segments(), lambda s: F.sqrt(F.pow(s["bx"] - s["ax"], 2) + F.pow(s["by"] - s["ay"], 2)))
    return traces.select("trace_id", F.round(F.aggregate(step, F.lit(0.0), lambda a, x: a + x), 9).alias("d"))


def distance_histogram(d: DataFrame, longest: float, buckets: int = 20, overflow: str = "drop") -> DataFrame:
    """``bucket, n``: equal buckets up to ``longest``, which falls in the last; beyond it: dropped, clamped, or an extra bucket."""
    width = longest / buckets
    b = F.least(F.floor(F.col("d") / width), F.lit(buckets - 1)) if width > 0 else F.lit(0)
    if overflow == "drop":
        d = d.where(F.col("d") <= longest)
    elif overflow == "extra":
        b = F.when(F.col("d") > longest, buckets).otherwise(b)
    return d.groupBy(b.cast("int").alias("bucket")).agg(F.count("*").alias("n"))


def distance_quantiles(traces: DataFrame, shares=(0.25, 0.5, 0.75, 0.95), accuracy: int = 10_000) -> DataFrame:
    """``share, d``: approximate quantiles of the travel distance, by a mergeable sketch."""
    held = distances(traces).agg(F.percentile_approx("d", list(shares), accuracy).alias("q"))
    return held.select(F.inline(F.arrays_zip(F.array(*[F.lit(float(s)) for s in shares]).alias("share"), F.col("q").alias("d"))))


def distinct_patterns(paths: DataFrame, low: int = 2, high: int = 8, rsd: float = 0.02) -> DataFrame:
    """``n``: about how many patterns occur, by a sketch of fixed size."""
    return ngrams(paths, low, high).select(F.explode("g").alias("pattern")).agg(F.approx_count_distinct("pattern", rsd).alias("n"))


def travel_distance_error(real: DataFrame, synth: DataFrame, buckets: int = 20, base: float = 2.0, overflow: str = "drop") -> DataFrame:
    a = distances(real)
    longest = a.agg(F.coalesce(F.max("d"), F.lit(0.0)).alias("m")).first().m
    mass = lambda d: distance_histogram(d, longest, buckets, overflow).withColumnRenamed("n", "mass")
    return named(jsd(mass(a), mass(distances(synth)), ["bucket"], base), "travel_distance_error")


# ---- places and travel between areas ----


def visits(paths: DataFrame) -> DataFrame:
    """``place, n``: readings per place, places being cells."""
    return paths.select(F.explode("cells").alias("place")).groupBy("place").agg(F.count("*").alias("n"))


def visit_count_error(real: DataFrame, synth: DataFrame, bound: float = 0.01, scale: float = 1.0) -> DataFrame:
    """Mean relative gap of visits over the places either side visits, floored at ``bound`` of the real traces."""
    a, b = visits(real), visits(synth)
    domain = a.select("place").union(b.select("place")).distinct()
    return named(relative_gap(a, b, domain, ["place"], bound * real.count(), scale), "visit_count_error")


def popularity(paths: DataFrame) -> DataFrame:
    """``place, n, rank``: places by visits, ties by place."""
    return visits(paths).withColumn("rank", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.desc("n"), "place")))


def popularity_ranking_error(real: DataFrame, synth: DataFrame, k: int = 10) -> DataFrame:
    """Kendall distance, 1 - Spearman, and 1 - overlap of the top k, over the places both sides rank. Places are a bounded set
    of areas, so ranking them in one partition and pairing them is small."""
    a, b = popularity(real), popularity(synth)
    both = a.select("place", F.col("rank").alias("ra")).join(b.select("place", F.col("rank").alias("rb")), "place")
    order = lambda c: F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(c))
    both = both.select("place", order("ra").alias("ra"), order("rb").alias("rb"))
    other = both.select(F.col("ra").alias("sa"), F.col("rb").alias("sb"))
    pairs = both.join(other, F.col("ra") < F.col("sa")).agg(F.count("*").alias("all"), F.count_if(F.col("rb") > F.col("sb")).alias("bad"))
    n = both.agg(F.count("*").cast("double").alias("n"), F.coalesce(F.sum(F.pow(F.col("ra") - F.col("rb"), 2)), F.lit(0.0)).alias("d"))
    shared = a.where(F.col("rank") <= k).join(b.where(F.col("rank") <= k), "place", "left_semi").agg(F.count("*").alias("shared"))
    size = a.where(F.col("rank") <= k).agg(F.count("*").alias("size"))
    row = pairs.crossJoin(n).crossJoin(shared).crossJoin(size)
    value = lambda name, x: F.struct(F.lit(name).alias("metric"), F.coalesce(x.cast("double"), F.lit(0.0)).alias("value"))
    spearman = F.try_divide(6 * F.col("d"), F.col("n") * (F.col("n") * F.col("n") - 1))
    return row.select(F.inline(F.array(value("kendall_distance", F.try_divide(F.col("bad"), F.col("all"))), value("spearman_distance", spearman), value("topk_miss", 1 - F.try_divide(F.col("shared"), F.col("size"))))))


def area_trips(traces: DataFrame, area) -> DataFrame:
    """``trace_id, a, b, first_ts, last_ts, day``: end areas and times of each trace; ``area(x, y)`` is a Column."""
    f, t = F.get("path", F.lit(0)), F.get("path", F.size("path") - 1)
    return traces.where(F.size("path") > 0).select("trace_id", area(f["x"], f["y"]).alias("a"), area(t["x"], t["y"]).alias("b"), f["ts"].alias("first_ts"), t["ts"].alias("last_ts"), f["ts"].cast("date").alias("day"))


def _mean_gap(a: DataFrame, b: DataFrame, keys: list[str], name: str) -> DataFrame:
    """Mean over the keys of the real side of |a - b| / a; keys with a = 0 count only where b differs, as 1."""
    met = a.withColumnRenamed("v", "va").join(b.withColumnRenamed("v", "vb"), keys, "left")
    gap = F.abs(F.col("va") - F.coalesce("vb", F.lit(0.0)))
    return named(met.agg(F.coalesce(F.avg(F.coalesce(F.try_divide(gap, F.col("va")), F.when(gap > 0, 1.0).otherwise(0.0))), F.lit(0.0)).alias("value")), name)


def daily_trips(trips: DataFrame) -> DataFrame:
    """``a, b, v``: trips per day between areas, over the days of the set."""
    days = trips.agg(F.count_distinct("day").alias("days"))
    return trips.groupBy("a", "b").agg(F.count("*").alias("k")).crossJoin(F.broadcast(days)).select("a", "b", F.coalesce(F.try_divide(F.col("k"), F.col("days")), F.lit(0.0)).alias("v"))


def daily_trips_error(real: DataFrame, synth: DataFrame, area) -> DataFrame:
    return _mean_gap(daily_trips(area_trips(real, area)), daily_trips(area_trips(synth, area)), ["a", "b"], "daily_trips_error")


def speeds(traces: DataFrame, area) -> DataFrame:
    """``a, v``: mean of distance over seconds of the moves that start in an area and take time."""
    moves = F.transform(F.slice("path", F.lit(1), F.greatest(F.size("path") - 1, F.lit(0))), lambda p, i: F.struct(p["x"].alias("x"), p["y"].alias("y"), p["ts"].alias("s"), F.get(F.col("path"), i + 1).alias("q")))
    each = traces.select(F.inline(moves)).select(area(F.col("x"), F.col("y")).alias("a"), F.sqrt(F.pow(F.col("q.x") - F.col("x"), 2) + F.pow(F.col("q.y") - F.col("y"), 2)).alias("d"), ((F.unix_micros(F.col("q.ts").cast("timestamp")) - F.unix_micros(F.col("s").cast("timestamp"))) / 1e6).alias("t"))
    return each.where("t > 0").groupBy("a").agg(F.avg(F.col("d") / F.col("t")).alias("v"))


def speed_error(real: DataFrame, synth: DataFrame, area) -> DataFrame:
    return _mean_gap(speeds(real, area), speeds(synth, area), ["a"], "speed_error")


def travel_times(traces: DataFrame, area) -> DataFrame:
    """``a, b, v``: mean seconds from first to last reading between areas."""
    seconds = (F.unix_micros(F.col("last_ts").cast("timestamp")) - F.unix_micros(F.col("first_ts").cast("timestamp"))) / 1e6
    return area_trips(traces, area).groupBy("a", "b").agg(F.avg(seconds).alias("v")).where("v is not null")


def travel_time_error(real: DataFrame, synth: DataFrame, area) -> DataFrame:
    return _mean_gap(travel_times(real, area), travel_times(synth, area), ["a", "b"], "travel_time_error")


def visit_change(visits_by_day: DataFrame, reference: str) -> DataFrame:
    """``category, day, v``: visits as percent change against the reference day. Input: category, day, n."""
    base = visits_by_day.where(F.col("day") == F.lit(reference).cast("date")).select("category", F.col("n").alias("ref"))
    return visits_by_day.join(base, "category").select("category", "day", F.try_divide(100.0 * (F.col("n") - F.col("ref")), F.col("ref")).alias("v"))


def visit_change_error(real: DataFrame, synth: DataFrame, reference: str) -> DataFrame:
    """Mean absolute gap of the two percent changes over the categories and days of both."""
    a, b = visit_change(real, reference), visit_change(synth, reference)
    met = a.join(b.withColumnRenamed("v", "w"), ["category", "day"])
    return named(met.agg(F.coalesce(F.avg(F.abs(F.col("v") - F.col("w"))), F.lit(0.0)).alias("value")), "visit_change_error")


def next_cell_accuracy(real: DataFrame, synth: DataFrame) -> DataFrame:
    """Share of real moves whose target is the likeliest next cell under the synthetic moves."""
    guess = statistics.transitions(synth).groupBy("src").agg(F.max(F.struct(F.round("weight", 9).alias("w"), (-F.col("dst")).alias("d"))).alias("g")).select("src", (-F.col("g.d")).alias("guess"))
    moves = F.transform(F.slice("cells", F.lit(1), F.col("n") - 1), lambda c, i: F.struct(c.alias("src"), F.get(F.col("cells"), i + 1).alias("dst")))
    met = real.where("n > 1").select(F.inline(moves)).groupBy("src", "dst").agg(F.count("*").alias("k")).join(guess, "src", "left")
    return named(met.agg(F.coalesce(F.try_divide(F.sum(F.when(F.col("dst") == F.col("guess"), F.col("k")).otherwise(0)), F.sum("k")), F.lit(0.0)).alias("value")), "next_cell_accuracy")


# ---- registry ----


class RealSide:
    """What every metric needs of the real set, made once and kept."""

    def __init__(self, traces: DataFrame, bounds: Bounds, seed: int = 42, queries: int = 200):
        spark = traces.sparkSession
        self.traces, self.bounds = traces.persist(), bounds
        self.cells = statistics.grid6_paths(self.traces, bounds).persist()
        self.total = self.traces.count()
        self.regions = random_regions(spark, bounds, queries, seed).persist()
        self.region_counts = query_counts(self.traces, self.regions).persist()
        self.mined = top_patterns(self.cells).persist()
        self.trips = statistics.trip_counts(self.cells).withColumnRenamed("n", "mass").persist()
        self.distances = d = distances(self.traces).persist()
        self.longest = d.agg(F.coalesce(F.max("d"), F.lit(0.0)).alias("m")).first().m
        self.histogram = distance_histogram(d, self.longest).withColumnRenamed("n", "mass").persist()

    def release(self) -> None:
        """Give the kept tables back."""
        for df in (self.traces, self.cells, self.regions, self.region_counts, self.mined, self.trips, self.distances, self.histogram):
            df.unpersist()

    def area(self, x: Column, y: Column) -> Column:
        from private_traces.functions.lattice import uniform_cell

        return uniform_cell(x, y, self.bounds, 6)


REGISTRY: dict[str, Callable[[RealSide, DataFrame, float], DataFrame]] = {
    "query_error": lambda r, s, k: named(relative_gap(r.region_counts, query_counts(s, r.regions), r.regions.select("qid"), ["qid"], 0.01 * r.total, k), "query_error"),
    "pattern_support_error": lambda r, s, k: pattern_support_error(r.cells, statistics.grid6_paths(s, r.bounds), scale=k, mined=r.mined),
    "trip_error": lambda r, s, k: named(jsd(r.trips, statistics.trip_counts(statistics.grid6_paths(s, r.bounds)).withColumnRenamed("n", "mass"), ["start_cell", "end_cell"]), "trip_error"),
    "travel_distance_error": lambda r, s, k: named(jsd(r.histogram, distance_histogram(distances(s), r.longest).withColumnRenamed("n", "mass"), ["bucket"]), "travel_distance_error"),
    "visit_count_error": lambda r, s, k: visit_count_error(r.cells, statistics.grid6_paths(s, r.bounds), scale=k),
    "pattern_frequency_error": lambda r, s, k: pattern_frequency_error(r.cells, statistics.grid6_paths(s, r.bounds)),
    "next_cell_accuracy": lambda r, s, k: next_cell_accuracy(r.cells, statistics.grid6_paths(s, r.bounds)),
    "pattern_set_similarity": lambda r, s, k: pattern_set_similarity(r.cells, statistics.grid6_paths(s, r.bounds)),
    "popularity_ranking_error": lambda r, s, k: popularity_ranking_error(r.cells, statistics.grid6_paths(s, r.bounds)),
    "daily_trips_error": lambda r, s, k: daily_trips_error(r.traces, s, r.area),
    "speed_error": lambda r, s, k: speed_error(r.traces, s, r.area),
    "travel_time_error": lambda r, s, k: travel_time_error(r.traces, s, r.area),
}


#: How much one trace more or less can move an error that is 0 to 1 by its definition. Others are not bounded.
SENSITIVITY = {"trip_error": 1.0, "travel_distance_error": 1.0}


def register_metric(name: str, fn: Callable[[RealSide, DataFrame, float], DataFrame]) -> None:
    """Add a metric: (real side, synthetic traces, count scale) -> frame (metric, value)."""
    REGISTRY[name] = fn


def combine(weights: dict[str, float]) -> Callable[[RealSide, DataFrame, float], DataFrame]:
    """A weighted sum of registered metrics as a metric."""

    def combined(r: RealSide, s: DataFrame, k: float) -> DataFrame:
        parts = [REGISTRY[m](r, s, k).select((F.col("value") * w).alias("value")) for m, w in weights.items()]
        return named(reduce(DataFrame.unionByName, parts).agg(F.sum("value").alias("value")), "combined")

    return combined


def error_report(real: RealSide, synth: DataFrame, metrics: list[str] | None = None, scale: float = 1.0) -> DataFrame:
    """Every registered metric (or those named) of one synthetic set."""
    return reduce(DataFrame.unionByName, [REGISTRY[m](real, synth, scale) for m in metrics or REGISTRY])
