"""What a results page shows, as tables: inputs, weights and errors, and real beside synthetic views."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from private_traces.config import Bounds, SplitWeights, SynthesisConfig
from private_traces.functions.lattice import axis

from . import metrics, statistics


def _beside(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    met = a.withColumnRenamed("n", "n_real").join(b.withColumnRenamed("n", "n_syn"), keys, "full")
    return met.select(*keys, F.coalesce("n_real", F.lit(0)).alias("n_real"), F.coalesce("n_syn", F.lit(0)).alias("n_syn"))


def heatmap(real: DataFrame, synth: DataFrame, b: Bounds, bins: int = 10) -> DataFrame:
    """``bx, by, n_real, n_syn``: readings per bin."""
    count = lambda d: d.select(F.inline("path")).groupBy(axis(F.col("x"), b.x0, b.x1, bins).alias("bx"), axis(F.col("y"), b.y0, b.y1, bins).alias("by")).agg(F.count("*").alias("n"))
    return _beside(count(real), count(synth), ["bx", "by"])


def trip_table(real_cells: DataFrame, synth_cells: DataFrame) -> DataFrame:
    return _beside(statistics.trip_counts(real_cells), statistics.trip_counts(synth_cells), ["start_cell", "end_cell"])


def distance_histograms(real: DataFrame, synth: DataFrame, buckets: int = 20) -> DataFrame:
    a = metrics.distances(real)
    longest = a.agg(F.coalesce(F.max("d"), F.lit(0.0)).alias("m")).first().m
    return _beside(metrics.distance_histogram(a, longest, buckets), metrics.distance_histogram(metrics.distances(synth), longest, buckets), ["bucket"])


def inputs(spark: SparkSession, cfg: SynthesisConfig) -> DataFrame:
    """``name, value`` of every setting; the seed of the noise is named but withheld."""
    import json

    shown = json.loads(cfg.to_json()) | {"seed": "withheld"}
    return spark.createDataFrame([(k, str(v)) for k, v in sorted(shown.items())], "name string, value string")


def results(real: metrics.RealSide, synth: DataFrame, weights: SplitWeights, accounting: str = "paper") -> DataFrame:
    """``metric, value, weights, accounting``: every built-in error of one release, and how its tuning was accounted."""
    return metrics.error_report(real, synth).withColumns({"weights": F.lit(str(weights.as_tuple())), "accounting": F.lit(accounting)})


VIEWS: dict[str, Callable] = {"patterns": lambda real_cells, synth_cells: metrics.top_patterns(real_cells).join(metrics.pattern_supports(synth_cells).withColumnRenamed("support", "synthetic"), "pattern", "left").na.fill(0)}


def register_view(name: str, fn: Callable) -> None:
    VIEWS[name] = fn
