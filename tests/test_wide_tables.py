"""Tables of all pairs of a large grid: in arrays, with the results of the small way, and no step that is made again for every mass."""

import time

import pytest
from pyspark.sql import functions as F

from private_traces.config import SynthesisConfig, equal_split
from private_traces.functions import noise
from private_traces.operators import generator, synopsis
from private_traces.sources.views import BOUNDS, VIEWS


def test_draws_in_arrays_are_those_of_columns(spark):
    seed = 2**127 + 5
    df = spark.range(300).select((F.col("id") * 37).alias("a"), F.pmod("id", F.lit(40)).alias("b")).withColumn("u", noise.keyed_uniform(seed, "place-x", "a", "b"))
    rows = df.toPandas()
    assert (noise.keyed_numbers(seed, "place-x", rows.a.to_numpy(), rows.b.to_numpy(), part=64) == rows.u.to_numpy()).all()


def test_clean_up_of_one_large_group_sums_it_once(spark):
    df = spark.range(20_000).select(F.lit(0).alias("g"), (noise.keyed_uniform(1, "m", "id") - 0.4).alias("m"))
    began = time.time()
    whole, kept = df.agg(F.sum("m")).first()[0], noise.clean_up(df, "m", [], "shift").agg(F.sum("m")).first()[0]
    assert kept == pytest.approx(whole) and time.time() - began < 15


def test_a_length_is_drawn_once_a_trace(spark):
    laws = spark.createDataFrame([(0, 0, "poisson", 3.0)], "start_cell int, end_cell int, family string, p1 double")
    trips = spark.range(5).select(F.col("id").alias("trace_id"), F.lit(0).alias("start_cell"), F.lit(0).alias("end_cell"))
    plan = generator.draw_lengths(trips, laws, 32, 1)._jdf.queryExecution().optimizedPlan().toString()
    at = plan.index("filter(cdf")
    assert "md5" not in plan[at : plan.index("<=", at) + 60]


def test_wide_tables_are_the_tables_of_small_grids(spark, sf, monkeypatch):
    traces, cfg = VIEWS["drift_trips"](spark, sf).persist(), SynthesisConfig(seed=11, uniform_grid=6)

    def release(c):
        syn = synopsis.extract_synopsis(traces, BOUNDS["drift_trips"], equal_split(), c)
        lengths = generator.draw_lengths(generator.draw_trips(syn.trips, 300, 3), syn.lengths, 32, 3, wide=synopsis.WIDE == 5).collect()
        keys = {"mobility": ["src", "dst"], "trips": ["start_cell", "end_cell"], "lengths": ["start_cell", "end_cell"]}
        return [{tuple(r[k] for k in own): r for r in getattr(syn, t).collect()} for t, own in keys.items()], {r.trace_id: r.n for r in lengths}

    for c in (cfg, cfg.but(epsilon=None), cfg.but(total="separate")):
        monkeypatch.setattr(synopsis, "WIDE", 350)
        small, drawn = release(c)
        monkeypatch.setattr(synopsis, "WIDE", 5)
        wide, drawn_wide = release(c)
        for a, b in zip(small, wide):
            assert a.keys() == b.keys()
            for k, row in a.items():
                for name, v in row.asDict().items():
                    assert b[k][name] == (pytest.approx(v, rel=1e-6, abs=1e-7) if isinstance(v, float) else v), (k, name)
        assert drawn == drawn_wide
    traces.unpersist()
