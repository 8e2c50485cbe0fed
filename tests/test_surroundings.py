"""The job entry, SQL functions, sketches, hints, sinks and the stateful trip builder."""

import math
import time

import pytest
from pyspark.sql import functions as F

from private_traces import job
from private_traces.config import Bounds, SynthesisConfig, equal_split
from private_traces.functions import noise, sql_functions
from private_traces.operators import metrics, relational, statistics, synopsis
from private_traces.sources import views
from private_traces.streaming import sessions

UNIT = Bounds(0.0, 1.0, 0.0, 1.0)


@pytest.fixture(scope="module")
def drift(spark, sf):
    return views.drift_trips(spark, sf).persist()


def test_job_releases_and_says_what_it_spent(spark, drift, tmp_path):
    relational.export(drift, str(tmp_path / "in"), "csv")
    told = job.run(spark, str(tmp_path / "in"), "csv", UNIT, str(tmp_path / "out"), SynthesisConfig(top_n=2, epsilon=2.0))
    made = spark.read.option("header", True).csv(str(tmp_path / "out" / "synthetic"))
    assert made.select("trace_id").distinct().count() == told["traces"] and told["epsilon"] == pytest.approx(2.0) and told["rejected"] == 0
    assert spark.read.parquet(str(tmp_path / "out" / "inputs")).where("name = 'seed'").first().value == "withheld"


def test_sql_functions_are_those_of_the_library(spark):
    assert set(sql_functions.register(spark)) >= {"jsd_term", "keyed_laplace", "gapped_patterns"}
    ids = spark.range(50)
    both = ids.select(F.expr("keyed_laplace(2D, '42|test', cast(id as string))").alias("a"), noise.laplace(2.0, 42, "test", "id").alias("b"), F.expr("uniform_cell(id / 50, 0.5, 0D, 1D, 0D, 1D, 6)").alias("c"))
    assert all(abs(r.a - r.b) < 1e-12 and r.c == min(5, int(i / 50 * 6)) * 6 + 3 for i, r in enumerate(both.collect()))
    assert spark.sql("SELECT jsd_term(0.5D, 0.5D) + jsd_term(0D, 1D) AS v").first().v == 0
    assert spark.sql("SELECT great_circle_km(0D, 0D, 90D, 0D) AS v").first().v == pytest.approx(6371.0088 * math.pi / 2)
    got = spark.sql("SELECT pattern FROM gapped_patterns(array(1, 2, 1), 2)").collect()
    assert [r.pattern for r in got] == ["1>1", "1>2", "2>1"]


def test_sketches(drift):
    d = sorted(r.d for r in metrics.distances(drift).collect())
    for r in metrics.distance_quantiles(drift).collect():
        assert abs(d[min(len(d) - 1, int(r.share * len(d)))] - r.d) < 0.01
    paths = statistics.grid6_paths(drift, UNIT)
    exact = metrics.pattern_supports(paths).count()
    assert abs(metrics.distinct_patterns(paths).first().n - exact) < 0.1 * exact


def test_joins_take_the_named_strategy(spark):
    a, b = spark.range(100).withColumn("v", F.col("id") * 2), spark.range(50)
    for strategy, node in (("merge", "SortMergeJoin"), ("shuffle_hash", "ShuffledHashJoin"), ("broadcast", "BroadcastHashJoin")):
        joined = relational.join_by(a, b, "id", strategy=strategy)
        assert joined.count() == 50 and node in joined._jdf.queryExecution().toString()
    with pytest.raises(ValueError):
        relational.join_by(a, b, "id", strategy="broadcast", most=10)


def test_bucketed_table_joins_without_a_shuffle(spark, drift):
    relational.bucketed_table(drift.select("trace_id", "n", "path"), "bucketed_traces", 4)
    t = spark.table("bucketed_traces")
    plan = t.groupBy("trace_id").agg(F.max("n"))._jdf.queryExecution().executedPlan().toString()
    assert t.count() == drift.count() and "hashpartitioning" not in plan
    spark.sql("DROP TABLE bucketed_traces")


def test_uniform_range(spark, drift):
    hist = spark.createDataFrame([(0, 0, k, float(n)) for k, n in ((1, 0.2), (3, 5.0), (4, 0.0), (7, 2.0))] + [(0, 1, 2, 0.0)], "start_cell int, end_cell int, len int, n double")
    assert {(r.end_cell, r.mean) for r in synopsis.range_parameters(hist, 9).collect()} == {(0, 5.0), (1, 5.0)}
    syn = synopsis.extract_synopsis(drift, UNIT, equal_split(), SynthesisConfig(top_n=2, params_from="range"))
    assert syn.lengths.where("p1 < 1 or p1 > 32").count() == 0


def test_streamed_trips(spark, sf, tmp_path):
    events = views.table(spark, sf, "events").where("value is not null")
    for low in (0, 400, 800):  # one after the other: the stream reads files in the order of their times
        events.where(f"event_id - {low} between 0 and {399 if low < 800 else 10**9}").coalesce(1).write.mode("append").parquet(str(tmp_path / "e"))
        time.sleep(1.1)
    q = sessions.stream_trips(sessions.read_events(spark, str(tmp_path / "e"))).writeStream.format("memory").queryName("trips").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(300)
    batch = {(r.user_id, str(r.first_ts)[:19]): r.n for r in sessions.batch_sessions(events).collect()}
    got = spark.table("trips").collect()
    assert got and all(batch.get((r.user_id, str(r.first_ts)[:19])) == r.n for r in got) and all(r.late == 0 for r in got)
    assert len(got) >= len(batch) - events.select("user_id").distinct().count()


def test_batches_replace_their_own_folder(spark, sf, tmp_path):
    events = views.table(spark, sf, "events")
    events.limit(100).write.parquet(str(tmp_path / "e"))
    q = relational.append_batches(sessions.read_events(spark, str(tmp_path / "e")), str(tmp_path / "o"), str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert spark.read.parquet(str(tmp_path / "o")).count() == 100
