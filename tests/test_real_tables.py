"""The real side from one pass over sorted lines against the one from tables."""

import dataclasses

import numpy as np
import pytest
from pyspark.sql import functions as F

from private_traces.config import Bounds
from private_traces.operators import lattice_model, metrics, statistics
from private_traces.plans import catalog
from private_traces.sources import views

UNIT = Bounds(0.0, 1.0, 0.0, 1.0)


def _both(spark, folder, max_len=32):
    traces = views.drift_trips(spark, folder).persist()
    old = lattice_model.tables(metrics.RealSide(traces, UNIT), statistics.leaf_statistics(traces, UNIT, 6, max_len))
    return old, lattice_model.real_tables(views.drift_steps(spark, folder), views.drift_positions, UNIT, 6, max_len)


def _same(old, new):
    for field in dataclasses.fields(old):
        a, b = getattr(old, field.name), getattr(new, field.name)
        if isinstance(a, tuple):  # rows of a leaf table, in any order
            a, b = (np.stack([c.astype(float) for c in t])[:, np.lexsort(t[-2::-1])] for t in (a, b))
        if isinstance(a, np.ndarray):
            assert a.shape == b.shape and np.allclose(a, b, rtol=1e-9, atol=1e-9), field.name
        else:
            assert a == b, field.name


@pytest.mark.parametrize("readings", [1_000_000, 7])
def test_one_pass_counts_what_the_tables_count(spark, sf, monkeypatch, readings):
    monkeypatch.setattr(lattice_model, "READINGS", readings)
    _same(*_both(spark, sf))


def test_long_traces_equal_lines_and_nulls(spark, sf, tmp_path):
    li = spark.read.parquet(f"{sf}/lineitem.parquet").where("l_orderkey < 300")
    key = F.when(F.col("l_orderkey") % 3 == 0, 7).when(F.col("l_orderkey") % 11 == 0, None).otherwise(F.col("l_orderkey"))
    odd = li.withColumn("l_orderkey", key.cast("bigint")).withColumn("l_tax", F.when(F.col("l_partkey") % 13 != 0, F.col("l_tax"))).withColumn("l_shipdate", F.when(F.col("l_partkey") % 5 != 0, F.col("l_shipdate")))
    odd.union(odd.where("l_suppkey % 2 = 0")).write.parquet(str(tmp_path / "lineitem.parquet"))
    old, new = _both(spark, str(tmp_path), max_len=4)
    assert new.total > 50 and len(new.patterns) == 100
    _same(old, new)


def test_without_traces_the_tables_are_empty(spark, sf, tmp_path):
    spark.read.parquet(f"{sf}/lineitem.parquet").limit(0).write.parquet(str(tmp_path / "lineitem.parquet"))
    _same(*_both(spark, str(tmp_path)))


def test_bulk_metrics_takes_its_real_side_in_one_pass(spark, sf, monkeypatch):
    class Done(Exception):
        pass

    def stop(spark, t, *_):
        raise Done(t.total)

    monkeypatch.setattr(metrics, "RealSide", None)
    monkeypatch.setattr(lattice_model, "evaluate_tables", stop, raising=False)
    with pytest.raises(Done) as done:
        catalog.QUERIES["bulk_metrics"](spark, sf)
    assert done.value.args == (views.drift_trips(spark, sf).count(),)


def test_a_guide_and_halves_find_what_a_full_look_finds():
    rng = np.random.default_rng(6)
    for size in (1, 3, 77, 300):
        cum = np.cumsum(rng.random((40, size)) * (rng.random((40, size)) < 0.3), axis=1)
        cum = cum[cum[:, -1] > 0]
        cum /= cum[:, -1:].copy()
        cum[0] = np.round(cum[0] * lattice_model.GUIDE) / lattice_model.GUIDE  # steps where a guide begins
        row, u = rng.integers(0, len(cum), 4000), np.r_[rng.random(3872), np.arange(128) / 128]
        assert (lattice_model._led(cum, lattice_model._guide(cum), row, u) == (cum[row] <= u[:, None]).sum(axis=1)).all()
    for n in (0, 1, 64, 65, 1000, 4097):
        words = rng.integers(0, 2**64, (n, 4), dtype=np.uint64)
        assert (lattice_model._ones(words) == np.unpackbits(words.view(np.uint8), axis=1).sum(axis=0)).all()


def test_later_blocks_of_a_run_take_kept_tables_and_follow_the_law():
    rng, size, n = np.random.default_rng(7), 9, 60_000
    p = rng.dirichlet(np.full(size, 0.5), size)
    pairs = np.arange(size**2)
    grid = lattice_model.uniform_grid(UNIT, 3, 3)
    model = lattice_model.Model(grid, p, np.full(size**2, size**-2.0), np.full(size**2, 1.0), pairs, np.tile([0.0, 0.0, 0.0, 1.0], (size**2, 1)))
    law = p[:, :, None, None] * p[None, :, :, None] * p[None, None]  # start, two between, end
    law = law / law.sum(axis=(1, 2), keepdims=True) / size**2
    for kept in (0, 1, 2):
        assert [seen for _, _, seen in model.held.get("tables", {}).values()] == [kept] * 2 * (kept > 0)
        length, cells, jumps = lattice_model.walked(model, n, rng)
        assert jumps == 0 and (length == 4).all()
        code = cells[3] * size**3 + cells[2] * size**2 + cells[1] * size + cells[0]
        found, want = np.bincount(code, minlength=size**4), law.ravel() * n
        assert (found[want == 0] == 0).all() and (np.abs(found - want) < 6 * np.sqrt(want) + 6).all()


def test_halves_are_rounded_as_round_does(spark, sf):
    rng = np.random.default_rng(9)
    odd = [0.0, -0.0, 0.5, -0.5, 1.5, -2.5, 0.49999999999999994, -0.49999999999999994, 4503599627370495.5, 1e15, 149999.99999999997, 150000.00000000003]
    v = [*odd, *(rng.integers(-400_000, 400_000, 2000) / 2).tolist(), *(rng.normal(size=2000) * 1e5).tolist()]
    li = spark.read.parquet(f"{sf}/lineitem.parquet").select((F.lit(3000000) * (F.col("l_discount") - 0.05)).alias("v"))
    frame = spark.createDataFrame([(float(x),) for x in v], "v double").union(li)
    assert frame.where(~views.half_up(F.col("v")).eqNullSafe(F.round("v").cast("bigint"))).count() == 0
    assert "round(" not in views.drift_steps(spark, sf)._jdf.queryExecution().optimizedPlan().toString()
