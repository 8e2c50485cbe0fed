"""Traces over the given tables. Each view is one row per trace: ``trace_id, n, path`` (array of seq, x, y, ts).

A trace is gathered by one aggregation on its id and sorted inside its row, so a view costs one shuffle. Readings with a
null id or coordinate are dropped before anything is counted.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from private_traces.config import Bounds

BOUNDS = {
    "order_trips": Bounds(900, 105000, 1, 51), "drift_trips": Bounds(0, 1, 0, 1), "subset_trips": Bounds(0, 1, 0, 1),
    "user_days": Bounds(0, 600, 0, 100), "user_long": Bounds(0, 600, 0, 100), "customer_long": Bounds(1000, 500000, 9131, 11536),
}
PATH = "array<struct<seq:int,x:double,y:double,ts:timestamp_ntz>>"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def gather(rows: DataFrame, trace: Column, order: list[Column], *values: Column) -> DataFrame:
    """``trace_id, r``: the rows of each trace in order; ``r`` holds o0.. (the order) and the given values."""
    row = F.struct(*[c.alias(f"o{i}") for i, c in enumerate(order)], *values)
    return rows.where(trace.isNotNull()).groupBy(trace.cast("bigint").alias("trace_id")).agg(F.sort_array(F.collect_list(row)).alias("r"))


def _path(gathered: DataFrame) -> DataFrame:
    """From r with x, y, ts to the canonical nested form."""
    path = F.transform("r", lambda p, i: F.struct((i + 1).cast("int").alias("seq"), p["x"].cast("double").alias("x"), p["y"].cast("double").alias("y"), p["ts"].cast("timestamp_ntz").alias("ts")))
    return gathered.select("trace_id", F.size("r").alias("n"), path.alias("path"))


def _line_order() -> list[Column]:
    return [F.col(c) for c in ("l_shipdate", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity")]


def order_trips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines of an order; price by quantity: a control without structure."""
    li = table(spark, sf_dir, "lineitem").where("l_extendedprice is not null and l_quantity is not null")
    return _path(gather(li, F.col("l_orderkey"), _line_order(), F.col("l_extendedprice").alias("x"), F.col("l_quantity").alias("y"), F.col("l_shipdate").alias("ts")))


def half_up(v: Column) -> Column:
    """``round(v)`` as bigint, halves away from zero, without the decimal number that ``round`` makes of every double."""
    whole = F.abs(v).cast("bigint")
    rest = F.abs(v) - whole  # exact
    return F.when(v < 0, -1).otherwise(1) * (whole + F.when((rest >= 0.5) & (rest < 1), 1).otherwise(0))


def _drift_lines(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[Column]]:
    """The lines that have all a walk needs, and dx, dy, sx, sy: the drift of a line and where a walk would start that begins with it."""
    li = table(spark, sf_dir, "lineitem").where("l_extendedprice is not null and l_quantity is not null and l_discount is not null and l_tax is not null")
    dx, dy = half_up(F.lit(3000000) * (F.col("l_discount") - 0.05)), half_up(F.lit(4000000) * (F.col("l_tax") - 0.04))
    u, v = (F.col("l_extendedprice") - 900) / 104100, (F.col("l_quantity") - 1) / 49
    sx, sy = half_up(u * u * 1000000), half_up(v * v * 1000000)
    return li, [dx.alias("dx"), dy.alias("dy"), sx.alias("sx"), sy.alias("sy")]


def drift_trips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as short walks: the start is skewed to a corner, each later line drifts by its discount and tax.

    Positions are summed in whole millionths, so they are the same whatever the order of summation."""
    li, moves = _drift_lines(spark, sf_dir)
    g = gather(li, F.col("l_orderkey"), _line_order(), *moves, F.col("l_shipdate").alias("ts"))
    inside = lambda v: F.least(F.lit(999999), F.greatest(F.lit(0), v)) / F.lit(1000000.0)
    start = F.struct(F.get("r", F.lit(0))["sx"].alias("x"), F.get("r", F.lit(0))["sy"].alias("y"), F.array().cast(PATH).alias("path"))

    def step(acc: Column, p: Column) -> Column:
        first = F.size(acc["path"]) == 0
        x, y = acc["x"] + F.when(first, 0).otherwise(p["dx"]), acc["y"] + F.when(first, 0).otherwise(p["dy"])
        here = F.struct((F.size(acc["path"]) + 1).cast("int").alias("seq"), inside(x).alias("x"), inside(y).alias("y"), p["ts"].cast("timestamp_ntz").alias("ts"))
        return F.struct(x.alias("x"), y.alias("y"), F.concat(acc["path"], F.array(here)).alias("path"))

    return g.select("trace_id", F.size("r").alias("n"), F.aggregate("r", start, step, lambda a: a["path"]).alias("path"))


def drift_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``trace_id, dx, dy, sx, sy``: the lines of the drift view, each trace whole in one partition and in order."""
    li, moves = _drift_lines(spark, sf_dir)
    order = [c.alias(f"o{i}") for i, c in enumerate(_line_order())]
    rows = li.where("l_orderkey is not null").select(F.col("l_orderkey").cast("bigint").alias("trace_id"), *order, *moves)
    names = ["dx", "dy", "sx", "sy"]
    return rows.repartition("trace_id").sortWithinPartitions("trace_id", *[f"o{i}" for i in range(len(order))], *names).select("trace_id", *names)


def drift_positions(first: np.ndarray, dx: np.ndarray, dy: np.ndarray, sx: np.ndarray, sy: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """x and y of the drift view from its lines; trace i holds those from ``first[i]`` to ``first[i + 1]``."""

    def along(start: np.ndarray, moves: np.ndarray) -> np.ndarray:
        gone = np.cumsum(moves)
        at = start[first[:-1]] - gone[first[:-1]]
        return np.clip(gone + np.repeat(at, np.diff(first)), 0, 999999) / 1000000.0

    return along(sx, dx), along(sy, dy)


def hash_share(trace_id: Column, stage: str = "subset") -> Column:
    """A number 0..9999 from the trace id: the same for all its readings."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(stage), trace_id.cast("string"))), 1, 8), 16, 10).cast("bigint") % 10000


def subset_trips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """20.28 % of the drift view's traces: the smaller set of the same semantics."""
    return drift_trips(spark, sf_dir).where(hash_share(F.col("trace_id")) < 2028)


def _events(spark: SparkSession, sf_dir: str, trace: Column) -> DataFrame:
    ev = table(spark, sf_dir, "events").withColumn("k", F.get_json_object("props", "$.k").cast("double")).where("value is not null and k is not null")
    return _path(gather(ev, trace, [F.col("ts"), F.col("event_id")], F.col("value").alias("x"), F.col("k").alias("y"), F.col("ts").alias("ts")))


def user_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _events(spark, sf_dir, F.col("user_id") * 100 + F.dayofmonth("ts"))


def user_long(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _events(spark, sf_dir, F.col("user_id"))


def customer_long(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").where("o_totalprice is not null and o_orderdate is not null")
    day = F.datediff(F.col("o_orderdate").cast("date"), F.lit("1970-01-01").cast("date"))
    return _path(gather(orders, F.col("o_custkey"), [F.col("o_orderdate"), F.col("o_orderkey")], F.col("o_totalprice").alias("x"), day.cast("double").alias("y"), F.col("o_orderdate").alias("ts")))


def point_cloud(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First two components of each vector, for density-only tests."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("trace_id"), F.lit(1).alias("n"), F.array(F.struct(F.lit(1).alias("seq"), F.get("embedding", F.lit(0)).cast("double").alias("x"), F.get("embedding", F.lit(1)).cast("double").alias("y"), F.lit(None).cast("timestamp_ntz").alias("ts"))).alias("path"))


def symbol_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``trace_id, n, cells``: turns of a conversation as symbols of role and length."""
    role = F.when(F.col("role") == "user", 0).when(F.col("role") == "assistant", 1).otherwise(2)
    cell = (role * 4 + F.least(F.lit(3), F.floor(F.coalesce(F.length("text"), F.lit(0)) / 200))).cast("int")
    g = table(spark, sf_dir, "conversations").groupBy(F.col("conv_id").alias("trace_id")).agg(F.sort_array(F.collect_list(F.struct("turn", cell.alias("c")))).alias("r"))
    return g.select("trace_id", F.size("r").alias("n"), F.col("r.c").alias("cells"))


VIEWS = {"order_trips": order_trips, "drift_trips": drift_trips, "subset_trips": subset_trips, "user_days": user_days, "user_long": user_long, "customer_long": customer_long}


def points(traces: DataFrame) -> DataFrame:
    """Long form: ``trace_id, seq, x, y, ts``."""
    return traces.select("trace_id", F.inline("path"))


def nest(long: DataFrame) -> DataFrame:
    """``trace_id, seq, x, y[, ts]`` rows as traces."""
    ts = F.col("ts") if "ts" in long.columns else F.lit(None).cast("timestamp_ntz")
    clean = long.where("trace_id is not null and x is not null and y is not null and not isnan(x) and not isnan(y)")
    return _path(gather(clean, F.col("trace_id"), [F.col("seq")], F.col("x"), F.col("y"), ts.alias("ts")))
