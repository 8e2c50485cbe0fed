"""Many weight vectors in one job: the released trip distribution of every candidate against the real one.

Candidates share their draws (common random numbers: the key holds no evaluation), so they differ in scale only. Rows are
candidates x pairs of cells; ``chunk`` bounds how many candidates one job takes.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from private_traces.functions.noise import clean_up, densify, keyed_uniform, laplace_of

from .grid import Grid
from .synopsis import pair_domain


def trip_errors(counts: DataFrame, grid: Grid, weights: np.ndarray, epsilon: float, seed: int, mode: str = "shift", chunk: int = 200) -> DataFrame:
    """``eval_id, w1..w4, value``: divergence (base 2) between the exact trip counts and each candidate's noisy distribution."""
    spark = counts.sparkSession
    keys = ["start_cell", "end_cell"]
    dense = densify(counts.select(*keys, F.col("n").cast("double").alias("c")), pair_domain(spark, grid.size, *keys), keys)
    drawn = dense.withColumn("unit", laplace_of(keyed_uniform(seed, "trip", *keys), 1.0))
    parts = []
    for a in range(0, len(weights), chunk):
        rows = [(a + i, *map(float, w)) for i, w in enumerate(weights[a : a + chunk])]
        evals = F.broadcast(spark.createDataFrame(rows, "eval_id int, w1 double, w2 double, w3 double, w4 double"))
        noisy = drawn.crossJoin(evals).withColumn("mass", F.col("c") + F.col("unit") / (F.col("w3") * epsilon))
        clean = clean_up(noisy, "mass", ["eval_id"], mode)
        per = Window.partitionBy("eval_id")
        p, q = F.col("c") / F.sum("c").over(per), F.try_divide(F.col("mass"), F.sum("mass").over(per))
        sides = clean.select("eval_id", "w1", "w2", "w3", "w4", p.alias("p"), F.coalesce(q, F.lit(0.0)).alias("q"))
        half = lambda x, y: F.when(F.col(x) > 0, 0.5 * F.col(x) * F.log2(2 * F.col(x) / (F.col(x) + F.col(y)))).otherwise(0.0)
        parts.append(sides.groupBy("eval_id", "w1", "w2", "w3", "w4").agg(F.sum(half("p", "q") + half("q", "p")).alias("value")))
    return reduce(DataFrame.unionByName, parts)
