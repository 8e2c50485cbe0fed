"""A service run: load traces, privatise, release, and forget the real ones.

``python -m private_traces.job --input FOLDER --form csv --bounds 0 1 0 1 --out FOLDER [--epsilon 1] [--weights 1 1 1 1 | --tune METRIC]``
"""

from __future__ import annotations

import argparse

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from private_traces.config import Bounds, SplitWeights, SynthesisConfig, equal_split
from private_traces.operators import generator, relational, report, synopsis, tuning


def nested(points: DataFrame) -> DataFrame:
    """``trace_id, n, path`` from ``trace_id, seq, x, y, ts``."""
    path = F.sort_array(F.collect_list(F.struct("seq", "x", "y", "ts")))
    return points.groupBy("trace_id").agg(path.alias("path")).select("trace_id", F.size("path").alias("n"), "path")


def run(spark: SparkSession, source: str, form: str, bounds: Bounds, out: str, cfg: SynthesisConfig, weights: SplitWeights | None = None, tune: bool = False) -> dict:
    """Write ``out``/synthetic, ``out``/ledger, ``out``/inputs and ``out``/rejected_rows (their number only); how many traces were made."""
    if form == "parquet":
        good, bad = spark.read.schema("trace_id bigint, seq int, x double, y double, ts timestamp_ntz").parquet(source), None
    else:
        good, bad = relational.read_upload(spark, source, form)
    traces = nested(good.where("trace_id is not null and x is not null and y is not null")).persist()
    try:
        if tune:
            made, syn = tuning.tune(traces, bounds, cfg).finalise()
        else:
            syn = synopsis.extract_synopsis(traces, bounds, weights or equal_split(), cfg)
            made = generator.generate(syn)
        relational.export(made, f"{out}/synthetic", "parquet" if form == "parquet" else form)
        syn.ledger.frame(spark).write.parquet(f"{out}/ledger")
        report.inputs(spark, cfg).write.parquet(f"{out}/inputs")
        return {"traces": syn.noisy_total, "epsilon": syn.ledger.total, "rejected": 0 if bad is None else bad.count()}
    finally:
        traces.unpersist()


def main(argv: list[str] | None = None) -> None:
    p = argparse.ArgumentParser(description=__doc__)
    p.add_argument("--input", required=True)
    p.add_argument("--form", choices=("csv", "json", "parquet"), default="csv")
    p.add_argument("--bounds", nargs=4, type=float, required=True)
    p.add_argument("--out", required=True)
    p.add_argument("--epsilon", type=float, default=1.0)
    p.add_argument("--weights", nargs=4, type=float)
    p.add_argument("--tune", metavar="METRIC")
    p.add_argument("--settings", default="{}", help="further settings as JSON")
    a = p.parse_args(argv)
    spark = SparkSession.builder.appName("private traces").getOrCreate()
    cfg = SynthesisConfig.from_json(a.settings).but(epsilon=a.epsilon, **({"metric": a.tune} if a.tune else {}))
    print(run(spark, a.input, a.form, Bounds(*a.bounds), a.out, cfg, SplitWeights.of(a.weights) if a.weights else None, bool(a.tune)))


if __name__ == "__main__":
    main()
