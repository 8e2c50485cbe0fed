"""Relational helpers around traces: clipping, sampling, as-of resampling, bucketed sinks and sources."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

UPLOAD = "trace_id bigint, seq int, x double, y double, ts timestamp_ntz, _corrupt_record string"


def inside(points: DataFrame, x0: float, x1: float, y0: float, y1: float) -> DataFrame:
    """Readings in a half-open rectangle; plain comparisons, so they reach the scan."""
    return points.where((F.col("x") >= x0) & (F.col("x") < x1) & (F.col("y") >= y0) & (F.col("y") < y1))


def sample_traces(traces: DataFrame, share: float, stage: str = "sample") -> DataFrame:
    """A share of whole traces by a hash of the id, never of readings."""
    return traces.where(F.pmod(F.xxhash64(F.lit(stage), "trace_id"), F.lit(1 << 20)) < int(share * (1 << 20)))


def resample(traces: DataFrame, hours: int) -> DataFrame:
    """``trace_id, at, x, y``: the last reading at or before each step of a fixed grid of hours, from the first step at or after
    the first reading to the last reading. Everything happens inside the row of a trace."""
    step = hours * 3600
    second = lambda p: F.floor(F.unix_micros(p["ts"].cast("timestamp")) / 1000000)
    first, last = second(F.get("path", F.lit(0))), second(F.get("path", F.size("path") - 1))
    start = F.ceil(first / step) * step
    grid = traces.where("n > 0").select("trace_id", "path", F.when(start <= last, F.sequence(start, last, F.lit(step).cast("bigint"))).otherwise(F.array().cast("array<bigint>")).alias("g"))
    long = grid.select("trace_id", "path", F.explode("g").alias("s"))
    at = long.withColumn("p", F.element_at(F.filter("path", lambda p: second(p) <= F.col("s")), -1))
    return at.select("trace_id", F.timestamp_seconds("s").cast("timestamp_ntz").alias("at"), F.col("p.x").alias("x"), F.col("p.y").alias("y"))


def as_of(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, values: list[str]) -> DataFrame:
    """For each left row the values of the last right row of its key at or before its time: one union, one window."""
    from pyspark.sql import Window

    a = left.select("*", F.col(left_time).alias("__t"), F.lit(1).alias("__side"), F.lit(None).cast(right.select(F.struct(*values)).schema[0].dataType).alias("__v"))
    b = right.select(F.col(key), F.col(right_time).alias("__t"), F.lit(0).alias("__side"), F.struct(*values).alias("__v"))
    w = Window.partitionBy(key).orderBy("__t", "__side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True).withColumn("__m", F.last("__v", ignorenulls=True).over(w))
    return both.where("__side = 1").select(*left.columns, *[F.col("__m")[v].alias(f"asof_{v}") for v in values])


def read_upload(spark: SparkSession, path: str, form: str = "csv") -> tuple[DataFrame, DataFrame]:
    """(good readings, broken rows) of an uploaded file; the schema is fixed, never inferred."""
    reader = spark.read.schema(UPLOAD).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt_record")
    rows = reader.option("header", True).csv(path) if form == "csv" else reader.json(path)
    bad = F.col("_corrupt_record").isNotNull() | F.col("trace_id").isNull() | F.col("x").isNull() | F.col("y").isNull()
    return rows.where(~bad).drop("_corrupt_record"), rows.where(bad)


def write_paths(traces: DataFrame, path: str, buckets: int = 64) -> None:
    """Nested traces partitioned by a hash of the id, so later passes are narrow scans."""
    traces.withColumn("bucket", F.pmod(F.xxhash64("trace_id"), F.lit(buckets)).cast("int")).repartition(buckets, "bucket").write.partitionBy("bucket").parquet(path)


def bucketed_table(traces: DataFrame, name: str, buckets: int = 64) -> None:
    """Nested traces as a table bucketed and sorted by the id: joins and groups on it need no shuffle."""
    traces.write.bucketBy(buckets, "trace_id").sortBy("trace_id").mode("overwrite").saveAsTable(name)


def append_batches(stream: DataFrame, path: str, checkpoint: str):
    """A stream as Parquet, a folder per micro-batch: a batch that is run again replaces its own folder."""

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint)


STRATEGIES = {"broadcast": "broadcast", "merge": "merge", "shuffle_hash": "shuffle_hash", "nested_loop": "shuffle_replicate_nl"}


def join_by(left: DataFrame, right: DataFrame, on, how: str = "inner", strategy: str | None = None, most: int = 1_000_000) -> DataFrame:
    """A join by the named strategy, or the optimizer's. A side is only broadcast within ``most`` rows, counted first."""
    if strategy is None:
        return left.join(right, on, how)
    if strategy not in STRATEGIES:
        raise ValueError(f"unknown strategy: {strategy}")
    if strategy == "broadcast" and right.limit(most + 1).count() > most:
        raise ValueError(f"over {most} rows to broadcast")
    return left.join(right.hint(STRATEGIES[strategy]), on, how)


def export(traces: DataFrame, path: str, form: str = "parquet") -> None:
    """A synthetic set as Parquet, CSV or JSON in long form."""
    long = traces.select("trace_id", F.inline("path"))
    writer = long.write.option("header", True)
    {"parquet": writer.parquet, "csv": writer.csv, "json": writer.json}[form](path)
