"""Streams of readings: session trips, density per window, late rows. A user spans many windows, so releases per window
compose sequentially for that user."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

RANGE = 1 << 16  # event ids that share a running maximum
EVENTS = "event_id bigint, user_id bigint, ts timestamp_ntz, event_type string, value double, props string"


def _sessions(events: DataFrame, gap: str) -> DataFrame:
    rows = events.withColumn("t", F.col("ts").cast("timestamp"))
    grouped = rows.groupBy("user_id", F.session_window("t", gap).alias("w"))
    return grouped.agg(F.count("*").alias("n"), F.min("ts").alias("first_ts"), F.max("ts").alias("last_ts"))


def batch_sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """``user_id, first_ts, last_ts, n``: runs of a user's events less than ``gap`` apart."""
    return _sessions(events, gap).select("user_id", "first_ts", "last_ts", "n")


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def stream_sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """The same sessions from a stream: those the watermark has passed; later rows than that are dropped."""
    rows = events.withColumn("t", F.col("ts").cast("timestamp")).withWatermark("t", late)
    grouped = rows.groupBy("user_id", F.session_window("t", gap).alias("w"))
    return grouped.agg(F.count("*").alias("n"), F.min("ts").alias("first_ts"), F.max("ts").alias("last_ts")).select("user_id", "first_ts", "last_ts", "n")


TRIP = "user_id bigint, first_ts timestamp, last_ts timestamp, n bigint, x0 double, y0 double, x1 double, y1 double, late bigint"
HELD = "first double, last double, n long, x0 double, y0 double, x1 double, y1 double, late long"


def stream_trips(events: DataFrame, gap_seconds: float = 6 * 3600, late: str = "1 hour") -> DataFrame:
    """Trips built reading by reading: a user's open trip is the state, and it ends when the next reading comes ``gap_seconds``
    later or the watermark is that far past its last one. ``late``: readings of the user so far that were older than the open
    trip's last one by more than the gap, which join no trip. The state is one fixed-size row a user."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key, batches, state: GroupState):
        (user,) = key
        held = list(state.get) if state.exists else None
        out = []

        def done(h):
            first, last = (pd.Timestamp(round(x * 1e6), unit="us", tz="UTC") for x in h[:2])
            out.append((user, first, last, int(h[2]), *h[3:7], int(h[7])))

        if state.hasTimedOut:
            done(held)
            state.remove()
        else:
            rows = pd.concat(list(batches)).sort_values(["at", "event_id"])
            for at, x, y in zip(rows["at"], rows["x"], rows["y"]):
                if held is not None and at < held[0] - gap_seconds:
                    held[7] += 1
                elif held is not None and at < held[1] + gap_seconds:
                    held[2] += 1
                    if at >= held[1]:
                        held[1], held[5], held[6] = at, x, y
                    elif at < held[0]:
                        held[0], held[3], held[4] = at, x, y
                else:
                    if held is not None:
                        done(held)
                    held = [at, at, 1, x, y, x, y, held[7] if held is not None else 0]
            state.update(tuple(held))
            state.setTimeoutTimestamp(max(int((held[1] + gap_seconds) * 1000), state.getCurrentWatermarkMs() + 1))
        if out:
            yield pd.DataFrame(out, columns=["user_id", "first_ts", "last_ts", "n", "x0", "y0", "x1", "y1", "late"])

    t = F.col("ts").cast("timestamp")
    rows = events.where("value is not null").select("user_id", "event_id", t.alias("t"), (F.unix_micros(t) / 1e6).alias("at"), F.col("value").alias("x"), F.coalesce(F.get_json_object("props", "$.k").cast("double"), F.lit(0.0)).alias("y"))
    return rows.withWatermark("t", late).groupBy("user_id").applyInPandasWithState(step, TRIP, HELD, "append", GroupStateTimeout.EventTimeTimeout)


def density_windows(events: DataFrame, window: str = "1 day", slide: str | None = None, late: str = "1 hour", bins: int = 6) -> DataFrame:
    """``start, cell, n``: readings per cell and (tumbling or sliding) window."""
    from private_traces.functions.lattice import uniform_cell
    from private_traces.sources.views import BOUNDS

    b = BOUNDS["user_days"]
    rows = events.withColumn("t", F.col("ts").cast("timestamp"))
    rows = rows.withWatermark("t", late) if events.isStreaming else rows
    cell = uniform_cell(F.col("value"), F.get_json_object("props", "$.k").cast("double"), b, bins)
    return rows.where("value is not null").groupBy(F.window("t", window, slide or window).alias("w"), cell.alias("cell")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "cell", "n")


def late_rows(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Rows older than the largest time of any earlier event id by more than ``late``: what a watermark may drop (batch form).

    The running maximum is taken within ranges of ``RANGE`` ids; the largest times of the ranges, one row each, carry it on."""
    from pyspark.sql import Window

    ranged = events.withColumn("range", F.floor(F.col("event_id") / RANGE))
    before = F.max("top").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1))
    tops = ranged.groupBy("range").agg(F.max("ts").alias("top")).select("range", before.alias("carried"))
    inside = F.max("ts").over(Window.partitionBy("range").orderBy("event_id").rangeBetween(Window.unboundedPreceding, -1))
    found = ranged.withColumn("inside", inside).join(F.broadcast(tops), "range")
    return found.where(F.col("ts") < F.greatest("carried", "inside") - F.expr(f"interval {late}")).select(*events.columns)
