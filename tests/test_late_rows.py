"""Late rows are counted across days: the late_events fixture moves every 50th row back by 2 hours."""

from datetime import timedelta

from pyspark.sql import functions as F

from private_traces.sources import views
from private_traces.streaming import sessions


def test_late_rows_are_found_across_days(spark, monkeypatch):
    sf = "/root/testdata/sf0.01"
    shifted = F.when(F.col("event_id") % 50 == 0, F.col("ts") - F.expr("interval 2 hours")).otherwise(F.col("ts"))
    late = views.table(spark, sf, "events").withColumn("ts", shifted)
    want, top = set(), None
    for r in sorted(late.select("event_id", "ts").collect()):
        if top and r.ts < top - timedelta(hours=1):
            want.add(r.event_id)
        top = max(top, r.ts) if top else r.ts
    days = {r.event_id: r.ts.date() for r in views.table(spark, sf, "events").collect()}
    crossed = {r.event_id for r in late.collect() if r.event_id in want and r.ts.date() != days[r.event_id]}
    assert want and crossed
    for size in (sessions.RANGE, 64):
        monkeypatch.setattr(sessions, "RANGE", size)
        got = sessions.late_rows(late)
        assert got.columns == late.columns and {r.event_id for r in got.collect()} == want
