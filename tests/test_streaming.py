import pytest
from pyspark.sql import functions as F

from couponspark.operators import estimate as E
from couponspark.operators import state
from couponspark.plans import catalog
from couponspark.plans.streams import drained
from couponspark.streaming import windows as W
from couponspark.streaming.history import History


def test_tumbling_equals_batch(spark, sf):
    got = {str(r.start)[:10]: r.coupons for r in catalog.queries()["stream_tumbling_distinct"](spark, sf).collect()}
    ev = spark.read.parquet(f"{sf}/events.parquet").withColumn("day", F.to_date("ts"))
    want = {str(r.day): r.coupons for r in state.collected(state.row_words(ev, "user_id", ["day"], 1024, "portable"), ["day"]).collect()}
    assert got == want


def test_history_equals_batch(spark, sf):
    got = {r.event_type: r.estimate for r in catalog.queries()["stream_history"](spark, sf).collect()}
    ev = spark.read.parquet(f"{sf}/events.parquet")
    a = state.first_arrivals(ev, "user_id", ["event_id"], ["event_type"], 1024, "portable")
    want = {r.event_type: r.estimate for r in E.est_history(a, ["event_type"], 1024, 61).collect()}
    assert got == pytest.approx(want, abs=1e-3)


def test_replays_are_harmless_and_late_rows_go(spark, sf, tmp_path):
    ev = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")).orderBy("ts").limit(3000).cache()
    half = ev.agg(F.percentile_approx("event_id", 0.5)).first()[0]
    ev.where(F.col("event_id") <= half).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    ev.where(F.col("event_id") <= half).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    ev.where(F.col("event_id") > half).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema(ev.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    got = {str(r.window.start)[:10]: r.coupons for r in drained(W.window_distinct(stream, "user_id", "ts", "1 day", late="40 days")).collect()}
    want = {str(r.day): r.coupons for r in state.collected(state.row_words(ev.withColumn("day", F.to_date("ts")), "user_id", ["day"]), ["day"]).collect()}
    assert all(want[d] == c for d, c in got.items())


def test_late_rows_are_counted(spark, tmp_path):
    schema = "user_id long, ts timestamp"
    for day in ("2024-01-10", "2024-01-20", "2024-01-21", "2024-01-10"):
        spark.sql(f"select id as user_id, timestamp'{day} 10:00:00' as ts from range(5)").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    late: list[int] = []  # Spark drops what was late a batch ago
    out = drained(W.window_words(stream, "user_id", "ts", "1 day"), "update", late)
    assert late == [5] and W.latest_distinct(out).count() == 3


def test_history_rule():
    h = History(1024, 61)
    h.add(3, 1)
    h.add(3, 1)
    assert h.total == 1 and h.rest == (1024 << 60) - (1 << 59)


def test_sessions(spark, sf):
    rows = catalog.queries()["stream_session_distinct"](spark, sf).collect()
    assert rows and all(r.coupons >= 1 for r in rows)
