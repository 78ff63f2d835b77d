"""Streaming queries, run once over what is there; each returns the table that the stream leaves."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from couponspark.sources.sketch_store import scratch
from couponspark.streaming import history as S
from couponspark.streaming import windows as W

from . import sqlgen as G
from .registry import query, table


def source(spark, d) -> DataFrame:
    schema = table(spark, d, "events").schema
    return spark.readStream.schema(schema).parquet(f"{d}/events.parquet*")


def drained(stream: DataFrame, mode: str = "append", late: list[int] | None = None) -> DataFrame:
    """All that is available, through a sink that writes to the shared folder; ``late`` gets the number of rows dropped as late."""
    spark = stream.sparkSession
    path = f"{scratch(spark)}/stream-{uuid.uuid4().hex[:12]}"

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("append").parquet(f"{path}/out")

    run = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()
    run.awaitTermination()
    if late is not None:
        late.append(W.late_rows(run))
    return spark.read.parquet(f"{path}/out")


def windowed(src: str) -> str:
    """SQL twin: estimates by ``start``."""
    return f"SELECT strftime(start, '%Y-%m-%d') AS start, coupons, estimate FROM ({G.count_inverse(G.collected(G.words(src, ['start']), ['start']), ['start'])})"


def by_window(updates: DataFrame) -> DataFrame:
    out = W.latest_distinct(updates, k=1024, profile="portable")
    return out.select(F.date_format("window.start", "yyyy-MM-dd").alias("start"), "coupons", F.round("estimate", 2).alias("estimate"))


@query("stream_tumbling_distinct", windowed(G.source("(SELECT *, date_trunc('day', ts) AS start FROM events)", ["user_id"], ["start"])))
def _(spark, d):
    return by_window(drained(W.window_words(source(spark, d), "user_id", "ts", "1 day", k=1024, profile="portable"), "update"))


@query("stream_sliding_distinct", windowed(G.source("(SELECT *, unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS start FROM events)", ["user_id", "props"], ["start"])))
def _(spark, d):
    return by_window(drained(W.window_words(source(spark, d), ["user_id", "props"], "ts", "2 days", "1 day", k=1024, profile="portable"), "update"))


_SESSIONS = "(SELECT *, sum(new) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS session FROM (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY event_type ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS new FROM events))"


@query("stream_session_distinct", f"SELECT event_type, strftime(start, '%Y-%m-%d %H:%M:%S') AS start, coupons FROM ({G.collected(G.words(G.source(_SESSIONS, ['user_id'], ['event_type', 'session']), ['event_type', 'session']), ['event_type', 'session'])}) JOIN (SELECT event_type, session, min(ts) AS start FROM {_SESSIONS} GROUP BY ALL) USING (event_type, session)")
def _(spark, d):
    """Complete mode: sessions that are still open count, and the last batch has them all."""
    out = drained(W.session_coupons(source(spark, d), "user_id", "ts", "30 minutes", ["event_type"], profile="portable"), "complete")
    last = out.join(F.broadcast(out.agg(F.max("batch").alias("batch"))), "batch")
    return last.select("event_type", F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "coupons")


@query("stream_history")
def _(spark, d):
    out = drained(S.history_stream(source(spark, d), "user_id", "event_type", ["event_id"], profile="portable"), "update")
    last = out.groupBy("event_type").agg(F.max(F.struct("batch", "coupons", "estimate")).alias("x"))
    return last.select("event_type", "x.coupons", F.round("x.estimate", 4).alias("estimate"))


@query("stream_exact_first_seen", "SELECT count(DISTINCT user_id) AS seen FROM events WHERE user_id IS NOT NULL")
def _(spark, d):
    out = drained(W.exact_first_seen(source(spark, d), ["user_id"], "ts"))
    return out.agg(F.count("*").alias("seen"))
