"""Distinct counts of event-time windows: the batch aggregation, keyed by window too. bit_or makes replays harmless."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from couponspark.functions import hashing as H
from couponspark.functions import solvers as S


def timed(df: DataFrame, ts: str) -> DataFrame:
    """``ts`` as a timestamp with time zone: watermarks refuse the kind without."""
    return df.withColumn(ts, F.col(ts).cast("timestamp"))


def window_words(stream: DataFrame, ids, ts: str, size: str, slide: str | None = None, late: str = "1 hour", by: Sequence[str] = (), k: int = 1024, profile: str = "fast") -> DataFrame:
    """(window, by.., row_id, word) of tumbling or sliding windows; rows later than ``late`` are dropped by the watermark."""
    row, bit = H.coupon(H.typed(stream, ids) if profile == "fast" else ids, k, profile)
    w: Column = F.window(ts, size, slide) if slide else F.window(ts, size)
    rows = timed(stream, ts).withWatermark(ts, late).where(H.present(ids)).select(ts, *by, row.alias("row_id"), bit.alias("bit"))
    return rows.groupBy(w.alias("window"), *by, "row_id").agg(F.bit_or("bit").alias("word"))


def window_distinct(stream: DataFrame, ids, ts: str, size: str, slide: str | None = None, late: str = "1 hour", by: Sequence[str] = (), k: int = 1024, profile: str = "fast") -> DataFrame:
    """(window, by.., coupons, estimate): a second aggregation over finished windows (append mode)."""
    words = window_words(stream, ids, ts, size, slide, late, by, k, profile)
    counts = words.groupBy("window", *by).agg(F.sum(F.bit_count("word")).alias("coupons"))
    return counts.select("window", *by, "coupons", S.count_inverse(F.col("coupons"), k, H.columns_of(profile)).alias("estimate"))


def session_coupons(stream: DataFrame, ids, ts: str, gap: str, by: Sequence[str], late: str = "1 hour", k: int = 1024, profile: str = "fast") -> DataFrame:
    """(window, by.., coupons) of session windows: the set of coupons is kept whole, since a key by row would split sessions."""
    row, bit = H.coupon(H.typed(stream, ids) if profile == "fast" else ids, k, profile)
    rows = timed(stream, ts).withWatermark(ts, late).where(H.present(ids)).select(ts, *by, F.struct(row.alias("r"), bit.alias("b")).alias("c"))
    return rows.groupBy(F.session_window(ts, gap).alias("window"), *by).agg(F.size(F.collect_set("c")).cast("long").alias("coupons"))


def latest_distinct(updates: DataFrame, by: Sequence[str] = (), k: int = 1024, profile: str = "fast") -> DataFrame:
    """(window, by.., coupons, estimate) from what ``window_words`` wrote in update mode, windows that are still open included.
    Words only gain bits, so the union of all updates is the last state."""
    words = updates.groupBy("window", *by, "row_id").agg(F.bit_or("word").alias("word"))
    counts = words.groupBy("window", *by).agg(F.sum(F.bit_count("word")).alias("coupons"))
    return counts.select("window", *by, "coupons", S.count_inverse(F.col("coupons"), k, H.columns_of(profile)).alias("estimate"))


def late_rows(run: StreamingQuery) -> int:
    """Rows that came after the watermark and were dropped, over the batches that the query still reports."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in run.recentProgress for op in p["stateOperators"])


def exact_first_seen(stream: DataFrame, ids: Sequence[str], ts: str, late: str = "1 hour") -> DataFrame:
    """The exact baseline: each id once within the watermark."""
    return timed(stream, ts).withWatermark(ts, late).dropDuplicatesWithinWatermark(list(ids))
