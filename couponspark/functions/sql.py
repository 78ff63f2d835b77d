"""SQL functions that Catalyst inlines, so that plain SQL builds and reads sketches."""

from __future__ import annotations

from pyspark.sql import SparkSession

from . import solvers as S
from .hashing import FAST_COLUMNS


def register(spark: SparkSession, k: int = 1024, columns: int = FAST_COLUMNS) -> None:
    """``cm_row(id)``, ``cm_bit(id)`` (fast profile), ``cm_count(word)`` and ``cm_estimate(coupons)`` for matrices of k rows."""
    rates = ", ".join(f"{v!r}D" for v in S.log_rest(k, columns))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION cm_row(id STRING) RETURNS INT RETURN cast(xxhash64(id) & {k - 1} AS INT)")
    guard = f"((xxhash64(1540483477, id) & {(1 << 62) - 1}L) | {1 << 62}L)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION cm_bit(id STRING) RETURNS BIGINT RETURN {guard} & -{guard}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cm_count(word BIGINT) RETURNS BIGINT RETURN bit_count(word)")
    mid = "pow(2D, (s.lo + s.hi) / 2)"
    less = f"{k} * aggregate(array({rates}), 0D, (a, l) -> a - expm1({mid} * l)) < coupons"
    step = f"named_struct('lo', IF({less}, (s.lo + s.hi) / 2, s.lo), 'hi', IF({less}, s.hi, (s.lo + s.hi) / 2))"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION cm_estimate(coupons BIGINT) RETURNS DOUBLE RETURN CASE WHEN coupons = 0 THEN 0D ELSE aggregate(sequence(1, {S.STEPS}), named_struct('lo', 0D, 'hi', {S.top_of(k)}D), (s, i) -> {step}, s -> pow(2D, (s.lo + s.hi) / 2)) END")
