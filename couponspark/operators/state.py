"""Sketch state as rows: (group.., row_id, word), built by a partial bit_or and merged by another."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from couponspark.functions import hashing as H

By = Sequence[str]


def coupon_rows(df: DataFrame, ids, by: By = (), k: int = 1024, profile: str = "fast", seed=None, extra: Sequence[str | Column] = ()) -> DataFrame:
    """One (by.., row_id, bit) for each input row with an id."""
    row, bit = H.coupon(H.typed(df, ids) if profile == "fast" else ids, k, profile, seed)
    return df.where(H.present(ids)).select(*by, *extra, row.alias("row_id"), bit.alias("bit"))


def coupons(df: DataFrame, ids, by: By = (), k: int = 1024, profile: str = "fast", seed=None) -> DataFrame:
    """The set of collected coupons (by.., row_id, col_id)."""
    return coupon_rows(df, ids, by, k, profile, seed).distinct().select(*by, "row_id", H.column_number(F.col("bit")).alias("col_id"))


def row_words(df: DataFrame, ids, by: By = (), k: int = 1024, profile: str = "fast", seed=None, floor: int = 0) -> DataFrame:
    """The matrix (by.., row_id, word). ``floor``: updates of the first columns are dropped; sound only if what they would
    add is in a state that is merged in (see ``saturation_floor``)."""
    rows = coupon_rows(df, ids, by, k, profile, seed)
    if floor:
        rows = rows.where(F.col("bit") >= F.lit(1 << floor))
    return rows.groupBy(*by, "row_id").agg(F.bit_or("bit").alias("word"))


def merge(words: DataFrame, *more: DataFrame, by: By = ()) -> DataFrame:
    """Union of sketches: the sketch of the joined streams."""
    for m in more:
        words = words.unionByName(m)
    return words.groupBy(*by, "row_id").agg(F.bit_or("word").alias("word"))


def collected(words: DataFrame, by: By = ()) -> DataFrame:
    """(by.., coupons): collected cells."""
    return words.groupBy(*by).agg(F.coalesce(F.sum(F.bit_count("word")), F.lit(0)).cast("bigint").alias("coupons"))


def occupancy(words: DataFrame, by: By = (), columns: int = H.FAST_COLUMNS) -> DataFrame:
    """(by.., coupons, occupancy): collected cells of each column, all in one pass."""
    sums = [F.coalesce(F.sum(F.shiftright("word", j).bitwiseAND(F.lit(1))), F.lit(0)).cast("bigint") for j in range(columns)]
    return words.groupBy(*by).agg(F.coalesce(F.sum(F.bit_count("word")), F.lit(0)).cast("bigint").alias("coupons"), F.array(*sums).alias("occupancy"))


def registers(words: DataFrame, by: By = ()) -> DataFrame:
    """The lossy view: rightmost collected column of each row."""
    return words.select(*by, "row_id", F.length(F.bin("word")).cast("int").alias("reg"))


def registers_direct(df: DataFrame, ids, by: By = (), k: int = 1024, profile: str = "fast", floor: int = 0) -> DataFrame:
    """Registers without the matrix; ``floor``: the least register of a state that is merged in."""
    rows = coupon_rows(df, ids, by, k, profile)
    if floor:
        rows = rows.where(F.col("bit") >= F.lit(1 << floor))
    return rows.groupBy(*by, "row_id").agg(F.max("bit").alias("bit")).select(*by, "row_id", H.column_number(F.col("bit")).alias("reg"))


def merge_registers(regs: DataFrame, *more: DataFrame, by: By = ()) -> DataFrame:
    for m in more:
        regs = regs.unionByName(m)
    return regs.groupBy(*by, "row_id").agg(F.max("reg").alias("reg"))


def register_histogram(regs: DataFrame, by: By = (), k: int = 1024, columns: int = H.FAST_COLUMNS) -> DataFrame:
    """(by.., hist): rows with register 0..columns; rows that are absent are 0."""
    counts = [F.sum((F.col("reg") == v).cast("bigint")) for v in range(1, columns + 1)]
    return regs.groupBy(*by).agg(F.array((F.lit(k) - F.count("*")).cast("bigint"), *[F.coalesce(c, F.lit(0)) for c in counts]).alias("hist"))


def saturation_floor(words: DataFrame, k: int) -> Column | int:
    """Leading columns that are full in all k rows: updates left of it can't change a state that holds this one."""
    row = words.agg(F.count("*").alias("n"), F.bit_and("word").alias("all")).first()
    if not row or row["n"] < k or row["all"] is None:
        return 0
    full, floor = row["all"], 0
    while full >> floor & 1:
        floor += 1
    return floor


def downsize(words: DataFrame, k: int, by: By = ()) -> DataFrame:
    """The sketch with fewer rows that the same stream gives."""
    return words.withColumn("row_id", F.col("row_id").bitwiseAND(F.lit(k - 1))).groupBy(*by, "row_id").agg(F.bit_or("word").alias("word"))


def first_arrivals(df: DataFrame, ids, order: Sequence[str], by: By = (), k: int = 1024, profile: str = "fast") -> DataFrame:
    """(by.., row_id, col_id, first_pos): when each coupon came first; order must be total.

    The least value of the first order column is a hash aggregate over all rows, which sorts nothing. Further columns decide only
    among the rows that share it, at most a few for each of k * 63 coupons a group.
    """
    first, *more = order
    rows = coupon_rows(df, ids, by, k, profile, extra=[F.col(c).alias(f"__{i}") for i, c in enumerate(order)])
    least = rows.groupBy(*by, "row_id", "bit").agg(F.min("__0").alias("__least"))
    if more:
        least = least.toDF(*[f"__g{i}" for i in range(len(by))], "__row", "__bit", "__least")
        same = (F.col("row_id") == F.col("__row")) & (F.col("bit") == F.col("__bit")) & F.col("__0").eqNullSafe(F.col("__least"))
        for i, c in enumerate(by):
            same = same & F.col(c).eqNullSafe(F.col(f"__g{i}"))
        ties = rows.join(least, same).groupBy(*by, "row_id", "bit")
        least = ties.agg(F.min(F.struct(*[F.col(f"__{i}").alias(c) for i, c in enumerate(order)])).alias("first_pos"))
    else:
        least = least.withColumn("first_pos", F.struct(F.col("__least").alias(first)))
    return least.select(*by, "row_id", H.column_number(F.col("bit")).alias("col_id"), "first_pos")


def merge_first_arrivals(a: DataFrame, b: DataFrame, by: By = ()) -> DataFrame:
    """Sketches that keep first positions merge with their history (an extension; eight bytes and more a coupon)."""
    return a.unionByName(b).groupBy(*by, "row_id", "col_id").agg(F.min("first_pos").alias("first_pos"))
