"""What users do with sketches: rollups, set operations, windows, many columns at once.

All of it works on row words, so that fan-out (cube, windows, pairs) multiplies at most k words a group and never input rows.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from couponspark.functions import solvers as S

from . import state


def _grouped(words: DataFrame, sets: str, dims: Sequence[str]) -> DataFrame:
    flags = [F.grouping(d).cast("int").alias(f"g_{d}") for d in dims]
    grouped = words.cube(*dims, "row_id") if sets == "cube" else words.rollup(*dims, "row_id")
    return grouped.agg(F.bit_or("word").alias("word"), *flags, F.grouping("row_id").alias("g_row")).where("g_row = 0").drop("g_row")


def cube(words: DataFrame, dims: Sequence[str]) -> DataFrame:
    """Words of every combination of dimensions, from the finest sketches; g_<dim> is 1 where a dimension is rolled up."""
    return _grouped(words, "cube", dims)


def rollup(words: DataFrame, dims: Sequence[str]) -> DataFrame:
    out = None
    for n in range(len(dims), -1, -1):
        part = words.groupBy(*dims[:n], "row_id").agg(F.bit_or("word").alias("word"))
        cols = [F.col(d) if i < n else F.lit(None).cast(words.schema[d].dataType).alias(d) for i, d in enumerate(dims)]
        part = part.select(*cols, "row_id", "word", *[F.lit(int(i >= n)).alias(f"g_{d}") for i, d in enumerate(dims)])
        out = part if out is None else out.unionByName(part)
    return out


def grouping_sets(words: DataFrame, dims: Sequence[str], sets: Sequence[Sequence[str]]) -> DataFrame:
    out = None
    for s in sets:
        part = words.groupBy(*s, "row_id").agg(F.bit_or("word").alias("word"))
        part = part.select(*[F.col(d) if d in s else F.lit(None).cast(words.schema[d].dataType).alias(d) for d in dims], "row_id", "word", *[F.lit(int(d not in s)).alias(f"g_{d}") for d in dims])
        out = part if out is None else out.unionByName(part)
    return out


def several(df: DataFrame, metrics: dict[str, Column], by: Sequence[str] = (), k: int = 1024, profile: str = "fast") -> DataFrame:
    """Words of several distinct counts in one scan: (metric, by.., row_id, word). Ids are rendered as text."""
    pairs = F.explode(F.array(*[F.struct(F.lit(n).alias("metric"), c.cast("string").alias("id")) for n, c in metrics.items()]))
    rows = df.select(*by, pairs.alias("m")).select(*by, "m.metric", "m.id")
    return state.row_words(rows, "id", ["metric", *by], k, profile)


def pair_counts(a: DataFrame, b: DataFrame, k: int, columns: int) -> DataFrame:
    """Estimates of |A|, |B|, |A or B|, and from them of the intersection, the difference and Jaccard's index.

    Inclusion-exclusion: the error is that of the union, so small intersections are uncertain.
    """
    both = a.withColumn("side", F.lit(1)).unionByName(b.withColumn("side", F.lit(2)))
    side = lambda s: F.bit_or(F.when(F.col("side") == s, F.col("word")).otherwise(F.lit(0)))
    rows = both.groupBy("row_id").agg(side(1).alias("a"), side(2).alias("b"), F.bit_or("word").alias("u"))
    sums = rows.agg(*[F.coalesce(F.sum(F.bit_count(c)), F.lit(0)).alias(c) for c in ("a", "b", "u")])
    est = sums.select(*[S.count_inverse(F.col(c), k, columns).alias(f"n_{c}") for c in ("a", "b", "u")])
    inter = F.greatest(F.col("n_a") + F.col("n_b") - F.col("n_u"), F.lit(0.0))
    return est.withColumn("n_intersection", inter).withColumn("n_difference", F.greatest(F.col("n_u") - F.col("n_b"), F.lit(0.0))).withColumn("jaccard", F.when(F.col("n_u") > 0, F.col("n_intersection") / F.col("n_u")))


def cumulative(df: DataFrame, ids, day: str, k: int, profile: str) -> DataFrame:
    """(day, coupons): collected coupons up to each day. First days of coupons are counted, then summed over few days."""
    first = state.first_arrivals(df, ids, [day], (), k, profile)
    new = first.groupBy(F.col(f"first_pos.{day}").alias(day)).agg(F.count("*").alias("new"))
    return new.select(day, F.sum("new").over(Window.orderBy(day)).alias("coupons"))


def rolling(words: DataFrame, day: str, days: int, by: Sequence[str] = ()) -> DataFrame:
    """Words of each day and the ``days`` - 1 before it: daily sketches fan out to the windows they are in."""
    spread = words.withColumn(day, F.explode(F.sequence(F.col(day), F.date_add(day, days - 1))))
    return spread.groupBy(*by, day, "row_id").agg(F.bit_or("word").alias("word"))
