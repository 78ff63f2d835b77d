"""Estimates from sketch state: one row a group."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from couponspark.functions import hashing as H
from couponspark.functions import solvers as S

from . import state

By = Sequence[str]
#: Limits of sqrt(k) * relative standard error.
ERROR_CONSTANTS = {"count_inverse": 0.69314718, "code_length": 0.649057, "history": 0.58870501, "register": 1.03896176, "register_code_length": 1.036624, "register_history": 0.83255461, "leftmost_gap": 0.78}


def est_count_inverse(words: DataFrame, by: By = (), k: int = 1024, columns: int = H.FAST_COLUMNS, poisson: bool = False) -> DataFrame:
    c = state.collected(words, by)
    return c.select(*by, "coupons", S.count_inverse(F.col("coupons"), k, columns, poisson).alias("estimate"))


def est_code_length(words: DataFrame, by: By = (), k: int = 1024, columns: int = H.FAST_COLUMNS) -> DataFrame:
    o = state.occupancy(words, by, columns)
    return o.select(*by, "coupons", "occupancy", S.code_length(F.col("occupancy"), k, columns).alias("estimate"))


def est_register(regs: DataFrame, by: By = (), k: int = 1024) -> DataFrame:
    sums = regs.groupBy(*by).agg((F.coalesce(F.sum(F.pow(F.lit(2.0), -F.col("reg"))), F.lit(0.0)) + k - F.count("*")).alias("s"), (F.lit(k) - F.count("*")).alias("empty"))
    return sums.select(*by, F.when(F.col("empty") == k, F.lit(0.0)).otherwise(S.register_estimate(F.col("s"), F.col("empty"), k)).alias("estimate"))


def est_register_code_length(regs: DataFrame, by: By = (), k: int = 1024, columns: int = H.FAST_COLUMNS) -> DataFrame:
    h = state.register_histogram(regs, by, k, columns)
    return h.select(*by, S.register_code_length(F.col("hist"), k, columns).alias("estimate"))


def est_leftmost_gap(words: DataFrame, by: By = (), k: int = 1024) -> DataFrame:
    """Rows that are absent have no leading column."""
    gaps = words.groupBy(*by).agg((F.sum(S.leftmost_gap(F.col("word"))) / F.lit(float(k))).alias("gap"))
    return gaps.select(*by, S.leftmost_gap_estimate(F.col("gap"), k).alias("estimate"))


def history_steps(arrivals: DataFrame, by: By = (), k: int = 1024, columns: int = H.FAST_COLUMNS) -> DataFrame:
    """Each novelty in order with its 1/(mass not collected before), in exact units. A group has k*columns coupons at most."""
    total = k << (columns - 1)
    before = Window.partitionBy(*by).orderBy("first_pos", "row_id", "col_id").rowsBetween(Window.unboundedPreceding, -1)
    spent = F.coalesce(F.sum(H.mass_units(F.col("col_id"), columns)).over(before), F.lit(0).cast("decimal(38,0)"))
    rest = F.lit(str(total)).cast("decimal(38,0)") - spent
    return arrivals.withColumn("step", F.lit(float(total)) / rest.cast("double"))


def est_history(arrivals: DataFrame, by: By = (), k: int = 1024, columns: int = H.FAST_COLUMNS) -> DataFrame:
    """Sum over novelties of one over the probability that the next id is novel. Not for merged sketches."""
    if "merged" in arrivals.columns:
        raise ValueError("a merged sketch has no arrival order: merge first positions instead")
    return history_steps(arrivals, by, k, columns).groupBy(*by).agg(F.count("*").alias("coupons"), F.sum("step").alias("estimate"))


def register_history_steps(arrivals: DataFrame, by: By = (), k: int = 1024, columns: int = H.FAST_COLUMNS, every: bool = False) -> DataFrame:
    """Coupons that raise their row's register, with one over the register mass before; ``every``: the others too, with step 0."""
    one = F.lit(1).cast("bigint")
    in_row = Window.partitionBy(*by, "row_id").orderBy("first_pos", "col_id").rowsBetween(Window.unboundedPreceding, -1)
    raised = arrivals.withColumn("old", F.coalesce(F.max("col_id").over(in_row), F.lit(0)))
    rises = F.col("col_id") > F.col("old")
    raised = raised if every else raised.where(rises)
    unit = lambda c: H.shift_left(one, F.lit(columns) - c).cast("decimal(20,0)")
    before = Window.partitionBy(*by).orderBy("first_pos", "row_id").rowsBetween(Window.unboundedPreceding, -1)
    # a row at register v leaves mass 2^-v to columns beyond v
    loss = F.when(F.col("old") == 0, F.lit(str(1 << columns)).cast("decimal(20,0)")).otherwise(unit(F.col("old"))) - unit(F.col("col_id"))
    total = k << columns
    rest = F.lit(str(total)).cast("decimal(38,0)") - F.coalesce(F.sum("loss").over(before), F.lit(0).cast("decimal(38,0)"))
    raised = raised.withColumn("loss", F.when(rises, loss).otherwise(F.lit(0).cast("decimal(20,0)")))
    return raised.withColumn("step", F.when(F.col("col_id") > F.col("old"), F.lit(float(total)) / rest.cast("double")).otherwise(0.0))


def est_register_history(arrivals: DataFrame, by: By = (), k: int = 1024, columns: int = H.FAST_COLUMNS) -> DataFrame:
    return register_history_steps(arrivals, by, k, columns).groupBy(*by).agg(F.sum("step").alias("estimate"))


def est_hybrid_history(arrivals: DataFrame, by: By = (), k: int = 1024, columns: int = H.FAST_COLUMNS, switch: float = 0.1) -> DataFrame:
    """Matrix history until the estimate reaches ``switch`` * k, then registers: the state forgets what lies left of each
    row's rightmost coupon, the remaining mass becomes that of the registers, and the sum goes on."""
    steps = history_steps(arrivals, by, k, columns)
    upto = Window.partitionBy(*by).orderBy("first_pos", "row_id", "col_id").rowsBetween(Window.unboundedPreceding, 0)
    early = steps.withColumn("sum", F.sum("step").over(upto)).withColumn("early", F.col("sum") - F.col("step") < switch * k)
    both = register_history_steps(early.withColumnRenamed("step", "matrix_step"), by, k, columns, every=True)
    step = F.when(F.col("early"), F.col("matrix_step")).otherwise(F.col("step"))
    return both.groupBy(*by).agg(F.sum(step).alias("estimate"), F.sum(F.col("early").cast("bigint")).alias("matrix_coupons"))


def est_hybrid(words: DataFrame, by: By = (), k: int = 1024, columns: int = H.FAST_COLUMNS, switch: float = 0.1) -> DataFrame:
    """Count-inverse below ``switch`` * k, the register estimate of the same state from there on."""
    lost = F.sum(F.pow(F.lit(2.0), -F.length(F.bin("word"))))
    sums = words.groupBy(*by).agg(F.coalesce(F.sum(F.bit_count("word")), F.lit(0)).cast("bigint").alias("coupons"), (F.coalesce(lost, F.lit(0.0)) + k - F.count("*")).alias("s"), (F.lit(k) - F.count("*")).alias("empty"))
    both = sums.select(*by, S.count_inverse(F.col("coupons"), k, columns).alias("matrix"), S.register_estimate(F.col("s"), F.col("empty"), k).alias("registers"))
    return both.select(*by, F.when(F.col("matrix") < switch * k, F.col("matrix")).otherwise(F.col("registers")).alias("estimate"))


def count_inverse_table(spark: SparkSession, k: int, columns: int = H.FAST_COLUMNS, upto: int | None = None) -> DataFrame:
    """(coupons, estimate) for 0 <= coupons <= ``upto`` (6k): of a size that k alone sets, so it may be broadcast."""
    return spark.range((upto or 6 * k) + 1).select(F.col("id").alias("coupons"), S.count_inverse(F.col("id"), k, columns).alias("estimate"))


def lookup_count_inverse(counts: DataFrame, table: DataFrame, k: int, upto: int | None = None) -> DataFrame:
    """Estimates by table, by the closed form beyond it."""
    joined = counts.join(F.broadcast(table), "coupons", "left")
    return joined.withColumn("estimate", F.when(F.col("coupons") <= (upto or 6 * k), F.col("estimate")).otherwise(S.count_inverse_asymptotic(F.col("coupons"), k)))


def bounds(estimates: DataFrame, method: str, k: int, z: float = 2.0) -> DataFrame:
    """Adds lower and upper at ``z`` standard errors."""
    half = z * ERROR_CONSTANTS[method] / k**0.5
    return estimates.withColumn("lower", F.col("estimate") * (1 - half)).withColumn("upper", F.col("estimate") * (1 + half))


def choose_k(relative_error: float, method: str = "count_inverse") -> int:
    """The least power of two whose standard error is within ``relative_error``."""
    need, k = (ERROR_CONSTANTS[method] / relative_error) ** 2, 16
    while k < need:
        k *= 2
    return k


def accuracy(df: DataFrame, estimate: str, truth: str, by: By = ()) -> DataFrame:
    """(by.., n, bias, rmse, standard_error) relative to the mean truth."""
    d = F.col(estimate) - F.col(truth)
    out = df.groupBy(*by).agg(F.count("*").alias("n"), F.avg(d).alias("bias"), F.sqrt(F.avg(d * d)).alias("rmse"), F.avg(truth).alias("mean_truth"))
    return out.withColumn("standard_error", F.col("rmse") / F.col("mean_truth"))
