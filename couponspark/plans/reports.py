"""Reports from simulation and codecs: what SQL can't express. Rows are few; the runs behind them are spread over tasks."""

from __future__ import annotations

import math
import uuid

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from couponspark.functions import hashing as H
from couponspark.operators import codec as C
from couponspark.operators import simulate as X
from couponspark.operators import state
from couponspark.sources import sketch_store
from couponspark.sources.sketch_store import scratch

from .registry import query, table

KS = tuple(1 << e for e in range(4, 14))
TRIALS, POINTS, FLAT = 64, 200, (25, 75)  # the flat part of the curves: counts from k 2^25 to k 2^75
#: Limits that theory gives for sqrt(k) * relative error, and the next coefficient of one of them.
THEORY = {"count_inverse": math.log(2), "history": math.sqrt(math.log(2) / 2), "register": math.sqrt(3 * math.log(2) - 1), "register_history": math.sqrt(math.log(2))}
NEXT = {"register_history": 0.449347}
_RUNS: dict[str, str] = {}


def flat_runs(spark):
    """Runs over the flat part, simulated once a session and written to the shared folder: five reports read them."""
    app = spark.sparkContext.applicationId
    if app not in _RUNS:
        path = f"{scratch(spark)}/flat-{uuid.uuid4().hex[:12]}"
        X.simulate(spark, KS, TRIALS, *FLAT, POINTS).write.parquet(path)
        _RUNS[app] = path
    return spark.read.parquet(_RUNS[app])


def fitted(spark):
    """(estimator, c0, c1, c2, theory, theory_c1): limits by a quadratic fit in 1/k beside theory."""
    known = lambda values: F.create_map(*[F.lit(x) for pair in values.items() for x in pair])[F.col("estimator")]
    return X.fit_inverse_k(X.moments(flat_runs(spark)), "scaled_error").withColumn("theory", known(THEORY)).withColumn("theory_c1", known(NEXT))


@query("simulated_error_constants")
def _(spark, d):
    return X.moments(flat_runs(spark)).select("k", "estimator", "runs", "scaled_error")


@query("simulated_bias_constants")
def _(spark, d):
    return X.moments(flat_runs(spark)).select("k", "estimator", "runs", "scaled_bias")


@query("inverse_k_fit")
def _(spark, d):
    return fitted(spark)


@query("digits_uncertain")
def _(spark, d):
    """How many digits of each limit the flat part fixes, by its disjoint stretches."""
    return X.digits_uncertain(flat_runs(spark), *FLAT)


@query("digits_match")
def _(spark, d):
    """How many digits of each measured limit agree with theory."""
    return fitted(spark).where("theory is not null").select("estimator", "c0", "theory", (-F.log10(F.abs(F.col("c0") / F.col("theory") - 1))).alias("digits"))


def curve(runs, *by):
    r = F.col("estimate") / F.col("n") - 1
    return runs.groupBy("n", "estimator", *by).agg(F.sqrt(F.avg(r * r)).alias("error"), F.count("*").alias("runs"))


@query("error_curve_simulated")
def _(spark, d):
    """Scaled error against n for six estimators, k = 512: the ordering of the methods, from small counts to the flat part."""
    return curve(X.simulate(spark, (512,), 200, -4, 12, 17)).select("n", "estimator", (F.sqrt(F.lit(512.0)) * F.col("error")).alias("scaled_error"))


MATCHED = {"summary": ("count_inverse", "register"), "code_length": ("code_length", "register_code_length"), "history": ("history", "register_history")}


@query("matched_space_simulated")
def _(spark, d):
    """Errors of a matrix of 2^15 rows and of registers of 2^16, which take about the same compressed space, for counts from 2^6 to
    2^26: three pairs of methods and the ratio of their errors."""
    kind = F.create_map(*[F.lit(x) for name, pair in MATCHED.items() for e in pair for x in (e, name)])[F.col("estimator")]
    runs = X.simulate(spark, (1 << 15,), 24, -9, 11, 11).where(F.col("estimator").isin([m for m, _ in MATCHED.values()]))
    runs = runs.union(X.simulate(spark, (1 << 16,), 24, -10, 10, 11, seed=2).where(F.col("estimator").isin([r for _, r in MATCHED.values()])))
    both = curve(runs, "k").withColumn("kind", kind).groupBy("kind", "n")
    out = both.agg(F.max(F.when(F.col("k") == 1 << 15, F.col("error"))).alias("matrix"), F.max(F.when(F.col("k") == 1 << 16, F.col("error"))).alias("registers"))
    return out.withColumn("ratio", F.col("registers") / F.col("matrix"))


@query("space_at_prefixes")
def _(spark, d):
    """Compressed bytes of the matrix (2^15 rows) and of registers (2^16) after growing prefixes of ``lineitem``, and their share of the rows."""
    li, ks = table(spark, d, "lineitem"), {"window_zstd": 1 << 15, "register_zstd": 1 << 16}
    order = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity", "l_shipdate", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]
    marks = spark.createDataFrame([(1 << e,) for e in range(8, 28, 2)], "upto long")
    longest = li.groupBy().agg(F.max("l_orderkey").alias("last"))
    out = None
    for codec, k in ks.items():
        first = state.first_arrivals(li, order, ["l_orderkey"], (), k)
        near = marks.crossJoin(F.broadcast(longest)).where(F.col("upto") <= F.col("last"))
        words = first.join(F.broadcast(near), F.col("first_pos.l_orderkey") <= F.col("upto")).groupBy("upto", "row_id").agg(F.bit_or(H.shift_left(F.lit(1).cast("bigint"), F.col("col_id") - 1)).alias("word"))
        part = sketch_store.unpacked_size(words, ["upto"], k, C.encode_window if codec == "window_zstd" else lambda w: C.encode_register_zstd(C.registers_of(w)))
        part = part.select("upto", F.lit(codec).alias("codec"), F.lit(k).alias("k"), "coupons", "size", (8 * F.col("size") / k).alias("bits_per_row"))
        out = part if out is None else out.union(part)
    return out


@query("small_n_simulation")
def _(spark, d):
    """n = 64, k = 512 by real draws."""
    return X.moments(X.simulate_direct(spark, 512, 64, 20000)).select("k", "estimator", "runs", "scaled_error")


IDS = {"parts": ["l_partkey"], "orders": ["l_orderkey"], "lines": ["l_orderkey", "l_linenumber"]}


def table_sizes(spark, d, k, measure):
    """(ids, k, n_over_k, codec, bits_per_row) of the states that ``lineitem`` leaves for three kinds of ids."""
    li, states, counts = table(spark, d, "lineitem"), None, None
    for name, ids in IDS.items():
        words = state.row_words(li, ids, k=k).select(F.lit(name).alias("ids"), "row_id", "word")
        n = li.groupBy().agg(F.count_distinct(*ids).alias("n")).select(F.lit(name).alias("name"), (F.col("n") / k).alias("ratio"))
        states, counts = (words, n) if states is None else (states.union(words), counts.union(n))

    def run(g: pd.DataFrame) -> pd.DataFrame:
        words = np.zeros(k, np.int64)
        words[g["row_id"]] = g["word"]
        found = list(measure(words))
        return pd.DataFrame({"ids": g["ids"].iloc[0], "codec": [name for name, _ in found], "bits_per_row": [bits / k for _, bits in found]})

    out = states.groupBy("ids").applyInPandas(run, "ids string, codec string, bits_per_row double")
    return out.join(F.broadcast(counts), F.col("ids") == F.col("name")).select("ids", F.lit(k).cast("long").alias("k"), F.col("ratio").alias("n_over_k"), "codec", "bits_per_row")


def all_codecs(words):
    for name, (encode, _) in C.CODECS.items():
        yield name, 8 * len(encode(words))
    regs = C.registers_of(words)
    for name, (encode, _) in C.REGISTER_CODECS.items():
        yield name, 8 * len(encode(regs))


@query("codec_sizes")
def _(spark, d):
    return table_sizes(spark, d, 4096, all_codecs)


def variants(words):
    for name, options in (("window", {}), ("no_rotation", {"rotate": False}), ("row_major", {"by_column": False}), ("level_3", {"level": 3}), ("level_9", {"level": 9})):
        yield name, 8 * len(C.encode_window(words, **options))


@query("codec_ablation")
def _(spark, d):
    return table_sizes(spark, d, 32768, variants)


@query("bits_report")
def _(spark, d):
    """Bits per row of states of ``lineitem``, and per row of a register sketch of twice the rows, beside the entropies."""
    s = table_sizes(spark, d, 32768, lambda w: (("window_zstd", 8 * len(C.encode_window(w))), ("register_zstd", 8 * len(C.encode_register_zstd(C.registers_of(w))))))
    return s.withColumn("normalised", F.when(F.col("codec") == "window_zstd", F.col("bits_per_row") / 2).otherwise(F.col("bits_per_row"))).withColumn("entropy", F.when(F.col("codec") == "window_zstd", 4.699204337).otherwise(2.831952664))
