"""Queries of the other ways in and out: Arrow path, table functions, data source, general laws."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from couponspark.functions import udtf
from couponspark.functions.hashing import PORTABLE_COLUMNS
from couponspark.operators import packed, state
from couponspark.operators.law import CouponLaw
from couponspark.operators.simulate import moments
from couponspark.sources import simulation_source, sketch_store

from . import sqlgen as G
from .registry import query, table
from .sketches import K, P

_EV = G.collected(G.words(G.source("events", ["user_id"], ["event_type"]), ["event_type"]), ["event_type"])


@query("packed_path_equals_native", _EV)
def _(spark, d):
    parts = packed.partial_sketches(table(spark, d, "events"), "user_id", "event_type", K, "portable")
    return state.collected(sketch_store.unpack(packed.merge_bodies(parts, ["event_type"]), ["event_type"]), ["event_type"])


@query("partition_history", G.history(G.arrivals(G.source("orders", ["o_custkey"], extra=["o_orderkey"]), "o_orderkey")))
def _(spark, d):
    """The Arrow path of the history: one partition in order equals the window over first arrivals."""
    one = table(spark, d, "orders").select("o_orderkey", "o_custkey").repartition(1).sortWithinPartitions("o_orderkey")
    return packed.partition_histories(one, "o_custkey", K, "portable").select("coupons", F.round("estimate", 4).alias("estimate"))


@query("udtf_unpack", G.coupons(G.source("orders", ["o_custkey"])))
def _(spark, d):
    udtf.register(spark)
    w = state.row_words(table(spark, d, "orders"), "o_custkey", **P)
    sketch_store.pack(w.withColumn("g", F.lit(1)), ["g"], K, PORTABLE_COLUMNS).createOrReplaceTempView("cm_packed")
    return spark.sql("SELECT u.row_id, u.col_id FROM cm_packed, LATERAL unpack_sketch(body) u")


@query("data_source_runs")
def _(spark, d):
    """Errors to expect at the numbers of orders that ``lineitem`` has by return flag, from runs of the data source at those counts."""
    simulation_source.register(spark)
    counts = table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_orderkey").cast("double").alias("n")).where("n > 0")
    points = sorted({r.n for r in counts.select("n").collect()})
    runs = spark.read.format("coupon_runs").option("k", "64").option("trials", "60").option("points", ",".join(map(repr, points)) or "1").load()
    return moments(runs.join(F.broadcast(counts), "n"), ["l_returnflag", "n"])


@query("generic_law_estimates")
def _(spark, d):
    """Three laws on the same ids: a bitmap, the matrix, and a law of two classes; count-inverse and code-length on each."""
    laws = {"bitmap": CouponLaw.bitmap(4096), "matrix": CouponLaw.matrix(K, PORTABLE_COLUMNS), "two_classes": CouponLaw((1024, 1024), (0.75 / 1024, 0.25 / 1024))}
    ids = table(spark, d, "orders").select("o_custkey").distinct()
    _, lo = state.H.portable_pair("o_custkey")
    hi, _ = state.H.portable_pair("o_custkey")
    cells = {"bitmap": F.struct(F.lit(0).alias("c"), (lo % 4096).alias("i")), "matrix": F.struct((state.H.leading_column(hi) - 1).alias("c"), (lo % K).alias("i")), "two_classes": F.struct(F.when(hi % 4 == 0, 1).otherwise(0).alias("c"), (lo % 1024).alias("i"))}
    pairs = F.explode(F.array(*[F.struct(F.lit(n).alias("law"), c["c"].cast("int").alias("class_id"), c["i"].cast("long").alias("cell")) for n, c in cells.items()]))
    counts = ids.select(pairs.alias("x")).select("x.*").distinct().groupBy("law", "class_id").count()

    def solve(g: pd.DataFrame) -> pd.DataFrame:
        law = laws[g["law"].iloc[0]]
        s = np.zeros(len(law.cells), int)
        s[g["class_id"]] = g["count"]
        return pd.DataFrame({"law": [g["law"].iloc[0]], "coupons": [int(s.sum())], "count_inverse": [law.count_inverse(s.sum())], "code_length": [law.code_length(tuple(s))]})

    return counts.groupBy("law").applyInPandas(solve, "law string, coupons long, count_inverse double, code_length double")
