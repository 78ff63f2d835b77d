"""Queries on hashing, sketch state, estimators and baselines (portable profile, k = 1024)."""

from __future__ import annotations

from pyspark.sql import functions as F

from couponspark.functions import hashing as H
from couponspark.functions import solvers as S
from couponspark.operators import estimate as E
from couponspark.operators import state

from . import sqlgen as G
from .registry import query, table

K, J = 1024, H.PORTABLE_COLUMNS
P = {"k": K, "profile": "portable"}
CUST = G.source("orders", ["o_custkey"])
CUST_ORDERED = G.source("orders", ["o_custkey"], extra=["o_orderkey"])
WORDS = G.words(CUST)
ARRIVALS = G.arrivals(CUST_ORDERED, "o_orderkey")
FLAGS = ("l_returnflag", "l_linestatus")
#: A total order of lineitem: the key columns alone repeat.
LINE_ORDER = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity", "l_shipdate", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]
LINE_POS = "row(" + ", ".join(LINE_ORDER) + ")"
PAIR = ["l_partkey", "l_suppkey"]


def orders(spark, d):
    return table(spark, d, "orders")


def words(spark, d):
    return state.row_words(orders(spark, d), "o_custkey", **P)


def arrivals(spark, d):
    return state.first_arrivals(orders(spark, d), "o_custkey", ["o_orderkey"], **P)


def rounded(df, *cols, digits=4):
    for c in cols:
        df = df.withColumn(c, F.round(F.col(c), digits))
    return df


# ---- hashing and state

@query("coupon_extract", f"SELECT o_orderkey, row_id, col_id FROM ({G.coupon_rows(CUST_ORDERED, extra=['o_orderkey'])})")
def _(spark, d):
    rows = state.coupon_rows(orders(spark, d), "o_custkey", extra=["o_orderkey"], **P)
    return rows.select("o_orderkey", "row_id", H.column_number(F.col("bit")).alias("col_id"))


@query("coupon_set", G.coupons(CUST))
def _(spark, d):
    return state.coupons(orders(spark, d), "o_custkey", **P)


@query("row_words", WORDS)
def _(spark, d):
    return words(spark, d)


@query("collected_count", G.collected(WORDS))
def _(spark, d):
    return state.collected(words(spark, d))


@query("column_occupancy", f"SELECT col_id, count(*) AS cnt FROM ({G.coupons(CUST)}) GROUP BY col_id")
def _(spark, d):
    o = state.occupancy(words(spark, d), columns=J).select(F.posexplode("occupancy").alias("p", "cnt"))
    return o.where("cnt > 0").select((F.col("p") + 1).cast("int").alias("col_id"), "cnt")


@query("register_view", G.registers(WORDS))
def _(spark, d):
    return state.registers(words(spark, d))


@query("register_direct", f"SELECT row_id, max(col_id) AS reg FROM ({G.coupon_rows(CUST)}) GROUP BY row_id")
def _(spark, d):
    return state.registers_direct(orders(spark, d), "o_custkey", **P)


@query("register_hist", f"SELECT reg, count(*) AS cnt FROM ({G.registers(WORDS)}) GROUP BY reg UNION ALL SELECT 0, {K} - count(*) FROM ({WORDS})")
def _(spark, d):
    h = state.register_histogram(state.registers(words(spark, d)), k=K, columns=J).select(F.posexplode("hist").alias("reg", "cnt"))
    return h.where("cnt > 0 or reg = 0")


HALVES = [G.source("orders", ["o_custkey"], where=f"o_orderkey % 2 = {i}") for i in (0, 1)]


@query("register_merge", f"SELECT row_id, max(reg) AS reg FROM (SELECT * FROM ({G.registers(G.words(HALVES[0]))}) UNION ALL SELECT * FROM ({G.registers(G.words(HALVES[1]))})) GROUP BY row_id")
def _(spark, d):
    halves = [state.registers_direct(orders(spark, d).where(f"o_orderkey % 2 = {i}"), "o_custkey", **P) for i in (0, 1)]
    return state.merge_registers(*halves)


@query("register_saturation_equal", f"SELECT row_id, max(col_id) AS reg FROM ({G.coupon_rows(G.source('orders', ['o_orderkey']), k=16)}) GROUP BY row_id")
def _(spark, d):
    o, p = orders(spark, d), {"k": 16, "profile": "portable"}
    old = state.registers_direct(o.where("o_orderkey % 2 = 0"), "o_orderkey", **p)
    row = old.agg(F.count("*").alias("n"), F.min("reg").alias("low")).first()
    floor = row["low"] if row["n"] == 16 else 0
    return state.merge_registers(old, state.registers_direct(o, "o_orderkey", floor=floor, **p))


@query("leftmost_gap", f"SELECT row_id, bit_count(word & ~(word + 1))::INTEGER AS gap FROM ({WORDS})")
def _(spark, d):
    return words(spark, d).select("row_id", S.leftmost_gap(F.col("word")).cast("int").alias("gap"))


@query("first_arrivals", ARRIVALS)
def _(spark, d):
    return arrivals(spark, d).select("row_id", "col_id", F.col("first_pos.o_orderkey").alias("first_pos"))


@query("merge_equals_concat", WORDS)
def _(spark, d):
    halves = [state.row_words(orders(spark, d).where(f"o_orderkey % 2 = {i}"), "o_custkey", **P) for i in (0, 1)]
    return state.merge(*halves)


@query("downsize_equals_direct", G.words(CUST, k=256))
def _(spark, d):
    return state.downsize(words(spark, d), 256)


@query("saturation_filter_equal", G.words(G.source("orders", ["o_orderkey"]), k=16))
def _(spark, d):
    o, p = orders(spark, d), {"k": 16, "profile": "portable"}
    old = state.row_words(o.where("o_orderkey % 2 = 0"), "o_orderkey", **p)
    return state.merge(old, state.row_words(o, "o_orderkey", floor=state.saturation_floor(old, 16), **p))


@query("null_ids_ignored", G.collected(G.words(G.source("(SELECT CASE WHEN o_orderkey % 3 = 0 THEN NULL ELSE o_custkey END AS c FROM orders)", ["c"]))))
def _(spark, d):
    o = orders(spark, d).select(F.when(F.col("o_orderkey") % 3 != 0, F.col("o_custkey")).alias("c"))
    return state.collected(state.row_words(o, "c", **P))


@query("filtered_sketch", G.count_inverse(G.collected(G.words(G.source("orders", ["o_custkey"], where="o_orderstatus = 'F'")))))
def _(spark, d):
    o = orders(spark, d).where("o_orderstatus = 'F'")
    return rounded(E.est_count_inverse(state.row_words(o, "o_custkey", **P), k=K, columns=J), "estimate", digits=2)


@query("generic_law_bitmap", f"SELECT count(*) AS coupons, round(CASE WHEN count(*) < {K} THEN {K} * ln({float(K)} / ({K} - count(*))) END, 4) AS estimate FROM (SELECT DISTINCT row_id FROM ({G.coupon_rows(CUST)}))")
def _(spark, d):
    """A law of k equal classes: the plain bitmap."""
    c = words(spark, d).agg(F.count("*").alias("coupons"))
    return rounded(c.select("coupons", S.bitmap_log(F.col("coupons"), K).alias("estimate")), "estimate")


# ---- estimators on the matrix

@query("est_count_inverse", G.count_inverse(G.collected(WORDS)))
def _(spark, d):
    return rounded(E.est_count_inverse(words(spark, d), k=K, columns=J), "estimate", digits=2)


@query("est_count_inverse_poisson", G.count_inverse(G.collected(WORDS), poisson=True))
def _(spark, d):
    return rounded(E.est_count_inverse(words(spark, d), k=K, columns=J, poisson=True), "estimate", digits=2)


@query("est_count_inverse_asym", f"SELECT coupons, round({S.GROWTH_CONSTANT * K!r} * pow(2, coupons / {float(K)}), 4) AS estimate FROM ({G.collected(G.words(G.source('lineitem', PAIR)))})")
def _(spark, d):
    c = state.collected(state.row_words(table(spark, d, "lineitem"), PAIR, **P))
    return rounded(c.select("coupons", S.count_inverse_asymptotic(F.col("coupons"), K).alias("estimate")), "estimate")


@query("count_inverse_lookup", G.count_inverse(G.collected(G.words(G.source("lineitem", ["l_partkey"], FLAGS), FLAGS), FLAGS), FLAGS))
def _(spark, d):
    counts = state.collected(state.row_words(table(spark, d, "lineitem"), "l_partkey", FLAGS, **P), FLAGS)
    out = E.lookup_count_inverse(counts, E.count_inverse_table(spark, K, J), K)
    return rounded(out.select(*FLAGS, "coupons", "estimate"), "estimate", digits=2)


@query("est_count_inverse_by_group", G.count_inverse(G.collected(G.words(G.source("lineitem", PAIR, FLAGS), FLAGS), FLAGS), FLAGS))
def _(spark, d):
    w = state.row_words(table(spark, d, "lineitem"), PAIR, FLAGS, **P)
    return rounded(E.est_count_inverse(w, FLAGS, K, J), "estimate", digits=2)


@query("est_code_length", G.code_length(G.occupancy(WORDS)))
def _(spark, d):
    return rounded(E.est_code_length(words(spark, d), k=K, columns=J).drop("occupancy"), "estimate", digits=2)


@query("est_code_length_by_group", G.code_length(G.occupancy(G.words(G.source("lineitem", PAIR, FLAGS), FLAGS), FLAGS), FLAGS, digits=1))
def _(spark, d):
    w = state.row_words(table(spark, d, "lineitem"), PAIR, FLAGS, **P)
    return rounded(E.est_code_length(w, FLAGS, K, J).drop("occupancy"), "estimate", digits=1)


GUESSES = [1000, 1200, 1400, 1450, 1500, 1550, 1600, 1800, 2000]
_CELL = f"SELECT guess, round(sum(CASE WHEN c.col_id IS NULL THEN -guess * l / ln(2) ELSE -ln(1 - exp(guess * l)) / ln(2) END), 3) AS bits FROM (SELECT unnest({GUESSES}) AS guess) g, (SELECT r::INTEGER AS row_id, j::INTEGER AS col_id, ({G.doubles(S.log_rest(K, J))})[j] AS l FROM range(0, {K}) a(r), range(1, {J + 1}) b(j)) cell LEFT JOIN ({G.coupons(CUST)}) c USING (row_id, col_id) GROUP BY guess"


@query("code_length_grid", _CELL.replace("guess, round", "guess::BIGINT AS guess, round").replace("GROUP BY guess", "GROUP BY 1").replace("-guess * l", "-g.guess * l").replace("exp(guess * l)", "exp(g.guess * l)").replace("guess::BIGINT AS guess", "g.guess::BIGINT AS guess"))
def _(spark, d):
    """The code length cell by cell, for some guesses: what the column sums stand for."""
    cells = spark.range(K).select(F.col("id").cast("int").alias("row_id"), F.posexplode(S.literal(S.log_rest(K, J))).alias("p", "l"))
    cells = cells.select("row_id", (F.col("p") + 1).cast("int").alias("col_id"), "l")
    got = state.coupons(orders(spark, d), "o_custkey", **P).withColumn("hit", F.lit(True))
    guesses = spark.createDataFrame([(g,) for g in GUESSES], "guess long")
    all_ = cells.join(got, ["row_id", "col_id"], "left").crossJoin(F.broadcast(guesses))
    bits = F.when(F.col("hit"), -F.log(-F.expm1(F.col("guess") * F.col("l")))).otherwise(-F.col("guess") * F.col("l")) / F.log(F.lit(2.0))
    return all_.groupBy("guess").agg(F.round(F.sum(bits), 3).alias("bits"))


@query("ideal_space", f"SELECT coupons, round(list_sum(list_transform(range(1, {J + 1}), lambda j: -(CASE WHEN occ[j] = 0 THEN 0 ELSE occ[j] * ln(1 - exp(1500 * ({G.doubles(S.log_rest(K, J))})[j])) END + ({K} - occ[j]) * 1500 * ({G.doubles(S.log_rest(K, J))})[j]) / ln(2))), 3) AS bits FROM ({G.occupancy(WORDS)})")
def _(spark, d):
    o = state.occupancy(words(spark, d), columns=J)
    return o.select("coupons", F.round(S.ideal_space_bits(F.col("occupancy"), F.lit(1500.0), K, J), 3).alias("bits"))


@query("est_history", G.history(ARRIVALS))
def _(spark, d):
    return rounded(E.est_history(arrivals(spark, d), k=K, columns=J), "estimate")


@query("est_history_by_group", G.history(f"SELECT {', '.join(FLAGS)}, row_id, col_id, min(pos) AS first_pos FROM ({G.coupon_rows(f'SELECT l_returnflag, l_linestatus, {LINE_POS} AS pos, l_partkey::VARCHAR AS id FROM lineitem', FLAGS, extra=['pos'])}) GROUP BY ALL", FLAGS))
def _(spark, d):
    a = state.first_arrivals(table(spark, d, "lineitem"), "l_partkey", LINE_ORDER, FLAGS, **P)
    return rounded(E.est_history(a, FLAGS, K, J), "estimate")


@query("history_ordered_merge", G.history(ARRIVALS))
def _(spark, d):
    halves = [state.first_arrivals(orders(spark, d).where(f"o_orderkey % 2 = {i}"), "o_custkey", ["o_orderkey"], **P) for i in (0, 1)]
    return rounded(E.est_history(state.merge_first_arrivals(*halves), k=K, columns=J), "estimate")


SUPP3 = f"SELECT DISTINCT lo % {3 * K} AS cell FROM (SELECT ('0x' || substr(md5(l_suppkey::VARCHAR), 18, 15))::BIGINT AS lo FROM lineitem)"


@query("est_triple_bitmap", f"SELECT coupons, round({G.harmonic('coupons', 3 * K)}, 4) AS estimate FROM (SELECT count(*) AS coupons FROM ({SUPP3}))")
def _(spark, d):
    """3k equal cells, for counts far below k."""
    _, lo = H.portable_pair("l_suppkey")
    c = table(spark, d, "lineitem").select((lo % (3 * K)).alias("cell")).distinct().agg(F.count("*").alias("coupons"))
    return rounded(c.select("coupons", S.harmonic_rest(F.col("coupons"), 3 * K).alias("estimate")), "estimate")


# ---- baselines

@query("est_register", G.register(G.registers(WORDS)))
def _(spark, d):
    return rounded(E.est_register(state.registers(words(spark, d)), k=K), "estimate")


@query("est_register_code_length", G.register_code_length(G.registers(WORDS)))
def _(spark, d):
    return rounded(E.est_register_code_length(state.registers(words(spark, d)), k=K, columns=J), "estimate", digits=2)


@query("est_register_history", G.register_history(ARRIVALS))
def _(spark, d):
    return rounded(E.est_register_history(arrivals(spark, d), k=K, columns=J), "estimate")


@query("est_leftmost_gap", G.leftmost_gap(WORDS))
def _(spark, d):
    return rounded(E.est_leftmost_gap(words(spark, d), k=K), "estimate")


BITMAP = f"SELECT count(DISTINCT row_id) AS coupons FROM ({G.coupon_rows(CUST)})"


@query("est_bitmap_harmonic", f"SELECT coupons, round({G.harmonic('coupons', K)}, 4) AS estimate FROM ({BITMAP})")
def _(spark, d):
    c = words(spark, d).agg(F.count("*").alias("coupons"))
    return rounded(c.select("coupons", S.harmonic_rest(F.col("coupons"), K).alias("estimate")), "estimate")


@query("est_bitmap_log", f"SELECT coupons, round(CASE WHEN coupons < {K} THEN {K} * ln({float(K)} / ({K} - coupons)) END, 4) AS estimate FROM ({BITMAP})")
def _(spark, d):
    c = words(spark, d).agg(F.count("*").alias("coupons"))
    return rounded(c.select("coupons", S.bitmap_log(F.col("coupons"), K).alias("estimate")), "estimate")


@query("hybrid_history", G.hybrid_history(ARRIVALS))
def _(spark, d):
    return rounded(E.est_hybrid_history(arrivals(spark, d), k=K, columns=J), "estimate")


EVENT_WORDS = G.words(G.source("events", ["user_id"], ["event_type"]), ["event_type"])


@query("hybrid_estimate", f"SELECT event_type, CASE WHEN a.estimate < {0.1 * K} THEN a.estimate ELSE b.estimate END AS estimate FROM ({G.count_inverse(G.collected(EVENT_WORDS, ['event_type']), ['event_type'])}) a JOIN ({G.register(G.registers(EVENT_WORDS, ['event_type']), ['event_type'], digits=2)}) b USING (event_type)")
def _(spark, d):
    w = state.row_words(table(spark, d, "events"), "user_id", ["event_type"], **P)
    return rounded(E.est_hybrid(w, ["event_type"], K, J), "estimate", digits=2)


NULLED = "(SELECT *, CASE WHEN event_type <> 'click' THEN event_type END AS kind FROM events)"
NULL_WORDS = G.words(G.source(NULLED, ["user_id"], ["kind"]), ["kind"])


def nulled(spark, d):
    return table(spark, d, "events").withColumn("kind", F.when(F.col("event_type") != "click", F.col("event_type")))


@query("hybrid_estimate_null_group", f"SELECT kind, CASE WHEN a.estimate < {0.1 * K} THEN a.estimate ELSE b.estimate END AS estimate FROM ({G.count_inverse(G.collected(NULL_WORDS, ['kind']), ['kind'])}) a JOIN (SELECT kind AS g, estimate FROM ({G.register(G.registers(NULL_WORDS, ['kind']), ['kind'], digits=2)})) b ON a.kind IS NOT DISTINCT FROM b.g")
def _(spark, d):
    """Groups with a null key are groups as all others."""
    w = state.row_words(nulled(spark, d), "user_id", ["kind"], **P)
    return rounded(E.est_hybrid(w, ["kind"], K, J), "estimate", digits=2)


@query("hybrid_history_null_group", f"SELECT CASE WHEN g <> 'none' THEN g END AS kind, estimate, matrix_coupons FROM ({' UNION ALL '.join('SELECT ' + repr(g) + ' AS g, * FROM (' + G.hybrid_history(G.arrivals(G.source(NULLED, ['user_id'], extra=['event_id'], where=w), 'event_id')) + ')' for g, w in (('none', 'kind IS NULL'), ('view', "kind = 'view'")))})")
def _(spark, d):
    a = state.first_arrivals(nulled(spark, d).where("kind is null or kind = 'view'"), "user_id", ["event_id"], ["kind"], **P)
    return rounded(E.est_hybrid_history(a, ["kind"], K, J), "estimate")


@query("exact_distinct", "SELECT count(DISTINCT o_custkey) AS n, count(DISTINCT o_orderkey) AS n_orders FROM orders")
def _(spark, d):
    return orders(spark, d).agg(F.count_distinct("o_custkey").alias("n"), F.count_distinct("o_orderkey").alias("n_orders"))


@query("exact_distinct_by_group", "SELECT l_returnflag, l_linestatus, count(DISTINCT (l_partkey, l_suppkey)) AS n FROM lineitem GROUP BY ALL")
def _(spark, d):
    return table(spark, d, "lineitem").groupBy(*FLAGS).agg(F.count_distinct(*PAIR).alias("n"))


@query("builtin_comparison")
def _(spark, d):
    """Spark's own sketches beside ours, on pairs."""
    li = table(spark, d, "lineitem")
    ours = E.est_count_inverse(state.row_words(li, PAIR, k=4096), k=4096)
    theirs = li.agg(F.approx_count_distinct(F.struct(*PAIR)).alias("builtin_approx"), F.hll_sketch_estimate(F.hll_sketch_agg(F.concat_ws("|", *PAIR))).alias("builtin_sketch"), F.expr("theta_sketch_estimate(theta_sketch_agg(concat_ws('|', l_partkey, l_suppkey)))").alias("builtin_theta"), F.count_distinct(*PAIR).alias("exact"))
    return theirs.crossJoin(ours.select("estimate"))


@query("fast_profile_accuracy")
def _(spark, d):
    """The production profile against the truth in five groups."""
    ev = table(spark, d, "events")
    ours = E.est_count_inverse(state.row_words(ev, ["user_id", "props"], ["event_type"], k=4096), ["event_type"], 4096)
    exact = ev.groupBy(F.col("event_type").alias("kind")).agg(F.count_distinct("user_id", "props").alias("exact"))
    return ours.join(exact, F.col("event_type").eqNullSafe(F.col("kind"))).select("event_type", "estimate", "exact", (F.col("estimate") / F.col("exact") - 1).alias("relative_error"))


# ---- workloads: accuracy on the tables

def replicate(df, seeds):
    """Every row under each seed: independent runs over one table."""
    return df.crossJoin(F.broadcast(df.sparkSession.range(seeds).select(F.col("id").cast("string").alias("seed"))))


def seeded(table_: str, ids, seeds: int, where="TRUE") -> str:
    inner = G.rendered(*ids)
    return f"SELECT s::VARCHAR AS seed, concat_ws('|', s::VARCHAR, {inner}) AS id FROM (SELECT * FROM {table_} WHERE {where}), range({seeds}) t(s)"


SEEDED = G.words(seeded("orders", ["o_custkey"], 32), ["seed"])


@query("replicate_rmse", f"SELECT count(*) AS runs, round(avg(estimate), 2) AS mean, round(sqrt(avg(pow(estimate - n, 2))) / any_value(n), 5) AS standard_error, round(sqrt({K}) * sqrt(avg(pow(estimate - n, 2))) / any_value(n), 4) AS scaled FROM ({G.count_inverse(G.collected(SEEDED, ['seed']), ['seed'], digits=6)}), (SELECT count(DISTINCT o_custkey) AS n FROM orders)")
def _(spark, d):
    o = orders(spark, d).select("o_custkey").distinct()
    est = E.est_count_inverse(state.row_words(replicate(o, 32), "o_custkey", ["seed"], seed=F.col("seed"), **P), ["seed"], K, J)
    n = orders(spark, d).agg(F.count_distinct("o_custkey").cast("double").alias("truth"))
    acc = E.accuracy(est.withColumn("estimate", F.round("estimate", 6)).crossJoin(F.broadcast(n)).withColumn("one", F.lit(1)), "estimate", "truth", ["one"])
    return acc.select(F.col("n").alias("runs"), F.round(F.col("bias") + F.col("mean_truth"), 2).alias("mean"), F.round("standard_error", 5).alias("standard_error"), F.round(F.sqrt(F.lit(float(K))) * F.col("standard_error"), 4).alias("scaled"))


FIRST64 = "(SELECT o_custkey FROM orders GROUP BY o_custkey ORDER BY min(o_orderkey) LIMIT 64)"
SMALL = G.words(seeded(FIRST64, ["o_custkey"], 200), ["seed"], 512)


@query("small_n_ratio", f"SELECT round(sqrt(512) * sqrt(avg(pow(a.estimate - 64, 2))) / 64, 4) AS matrix, round(sqrt(512) * sqrt(avg(pow(b.estimate - 64, 2))) / 64, 4) AS registers FROM ({G.count_inverse(G.collected(SMALL, ['seed']), ['seed'], 512, digits=6)}) a JOIN ({G.register(G.registers(SMALL, ['seed']), ['seed'], 512, digits=6)}) b USING (seed)")
def _(spark, d):
    """The first 64 distinct ids under many seeds, k = 512: matrix and registers."""
    ids = orders(spark, d).groupBy("o_custkey").agg(F.min("o_orderkey").alias("first")).orderBy("first").limit(64).select("o_custkey")
    w = state.row_words(replicate(ids, 200), "o_custkey", ["seed"], 512, "portable", seed=F.col("seed"))
    a = E.est_count_inverse(w, ["seed"], 512, J).select("seed", F.round("estimate", 6).alias("a"))
    b = E.est_register(state.registers(w, ["seed"]), ["seed"], 512).select("seed", F.round("estimate", 6).alias("b"))
    scaled = lambda c: F.round(F.sqrt(F.lit(512.0)) * F.sqrt(F.avg((F.col(c) - 64) * (F.col(c) - 64))) / 64, 4)
    return a.join(b, "seed").agg(scaled("a").alias("matrix"), scaled("b").alias("registers"))


_CURVE_SRC = f"SELECT pos, row_id, col_id FROM ({G.coupon_rows('SELECT row_number() OVER (ORDER BY ' + ', '.join(LINE_ORDER) + ') AS pos, l_partkey::VARCHAR AS id FROM lineitem', extra=['pos'])})"
_FIRST = f"SELECT row_id, col_id, min(pos) AS first_pos FROM ({_CURVE_SRC}) GROUP BY ALL"
_STEPS = G.history_steps(_FIRST)


@query("error_curve_prefix", f"WITH cp AS (SELECT (1::BIGINT << i) AS upto FROM range(0, 40) t(i) WHERE (1::BIGINT << i) <= (SELECT count(*) FROM lineitem)), ids AS (SELECT min(pos) AS pos FROM (SELECT row_number() OVER (ORDER BY {', '.join(LINE_ORDER)}) AS pos, l_partkey FROM lineitem) GROUP BY l_partkey) SELECT upto, (SELECT count(*) FROM ids WHERE pos <= upto) AS exact, count(*) AS coupons, round(sum(step), 4) AS history FROM cp, ({_STEPS}) s WHERE first_pos <= upto GROUP BY upto")
def _(spark, d):
    """Exact count, coupons and history estimate at power-of-two prefixes, from one pass over first arrivals."""
    from pyspark.sql import Window

    li = table(spark, d, "lineitem").select("l_partkey", *[c for c in LINE_ORDER if c != "l_partkey"])
    n = li.count()
    # positions: range partitions, their sizes, then a number in each (no global window)
    ranged = li.repartitionByRange(*LINE_ORDER).withColumn("part", F.spark_partition_id())
    local = ranged.withColumn("i", F.row_number().over(Window.partitionBy("part").orderBy(*LINE_ORDER))).select("part", "i", "l_partkey")
    sizes = ranged.groupBy("part").count()
    before = sizes.alias("a").join(sizes.alias("b"), F.col("b.part") < F.col("a.part"), "left").groupBy("a.part").agg(F.coalesce(F.sum("b.count"), F.lit(0)).alias("base"))
    pos = local.join(F.broadcast(before), "part").select((F.col("base") + F.col("i")).alias("pos"), "l_partkey")
    steps = E.history_steps(state.first_arrivals(pos, "l_partkey", ["pos"], **P), (), K, J).select(F.col("first_pos.pos").alias("pos"), "step", F.lit(1).alias("coupon"), F.lit(0).alias("id"))
    ids = pos.groupBy("l_partkey").agg(F.min("pos").alias("pos")).select("pos", F.lit(0.0).alias("step"), F.lit(0).alias("coupon"), F.lit(1).alias("id"))
    marks = spark.createDataFrame([(1 << i,) for i in range(n.bit_length()) if 1 << i <= n], "upto long")
    return steps.union(ids).join(F.broadcast(marks), F.col("pos") <= F.col("upto")).groupBy("upto").agg(F.sum("id").alias("exact"), F.sum("coupon").alias("coupons"), F.round(F.sum("step"), 4).alias("history"))


@query("accuracy_matched_space", f"SELECT count(*) AS runs, round(sqrt(avg(pow(a.estimate / n - 1, 2))), 5) AS matrix, round(sqrt(avg(pow(b.estimate / n - 1, 2))), 5) AS registers FROM ({G.count_inverse(G.collected(G.words(seeded('(SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)', PAIR, 8), ['seed'], 512), ['seed']), ['seed'], 512, digits=4)}) a JOIN ({G.register(G.registers(G.words(seeded('(SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)', PAIR, 8), ['seed'], 1024), ['seed']), ['seed'], 1024)}) b USING (seed), (SELECT count(DISTINCT (l_partkey, l_suppkey))::DOUBLE AS n FROM lineitem)")
def _(spark, d):
    """A matrix of k rows against registers of 2k, which take about the same compressed space."""
    pairs = table(spark, d, "lineitem").select(*PAIR).distinct()
    # as the SQL: the id is the text of the pair behind the seed
    ids = replicate(pairs.select(F.concat_ws("|", *PAIR).alias("p")), 8)
    w1 = state.row_words(ids, "p", ["seed"], 512, "portable", seed=F.col("seed"))
    w2 = state.registers_direct(ids.withColumn("sp", F.concat_ws("|", "seed", "p")), "sp", ["seed"], 1024, "portable")
    a = E.est_count_inverse(w1, ["seed"], 512, J).select("seed", F.round("estimate", 4).alias("a"))
    b = E.est_register(w2, ["seed"], 1024).select("seed", F.round("estimate", 4).alias("b"))
    n = pairs.agg(F.count("*").cast("double").alias("n"))
    err = lambda c: F.round(F.sqrt(F.avg((F.col(c) / F.col("n") - 1) * (F.col(c) / F.col("n") - 1))), 5)
    return a.join(b, "seed").crossJoin(F.broadcast(n)).agg(F.count("*").alias("runs"), err("a").alias("matrix"), err("b").alias("registers"))


_NYB = G.registers(G.words(G.source("lineitem", PAIR), k=4096))


@query("nybble_exceptions", f"SELECT low AS offset_, count(*) FILTER (WHERE reg >= low + 15) AS exceptions FROM (SELECT reg, min(reg) OVER () AS low FROM (SELECT reg FROM ({_NYB}) UNION ALL SELECT 0 FROM range(4096) t(i) WHERE i::INTEGER NOT IN (SELECT row_id FROM ({_NYB})))) GROUP BY low")
def _(spark, d):
    """Registers that four bits above a common offset can't hold."""
    regs = state.registers_direct(table(spark, d, "lineitem"), PAIR, k=4096, profile="portable")
    h = state.register_histogram(regs, k=4096, columns=J).select(F.posexplode("hist").alias("reg", "n")).where("n > 0")
    low = h.agg(F.min("reg").alias("offset_"))
    return h.crossJoin(F.broadcast(low)).groupBy("offset_").agg(F.sum(F.when(F.col("reg") >= F.col("offset_") + 15, F.col("n")).otherwise(0)).alias("exceptions"))


_BOUND = 2 * E.ERROR_CONSTANTS["count_inverse"] / K**0.5


@query("estimate_with_bounds", f"SELECT coupons, estimate, round(estimate * {1 - _BOUND!r}, 2) AS lower, round(estimate * {1 + _BOUND!r}, 2) AS upper FROM ({G.count_inverse(G.collected(WORDS))})")
def _(spark, d):
    return rounded(E.bounds(rounded(E.est_count_inverse(words(spark, d), k=K, columns=J), "estimate", digits=2), "count_inverse", K), "lower", "upper", digits=2)


@query("accuracy_summary", f"WITH e AS (SELECT l_returnflag, l_linestatus, estimate FROM ({G.count_inverse(G.collected(G.words(G.source('lineitem', PAIR, FLAGS), FLAGS), FLAGS), FLAGS)})), t AS (SELECT l_returnflag, l_linestatus, count(DISTINCT (l_partkey, l_suppkey))::DOUBLE AS n FROM lineitem GROUP BY ALL) SELECT count(*) AS n, round(avg(estimate - t.n), 2) AS bias, round(sqrt(avg(pow(estimate - t.n, 2))), 2) AS rmse FROM e JOIN t USING (l_returnflag, l_linestatus)")
def _(spark, d):
    li = table(spark, d, "lineitem")
    est = rounded(E.est_count_inverse(state.row_words(li, PAIR, FLAGS, **P), FLAGS, K, J), "estimate", digits=2)
    truth = li.groupBy(*FLAGS).agg(F.count_distinct(*PAIR).cast("double").alias("truth"))
    return rounded(E.accuracy(est.join(truth, list(FLAGS)), "estimate", "truth").select("n", "bias", "rmse"), "bias", "rmse", digits=2)
