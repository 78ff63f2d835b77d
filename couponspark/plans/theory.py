"""Queries on the theory: probabilities, entropies, variances and constants. Spark and DuckDB get each value by another way: closed
forms here, and recurrences, series, other bases or identities of moments there."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from couponspark.functions import hashing as H
from couponspark.operators.estimate import ERROR_CONSTANTS

from . import sqlgen as G
from .registry import query, table

K, J = 1024, 61
MATRIX_ENTROPY, REGISTER_ENTROPY = 4.699204337, 2.831952664


def num(x: float) -> str:
    """A double literal of both dialects."""
    r = repr(float(x))
    return r if "e" in r else f"{r}e0"


def both(name: str, columns: dict[str, str], ranges: dict[str, tuple[int, int]], group: list[str] | None = None, outer: dict[str, str] | None = None, twin: str | None = None):
    """Register ``SELECT columns FROM ranges [GROUP BY group]``, and a projection of that, for Spark; DuckDB runs ``twin``, or the
    same if None."""
    duck = ", ".join(f"range({a}, {b}) t_{v}({v})" for v, (a, b) in ranges.items()) or "(SELECT 1)"
    select = ", ".join(f"{e} AS {c}" for c, e in columns.items())
    sql = f"SELECT {select} FROM {duck}" + (f" GROUP BY {', '.join(group)}" if group else "")
    if outer:
        sql = f"SELECT {', '.join(f'{e} AS {c}' for c, e in outer.items())} FROM ({sql})"

    @query(name, twin or sql)
    def _(spark, d):
        df = None
        for v, (a, b) in ranges.items():
            r = spark.range(a, b).withColumnRenamed("id", v)
            df = r if df is None else df.crossJoin(F.broadcast(r))
        df = df if df is not None else spark.range(1)
        if group is not None:
            keys = {c: e for c, e in columns.items() if c in group or e in group}
            aggs = [F.expr(e).alias(c) for c, e in columns.items() if c not in keys]
            df = (df.groupBy(*[F.expr(e).alias(c) for c, e in keys.items()]) if keys else df).agg(*aggs)
        else:
            df = df.selectExpr(*[f"{e} AS {c}" for c, e in columns.items()])
        return df.selectExpr(*[f"{e} AS {c}" for c, e in outer.items()]) if outer else df


def mass(j: str = "j", k: int = K) -> str:
    return f"(pow(2e0, -least({j}, {J - 1})) / {num(k)})"


def log_rest(j: str = "j", k: int = K) -> str:
    """log(1 - p) by its series: p is at most 2^-11, so five terms are exact to the last bit."""
    p = mass(j, k)
    return f"(-{p} * (1e0 + {p} / 2e0 + {p} * {p} / 3e0 + {p} * {p} * {p} / 4e0 + {p} * {p} * {p} * {p} / 5e0))"


def q(n: str, j: str = "j", k: int = K) -> str:
    return f"(1e0 - exp({n} * {log_rest(j, k)}))"


N = "pow(2e0, i)"


def doubled(a: int, b: int, columns: str, tail: str = "", last: int = J) -> str:
    """SQL over t(i, j, q), a <= i < b and j <= last: chances to be collected in 2^i draws. Two halves of a stream miss a cell
    independently, so q becomes q (2 - q) with each doubling: neither powers nor logarithms."""
    seed = f"SELECT 0::BIGINT AS i, j, pow(0.5, least(j, {J - 1})) / {K} AS q FROM range(1, {last + 1}) r(j)"
    return f"WITH RECURSIVE t AS ({seed} UNION ALL SELECT i + 1, j, q * (2 - q) FROM t WHERE i < {b - 1}) SELECT {columns} FROM t WHERE i >= {a}{tail}"

both("prob_collected", {"i": "i", "j": "j", "q": f"round({q(N)}, 8)"}, {"i": (0, 24), "j": (1, 31)}, twin=doubled(0, 24, "i, j, round(q, 8) AS q", last=30))
both("expected_coupons", {"i": "i", "c": f"round({num(K)} * sum({q(N)}), 4)"}, {"i": (0, 30), "j": (1, J + 1)}, ["i"], twin=doubled(0, 30, f"i, round({K} * sum(q), 4) AS c", " GROUP BY i"))
both("expected_coupons_asym", {"i": "i", "exact": f"round({num(K)} * sum({q('pow(2e0, i)')}), 3)", "approximate": f"round(any_value({num(K)} * ln({N} / ({num(0.79402362 * K)})) / ln(2e0)), 3)"}, {"i": (14, 34), "j": (1, J + 1)}, ["i"], twin=doubled(14, 34, f"i, round({K} * sum(q), 3) AS exact, round({K} * (i - log2({num(0.79402362 * K)})), 3) AS approximate", " GROUP BY i"))
both("variance_coupons", {"i": "i", "exact_over_k": f"round(sum({q(N)} * (1e0 - {q(N)})), 6)", "telescoped": f"round(any_value(exp(-{N} / ({num(K)} * pow(2e0, {J - 1}))) - exp(-{N} / {num(K)})), 6)"}, {"i": (8, 34), "j": (1, J + 1)}, ["i"], twin=doubled(8, 34, f"i, round(sum(q) - sum(q * q), 6) AS exact_over_k, round(pow(exp({num(-1 / (K * 2.0 ** (J - 1)))}), pow(2, i)) - pow(exp({num(-1 / K)}), pow(2, i)), 6) AS telescoped", " GROUP BY i"))


def entropy(x: str) -> str:
    """Entropy in bits of a cell that is empty with chance exp(-x)."""
    return f"((exp(-{x}) * {x} - CASE WHEN 1e0 - exp(-{x}) <= 0e0 THEN 0e0 ELSE (1e0 - exp(-{x})) * ln(1e0 - exp(-{x})) END) / ln(2e0))"


X = "least(pow(2e0, i / 256e0 - d), 700e0)"
_CELLS = """WITH e AS (SELECT i, exp(-least(pow(2, i / 256.0::DOUBLE) * pow(0.5, d), 700)) AS e FROM range(0, 256) a(i), range(-80, 81) b(d)),
h AS (SELECT i, e, CASE WHEN e <= 0 OR e >= 1 THEN 0 ELSE -e * log2(e) - (1 - e) * log2(1 - e) END AS h FROM e) """
both("entropy_matrix_curve", {"i": "i", "bits": f"round(sum({entropy(X)}), 7)"}, {"i": (0, 256), "d": (-80, 81)}, ["i"], twin=f"{_CELLS}SELECT i, round(sum(h), 7) AS bits FROM h GROUP BY i")
both("entropy_register_curve", {"i": "i", "bits": f"round(sum(exp(-{X}) * {entropy(X)}), 7)"}, {"i": (0, 256), "d": (-80, 81)}, ["i"], twin=f"{_CELLS}SELECT i, round(sum(e * h), 7) AS bits FROM h GROUP BY i")
_ANGLE = f"(i * {num(2 * math.pi / 256)})"
_GROWTH = "SELECT length(bin(l_orderkey))::BIGINT AS i, count(DISTINCT l_orderkey) AS n FROM lineitem WHERE l_orderkey > 0 GROUP BY 1"


def growth(spark, d):
    """(i, n): the orders in ``lineitem`` whose key has i bits; n about doubles with i."""
    return table(spark, d, "lineitem").where("l_orderkey > 0").groupBy(F.length(F.bin("l_orderkey")).cast("long").alias("i")).agg(F.count_distinct("l_orderkey").alias("n"))


@query("entropy_finite", f"SELECT i, any_value(n) AS n, round(-sum(CASE WHEN q <= 0 OR q >= 1 THEN 0 ELSE q * log2(q) + (1 - q) * log2(1 - q) END), 6) AS bits_per_row FROM (SELECT i, n, 1 - exp(-2 * n * atanh(p / (2 - p))) AS q FROM ({_GROWTH}), (SELECT pow(0.5, least(j, {J - 1})) / {K} AS p FROM range(1, {J + 1}) r(j))) GROUP BY i")
def _(spark, d):
    """Entropy of a row of the matrix after the orders whose key has i bits."""
    chance = growth(spark, d).crossJoin(F.broadcast(spark.range(1, J + 1).withColumnRenamed("id", "j"))).selectExpr("i", "n", f"{q('n')} AS q")
    bits = "CASE WHEN q <= 0e0 OR q >= 1e0 THEN 0e0 ELSE q * ln(q) + (1e0 - q) * ln(1e0 - q) END"
    return chance.groupBy("i").agg(F.any_value("n").alias("n"), F.expr(f"round(-sum({bits}) / ln(2e0), 6)").alias("bits_per_row"))


@query(
    "entropy_fourier",
    f"{_CELLS}, m AS (SELECT sum(h) / 256 AS m0, sum(cos(i * pi() / 128) * h) / 128 AS mc, sum(sin(i * pi() / 128) * h) / 128 AS ms, sum(e * h) / 256 AS r0, sum(cos(i * pi() / 128) * e * h) / 128 AS rc, sum(sin(i * pi() / 128) * e * h) / 128 AS rs FROM h), g AS ({_GROWTH}) SELECT i, n, round(m0, 8) AS matrix_mean, round(sqrt(mc * mc + ms * ms), 8) AS matrix_amplitude, round(r0, 8) AS register_mean, round(sqrt(rc * rc + rs * rs), 8) AS register_amplitude, round(m0 + mc * cos(a) + ms * sin(a), 7) AS matrix_bits, round(r0 + rc * cos(a) + rs * sin(a), 7) AS register_bits FROM (SELECT i, n, 2 * pi() * (log2(n) - {int(math.log2(K))}) AS a FROM g), m",
)
def _(spark, d):
    """Mean and first wave of the entropies over a doubling of the count, and what they give at the counts of ``growth``."""
    cells = spark.range(256).withColumnRenamed("id", "i").crossJoin(F.broadcast(spark.range(-80, 81).withColumnRenamed("id", "d")))
    cells = cells.selectExpr("i", f"{entropy(X)} AS h", f"exp(-{X}) * {entropy(X)} AS g")
    sums = [F.expr(f"sum({w} * {h}) / {n}").alias(f"{name}{part}") for name, h in (("m", "h"), ("r", "g")) for part, w, n in (("0", "1e0", "256e0"), ("c", f"cos({_ANGLE})", "128e0"), ("s", f"sin({_ANGLE})", "128e0"))]
    at = growth(spark, d).withColumn("a", F.expr(f"ln(n / {num(K)}) * {num(2 * math.pi / math.log(2))}")).crossJoin(F.broadcast(cells.agg(*sums)))
    waves = {"matrix_mean": "round(m0, 8)", "matrix_amplitude": "round(sqrt(mc * mc + ms * ms), 8)", "register_mean": "round(r0, 8)", "register_amplitude": "round(sqrt(rc * rc + rs * rs), 8)"}
    waves |= {"matrix_bits": "round(m0 + mc * cos(a) + ms * sin(a), 7)", "register_bits": "round(r0 + rc * cos(a) + rs * sin(a), 7)"}
    return at.selectExpr("i", "n", *(f"{e} AS {c}" for c, e in waves.items()))


both("prob_retained", {"d": "d", "c": "round(1e0 + i / 8e0, 3)", "p": "round(exp(-(1e0 + i / 8e0) * pow(2e0, -d)), 8)"}, {"d": (-6, 20), "i": (0, 8)}, twin="SELECT d, round(c, 3) AS c, round(pow(exp(-c), pow(0.5, d)), 8) AS p FROM range(-6, 20) a(d), (SELECT (8 + i) / 8.0::DOUBLE AS c FROM range(0, 8) r(i)) b")

L2 = f"({num(math.log(2) ** 2)})"
_ORDERS = "(SELECT count(DISTINCT l_orderkey) AS ids FROM lineitem)"


@query("count_inverse_error_theory", f"WITH w AS (SELECT k, a, sqrt(w) - 1 AS bias, w * (w - 1) AS variance FROM (SELECT k, ln(2) * ln(2) / k AS a, exp(ln(2) * ln(2) / k) AS w FROM (SELECT (1::BIGINT << e::INTEGER) AS k FROM range(4, 17) t(e)))) SELECT k, round(bias, 9) AS bias, round(variance, 9) AS variance, round(variance + bias * bias, 9) AS mse, round(a / 2, 9) AS leading_bias, round(sqrt(a), 9) AS leading_error, ids, round(ids * (1 + bias), 2) AS mean_estimate, round(ids * sqrt(variance + bias * bias), 2) AS rms_error FROM w, {_ORDERS}")
def _(spark, d):
    """Bias and error of count-inverse with k rows, and what they mean for the number of orders in ``lineitem``."""
    ids = table(spark, d, "lineitem").agg(F.count_distinct("l_orderkey").alias("ids"))
    k = spark.range(4, 17).selectExpr("cast(pow(2e0, id) AS BIGINT) AS k").crossJoin(F.broadcast(ids))
    half, whole = f"exp({L2} / (2e0 * k))", f"exp(2e0 * {L2} / k)"
    mse = f"{whole} - 2e0 * {half} + 1e0"
    out = {"k": "k", "bias": f"round({half} - 1e0, 9)", "variance": f"round({whole} - exp({L2} / k), 9)", "mse": f"round({mse}, 9)", "leading_bias": f"round({L2} / (2e0 * k), 9)", "leading_error": "round(ln(2e0) / sqrt(k), 9)"}
    return k.selectExpr(*(f"{e} AS {c}" for c, e in out.items()), "ids", f"round(ids * {half}, 2) AS mean_estimate", f"round(ids * sqrt({mse}), 2) AS rms_error")


_XK = "pow(2e0, -1e0 / pow(2e0, e))"
both("history_error_theory", {"k": "cast(pow(2e0, e) AS BIGINT)", "series": f"round((1e0 - {_XK}) / (1e0 + {_XK}), 10)", "bound": "round((pow(2e0, 1e0 / pow(2e0, e)) - 1e0) / 2e0, 10)", "standard_error": "round(sqrt(ln(2e0) / (2e0 * pow(2e0, e))), 8)"}, {"e": (4, 17)}, twin="SELECT k, round(tanh(ln(2) / (2 * k)), 10) AS series, round((exp(ln(2) / k) - 1) / 2, 10) AS bound, round(sqrt(ln(2) / 2) / sqrt(k), 8) AS standard_error FROM (SELECT (1::BIGINT << e::INTEGER) AS k FROM range(4, 17) t(e))")
_SHARED = "SELECT n, count(*) AS parts FROM (SELECT count(DISTINCT l_orderkey) AS n FROM lineitem GROUP BY l_partkey) GROUP BY n"


@query("bitmap_variance", f"WITH v AS (SELECT n, any_value(parts) AS parts, {K} * sum(pow(n / {num(K)}, m) / factorial(m::INTEGER)::DOUBLE) AS v FROM ({_SHARED}) a, range(2, 33) b(m) GROUP BY n) SELECT n, parts, round(v, 6) AS variance, round(n * n / {num(2 * K)}, 6) AS small_n, round(sqrt(v) / n, 7) AS relative_error FROM v")
def _(spark, d):
    """Variance and relative error of a bitmap of K cells at each number of orders that parts have, and how many parts have it."""
    n = table(spark, d, "lineitem").groupBy("l_partkey").agg(F.count_distinct("l_orderkey").alias("n")).groupBy("n").agg(F.count("*").alias("parts"))
    v = f"{num(K)} * exp(n / {num(K)}) - n - {num(K)}"
    return n.selectExpr("n", "parts", f"round({v}, 6) AS variance", f"round(n * n / {num(2 * K)}, 6) AS small_n", f"round(sqrt({v}) / n, 7) AS relative_error")


_BALLS = f"""SELECT balls, count(*) AS orders, round(avg((cols = balls)::INTEGER), 8) AS seen_apart_matrix, round(avg((cols = balls - 1)::INTEGER), 8) AS seen_pair_matrix, round(avg((cols = 1)::INTEGER), 8) AS seen_one_matrix, round(avg((bins = balls)::INTEGER), 8) AS seen_apart_three_bins, round(avg((bins = 1)::INTEGER), 8) AS seen_one_three_bins
FROM (SELECT l_orderkey, count(*) AS balls, count(DISTINCT length(bin(hi)) * (hi > 0)::INTEGER) AS cols, count(DISTINCT lo % 3) AS bins FROM (SELECT l_orderkey, ('0x' || substr(md5(id), 1, 15))::BIGINT AS hi, ('0x' || substr(md5(id), 18, 15))::BIGINT AS lo FROM (SELECT DISTINCT l_orderkey, l_orderkey || '|' || l_linenumber AS id FROM lineitem)) GROUP BY l_orderkey) WHERE balls IN (2, 3) GROUP BY balls"""


@query("collision_laws", "SELECT * FROM (VALUES (2, round(2 / 3::DOUBLE, 10), round(1 / 3::DOUBLE, 10), round(1 / 3::DOUBLE, 10), round(2 / 3::DOUBLE, 10), round(1 / 3::DOUBLE, 10)), (3, round(2 / 7::DOUBLE, 10), round(4 / 7::DOUBLE, 10), round(1 / 7::DOUBLE, 10), round(2 / 9::DOUBLE, 10), round(1 / 9::DOUBLE, 10))) t(balls, all_apart_matrix, one_pair_matrix, all_one_matrix, all_apart_three_bins, all_one_three_bins) JOIN (" + _BALLS + ") USING (balls)")
def _(spark, d):
    """Two or three balls in one row: how often they fall into one, two or three cells, summed over all outcomes for the columns of
    a matrix (halving masses, 60 of them) and for three equal bins, and how often the lines of orders of two or three lines fall so.
    The SQL twin has the closed forms."""
    bins = spark.range(1, 61).select(F.lit("matrix").alias("law"), "id", F.pow(F.lit(2.0), -F.col("id")).alias("p"))
    bins = bins.union(spark.range(3).select(F.lit("three_bins"), "id", F.lit(1 / 3)))
    power = bins.groupBy("law").agg(*[F.sum(F.pow("p", F.lit(float(i)))).alias(f"s{i}") for i in (1, 2, 3)])
    # power sums give the chances of outcomes: all equal; exactly one pair among three; all apart
    rows = power.select("law", F.explode(F.array(*[F.lit(b) for b in (2, 3)])).alias("balls"), "s1", "s2", "s3")
    one = F.when(F.col("balls") == 2, F.col("s2")).otherwise(F.col("s3"))
    pair = F.when(F.col("balls") == 2, F.col("s2")).otherwise(3 * (F.col("s2") * F.col("s1") - F.col("s3")))
    apart = F.when(F.col("balls") == 2, F.col("s1") ** 2 - F.col("s2")).otherwise(F.col("s1") ** 3 - 3 * F.col("s1") * F.col("s2") + 2 * F.col("s3"))
    wide = rows.select("law", "balls", one.alias("one"), pair.alias("pair"), apart.alias("apart")).groupBy("balls")
    of = lambda law, c: F.round(F.max(F.when(F.col("law") == law, F.col(c))), 10)
    law = wide.agg(of("matrix", "apart").alias("all_apart_matrix"), of("matrix", "pair").alias("one_pair_matrix"), of("matrix", "one").alias("all_one_matrix"), of("three_bins", "apart").alias("all_apart_three_bins"), of("three_bins", "one").alias("all_one_three_bins"))
    hi, lo = H.portable_pair(["l_orderkey", "l_linenumber"])
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber").distinct().select("l_orderkey", H.leading_column(hi).alias("col"), (lo % 3).alias("bin"))
    orders = lines.groupBy("l_orderkey").agg(F.count("*").alias("balls"), F.count_distinct("col").alias("cols"), F.count_distinct("bin").alias("bins")).where("balls in (2, 3)")
    share = lambda test, c: F.expr(f"round(avg(cast({test} AS int)), 8)").alias(f"seen_{c}")
    seen = orders.groupBy("balls").agg(F.count("*").alias("orders"), share("cols = balls", "apart_matrix"), share("cols = balls - 1", "pair_matrix"), share("cols = 1", "one_matrix"), share("bins = balls", "apart_three_bins"), share("bins = 1", "one_three_bins"))
    return law.withColumn("balls", F.col("balls").cast("int")).join(seen.withColumn("balls", F.col("balls").cast("int")), "balls")


_MONTHS = "SELECT month, ids, ids // 2000 AS emptied, ids % 2000 AS items FROM (SELECT (year(l_shipdate) * 100 + month(l_shipdate))::BIGINT AS month, count(DISTINCT l_orderkey) AS ids FROM lineitem GROUP BY 1)"


@query("buffer_overhead", f"SELECT month, ids, emptied, items, round(items * pow(0.5, 16) * 22, 6) AS bits_per_row, round(CASE WHEN emptied > 0 THEN 2000 ELSE items END * 22 / 65536, 6) AS most_bits_per_row FROM ({_MONTHS})")
def _(spark, d):
    """A sketch of 2^16 rows with a buffer of 2000 updates of 22 bits, which is emptied when full: for the orders shipped in each month, how
    often that is, and what the buffer costs at the month's end and at most."""
    month = (F.year("l_shipdate") * 100 + F.month("l_shipdate")).cast("long").alias("month")
    ids = table(spark, d, "lineitem").groupBy(month).agg(F.count_distinct("l_orderkey").alias("ids"))
    cost = "round(least(ids, 2000) * 22 / 65536e0, 6) AS most_bits_per_row"
    return ids.selectExpr("month", "ids", "ids div 2000 AS emptied", "ids % 2000 AS items", "round(ids % 2000 * 22 / 65536e0, 6) AS bits_per_row", cost)



_C = ERROR_CONSTANTS
_EFF = [("summary", _C["register"], _C["count_inverse"]), ("code_length", _C["register_code_length"], _C["code_length"]), ("history", _C["register_history"], _C["history"])]
_SPACE = math.sqrt(REGISTER_ENTROPY / MATRIX_ENTROPY)


@query("efficiency_table", " UNION ALL ".join(f"SELECT '{n}' AS kind, {num(r)} AS register_constant, {num(m)} AS matrix_constant, round({num(r)} * sqrt({num(REGISTER_ENTROPY)} / {num(MATRIX_ENTROPY)}), 4) AS threshold, {num(m)} < {num(r)} * sqrt({num(REGISTER_ENTROPY)} / {num(MATRIX_ENTROPY)}) AS matrix_wins, round(1e0 / sqrt(2e0), 6) AS register_small_n, round(1e0 / sqrt(6e0), 6) AS matrix_small_n, ids, round(ids * {num(r)} / sqrt({K}), 3) AS register_error, round(ids * {num(m)} / sqrt({K}), 3) AS matrix_error FROM (SELECT count(DISTINCT l_orderkey) AS ids FROM lineitem)" for n, r, m in _EFF))
def _(spark, d):
    """Accuracy per bit: the matrix wins where its constant lies below the register constant times sqrt of the entropy ratio. The
    errors are those of K rows at the number of orders in ``lineitem``."""
    rows = spark.createDataFrame(_EFF, "kind string, register_constant double, matrix_constant double")
    threshold = F.col("register_constant") * _SPACE
    ids = table(spark, d, "lineitem").agg(F.count_distinct("l_orderkey").alias("ids"))
    rows = rows.crossJoin(F.broadcast(ids))
    errors = [F.round(F.col("ids") * F.col(f"{c}_constant") / math.sqrt(K), 3).alias(f"{c}_error") for c in ("register", "matrix")]
    return rows.select("kind", "register_constant", "matrix_constant", F.round(threshold, 4).alias("threshold"), (F.col("matrix_constant") < threshold).alias("matrix_wins"), F.round(F.lit(1 / math.sqrt(2)), 6).alias("register_small_n"), F.round(F.lit(1 / math.sqrt(6)), 6).alias("matrix_small_n"), "ids", *errors)


_TAKEN = G.coupons(G.source("orders", ["o_custkey"]), k=K)


@query("coupon_mass_sum", f"SELECT count(*) FILTER (WHERE taken) AS collected, round(sum(CASE WHEN taken THEN pow(0.5, least(col_id, {J - 1})) / {K} ELSE 0 END), 10) AS collected_mass, sum(1::HUGEINT << ({J - 1} - least(col_id, {J - 1}))) = ({K}::HUGEINT << {J - 1}) AS sums_to_one FROM (SELECT col_id, row_id IN (SELECT o.row_id FROM ({_TAKEN}) o WHERE o.col_id = c.col_id) AS taken FROM range(0, {K}) r(row_id), range(1, {J + 1}) c(col_id))")
def _(spark, d):
    """The mass of the coupons that the customers in ``orders`` have collected; with those still missing it sums to one, exactly."""
    hi, lo = H.portable_pair("o_custkey")
    taken = table(spark, d, "orders").where("o_custkey is not null").select(H.row_of(lo, K).alias("row_id"), H.leading_column(hi).alias("col_id")).distinct()
    cells = spark.range(K).select(F.col("id").cast("int").alias("row_id")).crossJoin(F.broadcast(spark.range(1, J + 1).select(F.col("id").cast("int").alias("col_id"))))
    missing = cells.join(taken, ["row_id", "col_id"], "left_anti").select(F.lit(0).alias("n"), H.mass_units(F.col("col_id"), J).alias("u"))
    both_ = taken.select(F.lit(1).alias("n"), H.mass_units(F.col("col_id"), J).alias("u")).union(missing).groupBy("n").agg(F.count("*").alias("cells"), F.sum("u").alias("u"))
    total = F.lit(str(K << (J - 1))).cast("decimal(38,0)")
    got = F.col("n") == 1
    return both_.agg(F.coalesce(F.sum(F.when(got, F.col("cells"))), F.lit(0)).alias("collected"), F.round(F.coalesce(F.sum(F.when(got, F.col("u"))).cast("double"), F.lit(0.0)) / float(K << (J - 1)), 10).alias("collected_mass"), (F.sum("u") == total).alias("sums_to_one"))
