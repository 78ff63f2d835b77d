"""Queries on joins, windows, rollups, set operations and ids of many kinds."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from couponspark.functions import solvers as S
from couponspark.functions.sql import register
from couponspark.operators import estimate as E
from couponspark.operators import state
from couponspark.operators import surface as U

from . import sqlgen as G
from .registry import query, table
from .sketches import PAIR, J, K, P, rounded


def est(words, by=()):
    return rounded(E.est_count_inverse(words, by, K, J), "estimate", digits=2)


def est_sql(src, by=()):
    return G.count_inverse(G.collected(G.words(src, by), by), by)


# ---- joins

_OC = "(SELECT o.o_custkey, c.c_nationkey, n.n_regionkey, r.r_name FROM orders o JOIN customer c ON o_custkey = c_custkey JOIN nation n ON c_nationkey = n_nationkey JOIN region r ON n_regionkey = r_regionkey)"


@query("join_distinct_by_region", est_sql(G.source(_OC, ["o_custkey"], ["r_name"]), ["r_name"]))
def _(spark, d):
    """Sketches by nation first, small dimensions after: the fact table is not shuffled by region."""
    o, c = table(spark, d, "orders"), table(spark, d, "customer").select("c_custkey", "c_nationkey")
    w = state.row_words(o.join(c, o.o_custkey == c.c_custkey), "o_custkey", ["c_nationkey"], **P)
    n, r = table(spark, d, "nation"), table(spark, d, "region")
    named = w.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    return est(state.merge(named.select("r_name", "row_id", "word"), by=["r_name"]), ["r_name"])


@query("left_join_zero_groups", f"SELECT n_name, coalesce(coupons, 0)::BIGINT AS coupons, coalesce(estimate, 0)::DOUBLE AS estimate FROM nation LEFT JOIN ({est_sql(G.source('(SELECT o_custkey, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey WHERE o_totalprice < 2000)', ['o_custkey'], ['c_nationkey']), ['c_nationkey'])}) ON n_nationkey = c_nationkey")
def _(spark, d):
    o = table(spark, d, "orders").where("o_totalprice < 2000")
    c = table(spark, d, "customer").select("c_custkey", "c_nationkey")
    e = est(state.row_words(o.join(c, o.o_custkey == c.c_custkey), "o_custkey", ["c_nationkey"], **P), ["c_nationkey"])
    n = table(spark, d, "nation").select("n_nationkey", "n_name")
    return n.join(e, n.n_nationkey == e.c_nationkey, "left").select("n_name", F.coalesce("coupons", F.lit(0)).alias("coupons"), F.coalesce("estimate", F.lit(0.0)).alias("estimate"))


for kind, word in (("left_semi", "IN"), ("left_anti", "NOT IN")):

    @query(f"{kind[5:]}_join_distinct", est_sql(G.source("customer", ["c_custkey"], where=f"c_custkey {word} (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)")))
    def _(spark, d, kind=kind):
        o = table(spark, d, "orders").where("o_totalprice > 300000").select("o_custkey")
        c = table(spark, d, "customer")
        return est(state.row_words(c.join(o, c.c_custkey == o.o_custkey, kind), "c_custkey", **P))


# ---- many groups

@query("pair_distinct", est_sql(G.source("lineitem", PAIR)))
def _(spark, d):
    return est(state.row_words(table(spark, d, "lineitem"), PAIR, **P))


_MULTI = " UNION ALL ".join(f"SELECT '{n}' AS metric, {G.rendered(c)} AS id FROM lineitem" for n, c in (("order", "l_orderkey"), ("part", "l_partkey"), ("supplier", "l_suppkey")))


@query("multi_column_distinct", est_sql(_MULTI, ["metric"]))
def _(spark, d):
    m = {"order": F.col("l_orderkey"), "part": F.col("l_partkey"), "supplier": F.col("l_suppkey")}
    return est(U.several(table(spark, d, "lineitem"), m, **P), ["metric"])


_SUPP = est_sql(G.source("lineitem", ["l_partkey"], ["l_suppkey"]), ["l_suppkey"])


def by_supplier(spark, d):
    return est(state.row_words(table(spark, d, "lineitem"), "l_partkey", ["l_suppkey"], **P), ["l_suppkey"])


@query("topk_groups", f"SELECT l_suppkey, estimate FROM ({_SUPP}) ORDER BY estimate DESC, l_suppkey LIMIT 10")
def _(spark, d):
    return by_supplier(spark, d).select("l_suppkey", "estimate").orderBy(F.desc("estimate"), "l_suppkey").limit(10)


@query("having_estimate", f"SELECT l_suppkey, estimate FROM ({_SUPP}) WHERE estimate > 520")
def _(spark, d):
    return by_supplier(spark, d).where("estimate > 520").select("l_suppkey", "estimate")


@query("rank_groups", f"SELECT l_suppkey, coupons, rank() OVER (ORDER BY coupons DESC)::INTEGER AS rnk, dense_rank() OVER (ORDER BY coupons DESC)::INTEGER AS dense, ntile(4) OVER (ORDER BY coupons DESC, l_suppkey)::INTEGER AS quartile FROM ({_SUPP})")
def _(spark, d):
    w = Window.orderBy(F.desc("coupons"))
    return by_supplier(spark, d).select("l_suppkey", "coupons", F.rank().over(w).alias("rnk"), F.dense_rank().over(w).alias("dense"), F.ntile(4).over(Window.orderBy(F.desc("coupons"), "l_suppkey")).alias("quartile"))


# ---- set operations: parts shipped in two years

YEARS = ("1995", "1996")
_YEAR = [G.source("lineitem", ["l_partkey"], where=f"year(l_shipdate) = {y}") for y in YEARS]


def year_words(spark, d):
    li = table(spark, d, "lineitem")
    return [state.row_words(li.where(F.year("l_shipdate") == int(y)), "l_partkey", **P) for y in YEARS]


@query("sketch_union", G.count_inverse(G.collected(G.words(f"{_YEAR[0]} UNION ALL {_YEAR[1]}"))))
def _(spark, d):
    return est(state.merge(*year_words(spark, d)))


_A, _B, _U = (G.count_inverse(G.collected(G.words(s)), digits=8) for s in (*_YEAR, f"{_YEAR[0]} UNION ALL {_YEAR[1]}"))
_PAIRS = f"FROM (SELECT estimate AS a FROM ({_A})), (SELECT estimate AS b FROM ({_B})), (SELECT estimate AS u FROM ({_U}))"


@query("sketch_intersection_ie", f"SELECT round(a, 2) AS n_a, round(b, 2) AS n_b, round(u, 2) AS n_u, round(greatest(a + b - u, 0), 2) AS n_intersection, round(greatest(u - b, 0), 2) AS n_difference {_PAIRS}")
def _(spark, d):
    out = U.pair_counts(*year_words(spark, d), K, J).drop("jaccard")
    return rounded(out, *out.columns, digits=2)


@query("sketch_jaccard", f"SELECT round(greatest(a + b - u, 0) / u, 4) AS jaccard {_PAIRS}")
def _(spark, d):
    return rounded(U.pair_counts(*year_words(spark, d), K, J).select("jaccard"), "jaccard")


for op, sql_op in (("intersect", "INTERSECT"), ("except", "EXCEPT")):

    @query(f"exact_{op}", f"SELECT count(*) AS n FROM (SELECT l_partkey FROM lineitem WHERE year(l_shipdate) = {YEARS[0]} {sql_op} SELECT l_partkey FROM lineitem WHERE year(l_shipdate) = {YEARS[1]})")
    def _(spark, d, op=op):
        li = table(spark, d, "lineitem")
        a, b = (li.where(F.year("l_shipdate") == int(y)).select("l_partkey") for y in YEARS)
        return (a.intersect(b) if op == "intersect" else a.subtract(b)).agg(F.count("*").alias("n"))


# ---- events: days, windows, rollups

EV = "(SELECT *, ts::DATE AS day FROM events)"


def events(spark, d):
    return table(spark, d, "events").withColumn("day", F.to_date("ts"))


def daily(spark, d, by=()):
    return state.row_words(events(spark, d), "user_id", [*by, "day"], **P)


_DAILY = est_sql(G.source(EV, ["user_id"], ["day"]), ["day"])


@query("daily_distinct", _DAILY)
def _(spark, d):
    return est(daily(spark, d), ["day"])


@query("monthly_distinct", est_sql(G.source("(SELECT *, date_trunc('month', o_orderdate)::DATE AS month FROM orders)", ["o_custkey"], ["month"]), ["month"]))
def _(spark, d):
    o = table(spark, d, "orders").withColumn("month", F.trunc("o_orderdate", "month"))
    return est(state.row_words(o, "o_custkey", ["month"], **P), ["month"])


@query("daily_growth", f"SELECT day, coupons, coupons - lag(coupons) OVER (ORDER BY day) AS growth FROM ({_DAILY})")
def _(spark, d):
    c = state.collected(daily(spark, d), ["day"])
    return c.select("day", "coupons", (F.col("coupons") - F.lag("coupons").over(Window.orderBy("day"))).alias("growth"))


_IDS = ["user_id", "props"]
_CUM = f"SELECT day, sum(new) OVER (ORDER BY day)::BIGINT AS coupons FROM (SELECT day, count(*) AS new FROM (SELECT row_id, col_id, min(day) AS day FROM ({G.coupon_rows(G.source(EV, _IDS, extra=['day']), extra=['day'])}) GROUP BY ALL) GROUP BY day)"


@query("cumulative_distinct", G.count_inverse(_CUM, ["day"]))
def _(spark, d):
    c = U.cumulative(events(spark, d), _IDS, "day", **P)
    return rounded(c.select("day", "coupons", S.count_inverse(F.col("coupons"), K, J).alias("estimate")), "estimate", digits=2)


@query("rolling_7d_distinct", G.count_inverse(G.collected(f"SELECT (w.day + n::INTEGER)::DATE AS day, row_id, bit_or(word) AS word FROM ({G.words(G.source(EV, _IDS, ['day']), ['day'])}) w, range(7) t(n) GROUP BY ALL", ["day"]), ["day"]))
def _(spark, d):
    w = state.row_words(events(spark, d), _IDS, ["day"], **P)
    return est(U.rolling(w, "day", 7), ["day"])


@query("asof_cumulative_distinct", f"SELECT event_id, coupons FROM (SELECT event_id, ts FROM events WHERE event_type = 'purchase') e ASOF JOIN ({_CUM}) c ON e.ts::DATE >= c.day")
def _(spark, d):
    """The latest cumulative count at each purchase, by one sort of both sides within a day's range."""
    c = U.cumulative(events(spark, d), _IDS, "day", **P)
    spans = c.withColumn("until", F.lead("day").over(Window.orderBy("day")))
    p = events(spark, d).where("event_type = 'purchase'").select("event_id", F.col("day").alias("at"))
    return p.join(F.broadcast(spans), (F.col("at") >= F.col("day")) & (F.col("until").isNull() | (F.col("at") < F.col("until")))).select("event_id", "coupons")


@query("session_distinct", f"WITH s AS (SELECT *, sum(new) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS session FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY event_type ORDER BY ts, event_id) > INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS new FROM events)) SELECT event_type, session::BIGINT AS session, coupons FROM ({G.collected(G.words(G.source('s', ['user_id'], ['event_type', 'session']), ['event_type', 'session']), ['event_type', 'session'])})")
def _(spark, d):
    """Sessions of each type by gaps of half an hour, then a sketch of each."""
    order = Window.partitionBy("event_type").orderBy("ts", "event_id")
    ev = table(spark, d, "events").withColumn("gap", F.col("ts") - F.lag("ts").over(order))
    ev = ev.withColumn("session", F.sum((F.coalesce(F.col("gap") > F.expr("INTERVAL '30' MINUTE"), F.lit(False))).cast("bigint")).over(order))
    return state.collected(state.row_words(ev, "user_id", ["event_type", "session"], **P), ["event_type", "session"])


_DIMS = ["event_type", "day"]
_EW = G.words(G.source(EV, ["user_id"], _DIMS), _DIMS)


def _sets(kind: str) -> str:
    return G.collected(f"SELECT event_type, day, grouping(event_type)::INTEGER AS g_event_type, grouping(day)::INTEGER AS g_day, row_id, bit_or(word) AS word FROM ({_EW}) GROUP BY row_id, {kind}", [*_DIMS, "g_event_type", "g_day"])


def _finest(spark, d):
    return state.row_words(events(spark, d), "user_id", _DIMS, **P)


KEYS = [*_DIMS, "g_event_type", "g_day"]


@query("sketch_cube", _sets("CUBE (event_type, day)"))
def _(spark, d):
    return state.collected(U.cube(_finest(spark, d), _DIMS), KEYS)


@query("sketch_rollup", _sets("ROLLUP (event_type, day)"))
def _(spark, d):
    return state.collected(U.rollup(_finest(spark, d), _DIMS), KEYS)


@query("sketch_grouping_sets", _sets("GROUPING SETS ((event_type), (day))"))
def _(spark, d):
    return state.collected(U.grouping_sets(_finest(spark, d), _DIMS, [["event_type"], ["day"]]), KEYS)


TYPES = ["click", "login", "logout", "purchase", "view"]
_PV = G.collected(_EW, _DIMS)


@query("pivot_estimates", f"SELECT day, {', '.join(f'max(CASE WHEN event_type = {t!r} THEN coupons END) AS {t}' for t in TYPES)} FROM ({_PV}) GROUP BY day")
def _(spark, d):
    return state.collected(_finest(spark, d), _DIMS).groupBy("day").pivot("event_type", TYPES).agg(F.max("coupons"))


@query("distinct_json_values", est_sql(G.source("(SELECT event_type, json_extract_string(props, '$.k') AS v FROM events)", ["v"], ["event_type"]), ["event_type"]))
def _(spark, d):
    ev = table(spark, d, "events").select("event_type", F.get_json_object("props", "$.k").alias("v"))
    return est(state.row_words(ev, "v", ["event_type"], **P), ["event_type"])


@query("udaf_matches_native", G.collected(G.words(G.source("events", ["user_id"], ["event_type"]), ["event_type"]), ["event_type"]))
def _(spark, d):
    """A grouped aggregate function in pandas: the count of distinct coupons, as the native path has it."""

    @F.pandas_udf("long")
    def coupons(row: pd.Series, bit: pd.Series) -> int:
        return int(pd.DataFrame({"r": row, "b": bit}).drop_duplicates().shape[0])

    rows = state.coupon_rows(table(spark, d, "events"), "user_id", ["event_type"], **P).distinct()
    return rows.groupBy("event_type").agg(coupons("row_id", "bit").alias("coupons"))


@query("sql_surface")
def _(spark, d):
    register(spark, K)
    table(spark, d, "events").createOrReplaceTempView("cm_events")
    return spark.sql("SELECT event_type, cm_estimate(sum(cm_count(word))) AS estimate FROM (SELECT event_type, cm_row(cast(user_id AS STRING)) AS row_id, bit_or(cm_bit(cast(user_id AS STRING))) AS word FROM cm_events GROUP BY 1, 2) GROUP BY event_type")


# ---- texts, pages, conversations, vectors

@query("distinct_texts_by_lang_source", est_sql(G.source("documents", ["text"], ["lang", "source"]), ["lang", "source"]))
def _(spark, d):
    return est(state.row_words(table(spark, d, "documents"), "text", ["lang", "source"], **P), ["lang", "source"])


_TOKENS = "(SELECT lang, unnest(regexp_split_to_array(lower(text), '[^a-z0-9]+')) AS token FROM documents)"


@query("distinct_tokens_by_lang", est_sql(G.source(_TOKENS, ["token"], ["lang"], where="token <> ''"), ["lang"]))
def _(spark, d):
    t = table(spark, d, "documents").select("lang", F.explode(F.split(F.lower("text"), "[^a-z0-9]+")).alias("token")).where("token <> ''")
    return est(state.row_words(t, "token", ["lang"], **P), ["lang"])


@query("distinct_hosts", est_sql(G.source("(SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM pages)", ["host"])))
def _(spark, d):
    p = table(spark, d, "pages").select(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"))
    return est(state.row_words(p, "host", **P))


@query("distinct_roles_by_turn", est_sql(G.source("conversations", ["role"], ["turn"]), ["turn"]))
def _(spark, d):
    return est(state.row_words(table(spark, d, "conversations"), "role", ["turn"], **P), ["turn"])


@query("distinct_embeddings", est_sql(G.source("(SELECT label, array_to_string(list_transform(embedding, lambda x: round(x::DOUBLE * 1000000)::BIGINT), '|') AS v FROM embeddings)", ["v"], ["label"]), ["label"]))
def _(spark, d):
    v = F.array_join(F.transform("embedding", lambda x: F.round(x.cast("double") * 1000000).cast("bigint").cast("string")), "|")
    return est(state.row_words(table(spark, d, "embeddings").select("label", v.alias("v")), "v", ["label"], **P), ["label"])


_LAB = "(SELECT text, EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id) AS labelled FROM documents d)"


@query("labelled_vs_unlabelled_docs", est_sql(G.source(_LAB, ["text"], ["labelled"]), ["labelled"]))
def _(spark, d):
    docs, labels = table(spark, d, "documents"), table(spark, d, "labels").select("doc_id")
    parts = [docs.join(labels, "doc_id", kind).select("text", F.lit(flag).alias("labelled")) for kind, flag in (("left_semi", True), ("left_anti", False))]
    return est(state.row_words(parts[0].union(parts[1]), "text", ["labelled"], **P), ["labelled"])


@query("benchmark_texts_in_documents", f"SELECT round(greatest(a + b - u, 0), 2) AS n_intersection FROM (SELECT estimate AS a FROM ({G.count_inverse(G.collected(G.words(G.source('benchmark', ['text']))), digits=8)})), (SELECT estimate AS b FROM ({G.count_inverse(G.collected(G.words(G.source('documents', ['text']))), digits=8)})), (SELECT estimate AS u FROM ({G.count_inverse(G.collected(G.words(G.source('benchmark', ['text']) + ' UNION ALL ' + G.source('documents', ['text']))), digits=8)}))")
def _(spark, d):
    a, b = (state.row_words(table(spark, d, t), "text", **P) for t in ("benchmark", "documents"))
    return rounded(U.pair_counts(a, b, K, J).select("n_intersection"), "n_intersection", digits=2)


@query("store_roundtrip", G.count_inverse(G.collected(G.words(G.source(EV, ["user_id"])))))
def _(spark, d):
    """Daily sketches packed, written by day, read back, unpacked and merged."""
    import uuid

    from couponspark.sources.sketch_store import read_sketches, scratch, write_sketches

    path = f"{scratch(spark)}/sketches-{uuid.uuid4().hex[:12]}"
    write_sketches(daily(spark, d), ["day"], path, K, J)
    return est(state.merge(read_sketches(spark, path).select("row_id", "word")))
