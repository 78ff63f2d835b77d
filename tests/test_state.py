import pytest
from pyspark.sql import functions as F

from couponspark.api import distinct_estimate
from couponspark.operators import estimate as E
from couponspark.operators import packed, state
from couponspark.operators.surface import rolling
from couponspark.sources.readers import rate_ids, read_ids, stream_ids
from couponspark.sources.sketch_store import check_same, pack, unpack


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.fixture(scope="module")
def orders(spark, sf):
    return spark.read.parquet(f"{sf}/orders.parquet").select("o_orderkey", "o_custkey").cache()


def test_union_idempotent_and_free_of_order(orders):
    w = rows(state.row_words(orders, "o_custkey"))
    assert w == rows(state.row_words(orders.union(orders).union(orders), "o_custkey"))
    assert w == rows(state.row_words(orders.repartition(17), "o_custkey"))
    parts = [state.row_words(orders.where(F.col("o_orderkey") % 3 == i), "o_custkey") for i in range(3)]
    assert w == rows(state.merge(*parts)) == rows(state.merge(*parts[::-1]))


def test_empty_one_and_null(spark, orders):
    none = state.row_words(orders.where("false"), "o_custkey")
    assert E.est_count_inverse(none).first().estimate == 0
    assert E.est_code_length(none).first().estimate == 0
    assert E.est_register(state.registers(none)).first().estimate == 0
    one = orders.where("o_custkey = 7")
    assert E.est_count_inverse(state.row_words(one, "o_custkey")).first().estimate == pytest.approx(1, abs=1e-3)
    assert E.est_history(state.first_arrivals(one, "o_custkey", ["o_orderkey"])).first().estimate == 1
    nulls = orders.withColumn("c", F.when(F.col("o_orderkey") % 3 == 0, None).otherwise(F.col("o_custkey")))
    kept = orders.where("o_orderkey % 3 <> 0")
    assert rows(state.row_words(nulls, "c")) == rows(state.row_words(kept, "o_custkey"))


@pytest.mark.parametrize("k", [16, 256, 65536])
def test_sizes(orders, k):
    w = state.row_words(orders, "o_orderkey", k=k)
    error = E.est_count_inverse(w, k=k).first().estimate / 15000 - 1
    assert abs(error) < 5 * 0.69 / k**0.5
    assert rows(state.downsize(w, 16)) == rows(state.row_words(orders, "o_orderkey", k=16))


def test_saturation(orders):
    old = state.row_words(orders.where("o_orderkey % 2 = 0"), "o_orderkey", k=16)
    floor = state.saturation_floor(old, 16)
    assert floor > 2
    assert rows(state.merge(old, state.row_words(orders, "o_orderkey", k=16, floor=floor))) == rows(state.row_words(orders, "o_orderkey", k=16))
    assert rows(state.registers(state.row_words(orders, "o_orderkey"))) == rows(state.registers_direct(orders, "o_orderkey"))


def test_pack_and_guards(orders):
    w = state.row_words(orders, "o_custkey", k=1024)
    packed = pack(w.withColumn("g", F.lit(1)), ["g"], 1024, 63, "fast")
    assert rows(unpack(packed).select("row_id", "word")) == rows(w)
    with pytest.raises(ValueError):
        check_same(packed, packed.withColumn("k", F.lit(2048)))
    merged = state.first_arrivals(orders, "o_custkey", ["o_orderkey"]).withColumn("merged", F.lit(True))
    with pytest.raises(ValueError):
        E.est_history(merged)


@pytest.mark.parametrize("method", ["count_inverse", "code_length", "history", "register", "register_code_length", "register_history", "exact"])
def test_api(orders, method):
    n = distinct_estimate(orders, "o_custkey", method=method, order=["o_orderkey"], k=4096).first().estimate
    assert abs(n / 1500 - 1) < 5 * 1.04 / 64
    with pytest.raises(ValueError):
        distinct_estimate(orders, "o_custkey", method="none")


def test_bounds_and_size(orders):
    assert E.choose_k(0.01) == 8192
    row = E.bounds(E.est_count_inverse(state.row_words(orders, "o_custkey")), "count_inverse", 1024).first()
    assert row.lower < row.estimate < row.upper


def test_rolling_has_each_day_once(spark):
    w = spark.sql("select date'2024-01-01' day, 1 row_id, 1L word union all select date'2024-01-03', 1, 2L")
    got = {str(r.day): r.word for r in rolling(w, "day", 3).collect()}
    assert got["2024-01-01"] == 1 and got["2024-01-03"] == 3 and got["2024-01-05"] == 2


def test_native_plan(spark, sf, capsys):
    li = spark.read.parquet(f"{sf}/lineitem.parquet")
    E.est_count_inverse(state.row_words(li, "l_partkey", ["l_returnflag"], k=4096), ["l_returnflag"], 4096).explain("formatted")
    plan = capsys.readouterr().out
    assert "partial_bit_or" in plan and "Python" not in plan
    assert "ReadSchema: struct<l_partkey:bigint,l_returnflag:string>" in plan


def test_history_plan_sorts_nothing(spark, sf, capsys):
    ev = spark.read.parquet(f"{sf}/events.parquet")
    a = state.first_arrivals(ev, "user_id", ["event_id"], ["event_type"])
    E.est_history(a, ["event_type"]).explain("formatted")
    plan = capsys.readouterr().out
    assert "SortAggregate" not in plan and "partial_min" in plan


def test_several_order_columns_and_null_groups(spark):
    rows = [(1, 5, 2, None), (1, 5, 1, None), (2, 5, 3, None), (1, None, 9, "a"), (1, None, 8, "a"), (3, 4, 4, "a")]
    df = spark.createDataFrame(rows, "id int, t int, u int, g string")
    got = {(r.g, r.first_pos.t, r.first_pos.u) for r in state.first_arrivals(df, "id", ["t", "u"], ["g"]).collect()}
    assert got == {(None, 5, 1), (None, 5, 3), ("a", None, 8), ("a", 4, 4)}


def test_hybrid_keeps_null_groups(spark):
    df = spark.range(400).selectExpr("id", "case when id % 2 = 0 then 'a' end as g", "id as pos")
    w = state.row_words(df, "id", ["g"], 256)
    got = {r.g: r.estimate for r in E.est_hybrid(w, ["g"], 256).collect()}
    steps = {r.g: r.estimate for r in E.est_hybrid_history(state.first_arrivals(df, "id", ["pos"], ["g"], 256), ["g"], 256).collect()}
    assert set(got) == set(steps) == {None, "a"}
    assert all(abs(x / 200 - 1) < 0.35 for x in [*got.values(), *steps.values()])


def test_equal_ids_of_unequal_types(spark):
    a = spark.range(2000).selectExpr("cast(id as int) id", "cast(id as float) f")
    b = spark.range(2000).selectExpr("id", "cast(id as double) f")
    for c in ("id", "f"):
        assert rows(state.row_words(a, c)) == rows(state.row_words(b, c)) == rows(state.merge(state.row_words(a, c), state.row_words(b, c)))


def test_prior_words(spark, orders):
    k = 64
    first = state.row_words(orders.where("o_orderkey % 3 = 0"), "o_orderkey", k=k)
    assert state.saturation_floor(first, k) > 2
    for method in ("count_inverse", "code_length"):
        whole = distinct_estimate(orders, "o_orderkey", k=k, method=method).first().estimate
        assert distinct_estimate(orders, "o_orderkey", k=k, method=method, prior=first).first().estimate == pytest.approx(whole)
    with pytest.raises(ValueError):
        distinct_estimate(orders, "o_orderkey", k=k, method="register", prior=first)


def test_readers(spark, orders, tmp_path):
    want = rows(state.row_words(orders, "o_custkey"))
    for kind in ("parquet", "csv", "json", "orc"):
        orders.write.format(kind).save(f"{tmp_path}/{kind}")
        df = read_ids(spark, f"{tmp_path}/{kind}", ["o_custkey"], kind, "o_orderkey long, o_custkey long")
        assert df.columns == ["o_custkey"] and rows(state.row_words(df, "o_custkey")) == want
    orders.selectExpr("cast(o_custkey as string) value").write.text(f"{tmp_path}/text")
    assert read_ids(spark, f"{tmp_path}/text", ["value"], "text").distinct().count() == orders.select("o_custkey").distinct().count()
    with pytest.raises(ValueError):
        read_ids(spark, "x", ["a"], "csv")
    assert rate_ids(spark).isStreaming and stream_ids(spark, f"{tmp_path}/parquet", ["o_custkey"], "o_orderkey long, o_custkey long").columns == ["o_custkey"]


def test_many_groups_leave_early(spark, orders, monkeypatch):
    monkeypatch.setattr(packed, "HELD", 1)
    parts = packed.partial_sketches(orders.withColumn("g", F.col("o_custkey") % 7), "o_custkey", "g", 256)
    got = state.collected(unpack(packed.merge_bodies(parts, ["g"]), ["g"]), ["g"])
    want = state.collected(state.row_words(orders.withColumn("g", (F.col("o_custkey") % 7).cast("string")), "o_custkey", ["g"], 256), ["g"])
    assert rows(got) == rows(want)
