"""Estimates against values made by an independent loop over rows (FIXTURES.md)."""

import pytest

from couponspark.operators import estimate as E
from couponspark.operators import state
from couponspark.plans.sketches import LINE_ORDER

P, J = {"k": 1024, "profile": "portable"}, 61
GOLDEN = [
    ("orders", ["o_custkey"], ["o_orderkey"], 1198, 1498.25, 1496.18, 1499.17, 1507.21, 1506.97, 2148.0),
    ("orders", ["o_orderkey"], ["o_orderkey"], 4371, 15670.48, 15557.38, 15525.42, 15879.70, 15723.62, 15577.2),
    ("lineitem", ["l_orderkey"], LINE_ORDER, 4337, 15313.94, 15222.97, 15195.59, 15632.00, 15391.65, 15315.8),
    ("lineitem", ["l_partkey"], LINE_ORDER, 1496, 1999.84, 2000.54, 2005.42, 2052.32, 2010.76, 2492.9),
    ("lineitem", ["l_suppkey"], LINE_ORDER, 99, 100.61, 100.68, 100.66, 100.80, 100.11, 1375.0),
    ("lineitem", ["l_partkey", "l_suppkey"], LINE_ORDER, 6171, 52996.47, 53605.12, 53261.65, 52877.11, 52053.83, 54309.1),
    ("events", ["user_id"], ["event_id"], 147, 150.59, 150.56, 150.89, 150.54, 152.88, 1394.7),
    ("events", ["user_id", "props"], ["event_id"], 3204, 7107.34, 7143.08, 7145.29, 7293.81, 7178.21, 7215.1),
    ("documents", ["text"], ["doc_id"], 800, 922.24, 920.69, 921.45, 919.95, 925.61, 1786.8),
]


@pytest.mark.parametrize("case", GOLDEN, ids=lambda c: f"{c[0]}-{'-'.join(c[1])}")
def test_golden(spark, sf, case):
    table, ids, order, c, icon, mdl, hip, reg, reg_hip, gap = case
    df = spark.read.parquet(f"{sf}/{table}.parquet")
    if table == "documents" and state.collected(state.row_words(df, ids, **P)).first()[0] != c:
        pytest.skip("the documents table is another one than that of the golden values")
    w, a = state.row_words(df, ids, **P), state.first_arrivals(df, ids, order, **P)
    first = E.est_count_inverse(w, k=1024, columns=J).first()
    assert first.coupons == c and first.estimate == pytest.approx(icon, abs=0.006)
    assert E.est_code_length(w, k=1024, columns=J).first().estimate == pytest.approx(mdl, rel=1e-4)
    assert E.est_history(a, k=1024, columns=J).first().estimate == pytest.approx(hip, abs=0.006)
    assert E.est_register(state.registers(w), k=1024).first().estimate == pytest.approx(reg, abs=0.006)
    assert E.est_register_history(a, k=1024, columns=J).first().estimate == pytest.approx(reg_hip, abs=0.006)
    assert E.est_leftmost_gap(w, k=1024).first().estimate == pytest.approx(gap, abs=0.06)


def test_hybrid(spark, sf):
    o = spark.read.parquet(f"{sf}/orders.parquet")
    row = E.est_hybrid_history(state.first_arrivals(o, "o_custkey", ["o_orderkey"], **P), k=1024, columns=J).first()
    assert row.estimate == pytest.approx(1506.2102, abs=1e-4) and row.matrix_coupons == 101
