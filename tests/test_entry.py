import __spark_entry__ as entry
from couponspark.plans.theory import ERROR_CONSTANTS


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["coupons", "estimate"] and df.count() == 1


def test_names():
    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q) and len(q) > 100


def test_theory(spark, sf):
    q = entry.queries()
    f = q["entropy_fourier"](spark, sf).first()
    assert abs(f.matrix_mean - 4.699204337) < 1e-7 and abs(f.register_mean - 2.831952664) < 1e-7
    assert all(r.matrix_wins for r in q["efficiency_table"](spark, sf).collect())
    full = q["buffer_overhead"](spark, sf).collect()
    assert all(r.most_bits_per_row == (0.671387 if r.emptied else r.bits_per_row) and r.ids == 2000 * r.emptied + r.items for r in full)
    assert ERROR_CONSTANTS["count_inverse"] < 0.807
