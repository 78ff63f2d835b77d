import numpy as np
import pytest

from couponspark.operators import simulate as X

SMALL = {"count_inverse": 0.408845, "register": 0.716768, "code_length": 0.407660, "register_code_length": 0.710784, "history": 0.407170, "register_history": 0.578730}
LARGE = {"count_inverse": 0.6931697, "history": 0.5887044, "code_length": 0.649057, "register": 1.0390092, "register_history": 0.8325560, "register_code_length": 1.036624}


def test_small_counts(spark):
    got = {r.estimator: r.scaled_error for r in X.moments(X.simulate_direct(spark, 512, 64, 6000)).collect()}
    for name, value in SMALL.items():
        assert got[name] == pytest.approx(value, rel=0.05), name


def test_large_counts(spark):
    """The order of the methods, and the limits of six constants by the fit over k = 2^4 .. 2^10."""
    runs = X.simulate(spark, [1 << e for e in range(4, 11)], 160, 25, 75, 200)
    got = {r.estimator: r.c0 for r in X.fit_inverse_k(X.moments(runs), "scaled_error").collect()}
    for name, value in LARGE.items():
        assert got[name] == pytest.approx(value, rel=0.02), name
    assert got["history"] < got["code_length"] < got["count_inverse"] < got["register_history"] < got["register_code_length"]


def test_bias(spark):
    got = {r.estimator: r.scaled_bias for r in X.moments(X.simulate(spark, (16,), 3000, 25, 70, 20)).collect()}
    assert got["count_inverse"] == pytest.approx(0.24, abs=0.08)
    assert abs(got["history"]) < 0.08


def test_direct_equals_sequence():
    rng = np.random.default_rng(1)
    a = np.mean([X.along(64, X.sequence(64, rng), np.array([40.0]))["count_inverse"][0] for _ in range(600)])
    b = np.mean([X.along(64, X.direct(64, 40, rng), np.array([40.0]))["count_inverse"][0] for _ in range(600)])
    assert a == pytest.approx(b, rel=0.03)
