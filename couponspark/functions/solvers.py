"""Estimators as expressions of one row: fixed numbers of bisection steps over column sums, so that plans stay declarative.

``m`` is a candidate count, p_j = 2^-min(j, J-1)/k the mass of a coupon of column j and l_j = log(1 - p_j). Cells of a column
share their mass, so each sum over cells is a sum over at most 63 columns.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

STEPS = 60
GROWTH_CONSTANT = 0.79402362  # limit of n / (k 2^(C/k)), found numerically from the expected coupon count
GAP_CONSTANT = 0.77351  # published constant of leftmost-gap counting


def masses(k: int, columns: int) -> list[float]:
    return [2.0 ** -min(j, columns - 1) / k for j in range(1, columns + 1)]


def log_rest(k: int, columns: int) -> list[float]:
    return [math.log1p(-p) for p in masses(k, columns)]


def literal(values: list[float]) -> Column:
    return F.array(*[F.lit(float(v)) for v in values])


def bisect(too_small, top: float, steps: int = STEPS) -> Column:
    """2^x for the x in [0, top] where ``too_small(2^x)`` turns false."""
    start = F.struct(F.lit(0.0).alias("lo"), F.lit(float(top)).alias("hi"))

    def step(s: Column, _: Column) -> Column:
        mid = (s["lo"] + s["hi"]) / 2
        less = too_small(F.pow(F.lit(2.0), mid))
        return F.struct(F.when(less, mid).otherwise(s["lo"]).alias("lo"), F.when(less, s["hi"]).otherwise(mid).alias("hi"))

    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, step, lambda s: F.pow(F.lit(2.0), (s["lo"] + s["hi"]) / 2))


def top_of(k: int) -> float:
    return math.log2(k) + 62


def expected_coupons(m: Column, k: int, columns: int, poisson: bool = False) -> Column:
    rates = [-p for p in masses(k, columns)] if poisson else log_rest(k, columns)
    return F.aggregate(literal(rates), F.lit(0.0), lambda a, r: a - F.expm1(m * r)) * k


def variance_coupons(m: Column, k: int, columns: int) -> Column:
    return F.aggregate(literal(log_rest(k, columns)), F.lit(0.0), lambda a, r: a - F.expm1(m * r) * F.exp(m * r)) * k


def count_inverse(c: Column, k: int, columns: int, poisson: bool = False) -> Column:
    """The count whose expected number of coupons is ``c``."""
    found = bisect(lambda m: expected_coupons(m, k, columns, poisson) < c, top_of(k))
    return F.when(c == 0, F.lit(0.0)).otherwise(found)


def count_inverse_asymptotic(c: Column, k: int) -> Column:
    """Closed form for counts far above k."""
    return F.lit(GROWTH_CONSTANT * k) * F.pow(F.lit(2.0), c / k)


def code_length(occupancy: Column, k: int, columns: int) -> Column:
    """The count that minimises the ideal code length of a state with these column sums."""
    pairs = F.arrays_zip(occupancy.alias("s"), literal(log_rest(k, columns)).alias("l"))

    def slope(m: Column) -> Column:
        def term(a: Column, x: Column) -> Column:
            s, l = x["s"], x["l"]
            return a + l * ((k - s) - F.when(s == 0, F.lit(0.0)).otherwise(s / F.expm1(-m * l)))

        return F.aggregate(pairs, F.lit(0.0), term)

    total = F.aggregate(occupancy, F.lit(0).cast("bigint"), lambda a, s: a + s)
    # the slope is that of the code length in m times the sign of log(1 - p): positive while m is too small
    return F.when(total == 0, F.lit(0.0)).otherwise(bisect(lambda m: slope(m) > 0, top_of(k)))


def ideal_space_bits(occupancy: Column, m: Column, k: int, columns: int) -> Column:
    """Ideal code length in bits of a state under count ``m``."""
    pairs = F.arrays_zip(occupancy.alias("s"), literal(log_rest(k, columns)).alias("l"))

    def term(a: Column, x: Column) -> Column:
        s, l = x["s"], x["l"]
        full = F.when(s == 0, F.lit(0.0)).otherwise(s * F.log(-F.expm1(m * l)))
        return a - (full + (k - s) * m * l) / math.log(2)

    return F.aggregate(pairs, F.lit(0.0), term)


def register_code_length(histogram: Column, k: int, columns: int) -> Column:
    """The count under which registers are most likely; ``histogram`` has k rows spread over values 0..columns."""
    ls = log_rest(k, columns)
    steps = F.sequence(F.lit(0), F.lit(columns))

    def slope(m: Column) -> Column:
        # d/dm of log P: a register at v has column v collected and all later ones not; at 0 none is collected
        def term(a: Column, v: Column) -> Column:
            n = F.element_at(histogram, v + 1)
            later = F.element_at(literal([sum(ls[j:]) for j in range(columns + 1)]), v + 1)
            own = F.element_at(literal([0.0, *ls]), v + 1)
            gain = F.when(v == 0, F.lit(0.0)).otherwise(own / F.expm1(-m * own) * -1)
            return a + F.when(n == 0, F.lit(0.0)).otherwise(n * (later + gain))

        return F.aggregate(steps, F.lit(0.0), term)

    return F.when(F.element_at(histogram, 1) == k, F.lit(0.0)).otherwise(bisect(lambda m: slope(m) > 0, top_of(k)))


def register_alpha(k: int) -> float:
    """Published bias constants of the harmonic register estimator."""
    return {16: 0.673, 32: 0.697, 64: 0.709}.get(k, 0.7213 / (1 + 1.079 / k))


def register_estimate(inverse_sum: Column, empty: Column, k: int) -> Column:
    """Harmonic estimate from sum of 2^-register and the number of empty rows; bitmap form while small."""
    raw = F.lit(register_alpha(k) * k * k) / inverse_sum
    return F.when((raw <= 2.5 * k) & (empty > 0), k * F.log(F.lit(float(k)) / F.greatest(empty, F.lit(1)))).otherwise(raw)


def harmonic_rest(c: Column, cells: int) -> Column:
    """cells * (H(cells) - H(cells - c)): the count behind ``c`` of equally likely cells; null when all are full."""
    sum_ = F.aggregate(F.sequence(F.lit(1), F.greatest(c, F.lit(1)).cast("int")), F.lit(0.0), lambda a, i: a + F.lit(1.0) / (F.lit(cells + 1) - i))
    return F.when(c == 0, F.lit(0.0)).when(c < cells, sum_ * cells)


def bitmap_log(c: Column, k: int) -> Column:
    return F.when(c < k, k * F.log(F.lit(float(k)) / (k - c)))


def leftmost_gap(word: Column) -> Column:
    """Collected columns before the first gap of a row."""
    every = F.lit((1 << 63) - 1)
    return F.when(word == every, F.lit(63)).otherwise(F.bit_count(word.bitwiseAND(F.bitwise_not(F.when(word == every, F.lit(0)).otherwise(word) + 1))))


def leftmost_gap_estimate(mean_gap: Column, k: int) -> Column:
    return F.lit(k / GAP_CONSTANT) * F.pow(F.lit(2.0), mean_gap)
