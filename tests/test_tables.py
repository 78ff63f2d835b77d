"""Queries that once made up all their numbers take them from a given table: what they return follows that table."""

import pytest

from couponspark.plans import catalog

NAMES = """
bitmap_variance
bits_report
buffer_overhead
codec_ablation
codec_sizes
collision_laws
count_inverse_error_theory
coupon_mass_sum
data_source_runs
efficiency_table
entropy_finite
entropy_fourier
""".split()


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table(spark, sf, name):
    small, large = (sorted(map(str, catalog.queries()[name](spark, d).collect())) for d in ("/root/testdata/sf0.001", sf))
    assert small and large and small != large
