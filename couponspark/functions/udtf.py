"""Table functions: a packed sketch as coupons, and simulated runs."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from couponspark.operators.codec import decode_window
from couponspark.operators.simulate import ESTIMATORS, along, sequence


@udtf(returnType="row_id: int, col_id: int")
class UnpackSketch:
    """The coupons of one packed sketch."""

    def eval(self, body: bytes):
        if body is None:
            return
        words = decode_window(bytes(body))
        for r in np.flatnonzero(words).tolist():
            w = int(words[r])
            while w:
                low = w & -w
                yield r, low.bit_length()
                w ^= low


@udtf(returnType="trial: int, estimator: string, estimate: double")
class SimulateRuns:
    """Estimates at one count in some runs."""

    def eval(self, k: int, n: float, trials: int):
        for t in range(trials):
            est = along(k, sequence(k, np.random.default_rng([7, k, t])), np.array([float(n)]))
            for name in ESTIMATORS:
                yield t, name, float(est[name][0])


def register(spark: SparkSession) -> None:
    spark.udtf.register("unpack_sketch", UnpackSketch)
    spark.udtf.register("simulate_runs", SimulateRuns)
