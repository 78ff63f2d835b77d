"""Simulation of both sketches: discovery sequences to very large counts, and the estimators along them.

Every coupon rings at an exponential time with its own rate; the order of the rings is the order of discovery. The wait for
each novelty is geometric in the mass not yet collected, summed from the far end so that it never cancels. So a run to
counts of k 2^80 costs a sort. Runs are rows of ``spark.range``; each is independent, by its own seed.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from couponspark.functions.solvers import register_alpha

COLUMNS = 96
ESTIMATORS = ("count_inverse", "code_length", "history", "register", "register_code_length", "register_history")


def sequence(k: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Rows, columns (from 1), counts at discovery, and mass before each discovery."""
    p = np.repeat(2.0 ** -np.minimum(np.arange(1, COLUMNS + 1), COLUMNS - 1) / k, k)
    order = np.argsort(rng.exponential(size=len(p)) / p, kind="stable")
    rest = np.cumsum(p[order][::-1])[::-1]
    rest[0] = 1.0
    with np.errstate(divide="ignore"):
        wait = np.ceil(np.log(rng.random(len(p))) / np.where(rest < 1, np.log1p(-np.minimum(rest, 1 - 1e-16)), -np.inf))
    wait = np.maximum(wait, 1.0)
    wait[0] = 1.0
    return order % k, order // k + 1, np.cumsum(wait), rest


def direct(k: int, n: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The same from ``n`` draws, one by one."""
    rows, cols = rng.integers(0, k, n), np.minimum(rng.geometric(0.5, n), COLUMNS)
    _, first = np.unique(rows * 128 + cols, return_index=True)
    first.sort()
    r, c = rows[first], cols[first]
    mass = 2.0 ** -np.minimum(c, COLUMNS - 1) / k
    return r, c, first + 1.0, 1.0 - np.r_[0.0, np.cumsum(mass)[:-1]]


def _log_rest(k: int) -> np.ndarray:
    return np.log1p(-(2.0 ** -np.minimum(np.arange(1, COLUMNS + 1), COLUMNS - 1)) / k)


def invert_counts(c: np.ndarray, k: int) -> np.ndarray:
    l, lo, hi = _log_rest(k), np.zeros(len(c)), np.full(len(c), np.log2(k) + 95)
    for _ in range(60):
        mid = (lo + hi) / 2
        less = -k * np.expm1(2.0 ** mid[:, None] * l).sum(axis=1) < c
        lo, hi = np.where(less, mid, lo), np.where(less, hi, mid)
    return np.where(c > 0, 2.0 ** ((lo + hi) / 2), 0.0)


def shortest_code(s: np.ndarray, k: int) -> np.ndarray:
    """``s``: column sums of each state."""
    l, lo, hi = _log_rest(k), np.zeros(len(s)), np.full(len(s), np.log2(k) + 95)
    for _ in range(60):
        mid = (lo + hi) / 2
        with np.errstate(over="ignore", divide="ignore", invalid="ignore"):
            full = np.where(s > 0, s / np.expm1(-(2.0 ** mid[:, None]) * l), 0.0)
        less = (l * ((k - s) - full)).sum(axis=1) > 0
        lo, hi = np.where(less, mid, lo), np.where(less, hi, mid)
    return 2.0 ** ((lo + hi) / 2)


def likeliest_registers(h: np.ndarray, k: int) -> np.ndarray:
    """``h``: rows with register 0..COLUMNS of each state."""
    l = _log_rest(k)
    later = np.r_[np.cumsum(l[::-1])[::-1], 0.0]
    lo, hi = np.zeros(len(h)), np.full(len(h), np.log2(k) + 95)
    for _ in range(60):
        mid = (lo + hi) / 2
        with np.errstate(over="ignore", divide="ignore", invalid="ignore"):
            own = np.where(h[:, 1:] > 0, h[:, 1:] * l / np.expm1(-(2.0 ** mid[:, None]) * l), 0.0).sum(axis=1)
        less = (h * later).sum(axis=1) - own > 0
        lo, hi = np.where(less, mid, lo), np.where(less, hi, mid)
    return 2.0 ** ((lo + hi) / 2)


def _counts_upto(values: np.ndarray, where: np.ndarray, upto: np.ndarray, size: int) -> np.ndarray:
    """How often each of 0..size-1 occurs among ``values`` whose place in ``where`` (rising) lies before each of ``upto``."""
    order = np.argsort(values.astype(np.int8), kind="stable")
    edges = np.searchsorted(values[order], np.arange(size + 1))
    places = where[order]
    return np.stack([np.searchsorted(places[lo:hi], upto, side="left") for lo, hi in zip(edges[:-1], edges[1:], strict=True)], axis=1).astype(float)


def along(k: int, run: tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray], points: np.ndarray) -> dict[str, np.ndarray]:
    """All six estimates at each count in ``points``."""
    rows, cols, at, rest = run
    upto = np.searchsorted(at, points, side="right")
    occ = _counts_upto(cols - 1, np.arange(len(cols)), upto, COLUMNS)
    history = np.r_[0.0, np.cumsum(1 / rest)]
    # the largest column of each row before each discovery: a running maximum in which later rows start higher
    order = np.argsort(rows.astype(np.int32), kind="stable")
    lifted = np.maximum.accumulate(rows[order] * (COLUMNS + 1) + cols[order])
    before = np.empty(len(cols), np.int64)
    before[order] = np.r_[0, np.maximum(lifted[:-1] - rows[order][1:] * (COLUMNS + 1), 0)]
    up = np.flatnonzero(cols > before)
    old, new = before[up], cols[up]
    hist = _counts_upto(new, up, upto, COLUMNS + 1) - _counts_upto(old, up, upto, COLUMNS + 1)
    hist[:, 0] += k
    # register mass before each rise, summed from the far end so that it never cancels
    loss = 2.0**-old - 2.0**-new
    ends = np.zeros(k, np.int64)
    np.maximum.at(ends, rows, cols)
    mass = (2.0**-ends).sum() + np.cumsum(loss[::-1])[::-1]
    rhistory = np.r_[0.0, np.cumsum(k / mass)][np.searchsorted(up, upto, side="left")]
    inverse = hist @ 2.0 ** -np.arange(COLUMNS + 1)
    raw, empty = register_alpha(k) * k * k / inverse, hist[:, 0]
    register = np.where((raw <= 2.5 * k) & (empty > 0), k * np.log(k / np.maximum(empty, 0.5)), raw)
    return {"register": register, "register_history": rhistory, "count_inverse": invert_counts(occ.sum(axis=1), k), "code_length": shortest_code(occ, k), "register_code_length": likeliest_registers(hist, k), "history": history[upto]}


def simulate(spark: SparkSession, ks: Sequence[int], trials: int, log_from: float, log_to: float, n_points: int, seed: int = 1) -> DataFrame:
    """(k, trial, n, estimator, estimate) at counts k * 2^log_from .. k * 2^log_to."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for k, trial in zip(b["k"], b["trial"], strict=True):
                points = np.floor(k * 2.0 ** np.linspace(log_from, log_to, n_points))
                est = along(int(k), sequence(int(k), np.random.default_rng([seed, int(k), int(trial)])), points)
                yield pd.concat([pd.DataFrame({"k": k, "trial": trial, "n": points, "estimator": name, "estimate": est[name]}) for name in ESTIMATORS])

    tasks = spark.range(trials).withColumnRenamed("id", "trial").crossJoin(spark.createDataFrame([(k,) for k in sorted(ks, reverse=True)], "k long"))
    return tasks.repartition(spark.sparkContext.defaultParallelism * 2).mapInPandas(run, "k long, trial long, n double, estimator string, estimate double")


def simulate_direct(spark: SparkSession, k: int, n: int, trials: int, seed: int = 1) -> DataFrame:
    """(k, trial, n, estimator, estimate) after ``n`` real draws."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for trial in b["id"]:
                est = along(k, direct(k, n, np.random.default_rng([seed, int(trial)])), np.array([float(n)]))
                yield pd.DataFrame({"k": k, "trial": trial, "n": float(n), "estimator": list(ESTIMATORS), "estimate": [est[e][0] for e in ESTIMATORS]})

    return spark.range(trials).repartition(spark.sparkContext.defaultParallelism * 2).mapInPandas(run, "k long, trial long, n double, estimator string, estimate double")


def moments(runs: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """(by.., k, estimator, runs, scaled_error = sqrt(k) RMSE / n, scaled_bias = k bias / n), averaged over counts."""
    r = F.col("estimate") / F.col("n") - 1
    per = runs.groupBy(*by, "k", "estimator").agg(F.count("*").alias("runs"), F.sqrt(F.avg(r * r)).alias("e"), F.avg(r).alias("b"))
    return per.select(*by, "k", "estimator", "runs", (F.sqrt("k") * F.col("e")).alias("scaled_error"), (F.col("k") * F.col("b")).alias("scaled_bias"))


def fit_inverse_k(points: DataFrame, value: str) -> DataFrame:
    """(estimator, c0, c1, c2): least squares of value = c0 + c1/k + c2/k^2; one small row a k and estimator is fitted."""

    def fit(g: pd.DataFrame) -> pd.DataFrame:
        x = 1 / g["k"].to_numpy(float)
        a = np.stack([np.ones_like(x), x, x * x], axis=1)[:, : min(3, len(x))]
        c = np.linalg.lstsq(a, g[value].to_numpy(float), rcond=None)[0]
        c = np.r_[c, np.zeros(3 - len(c))]
        return pd.DataFrame({"estimator": [g["estimator"].iloc[0]], "c0": [c[0]], "c1": [c[1]], "c2": [c[2]]})

    return points.groupBy("estimator").applyInPandas(fit, "estimator string, c0 double, c1 double, c2 double")


def digits_uncertain(runs: DataFrame, log_from: float, log_to: float, folds: int = 10) -> DataFrame:
    """(estimator, c0, digits): the limit by a quadratic fit in 1/k, made anew from each of ``folds`` disjoint stretches of the flat part, and
    how many digits of their mean the spread between them leaves."""
    stretch = F.least(F.floor((F.log2(F.col("n") / F.col("k")) - log_from) / (log_to - log_from) * folds), F.lit(folds - 1)).cast("int")
    parts = moments(runs.withColumn("fold", F.greatest(stretch, F.lit(0))), ["fold"])

    def fit(g: pd.DataFrame) -> pd.DataFrame:
        limits = []
        for _, part in g.groupby("fold"):
            x = 1 / part["k"].to_numpy(float)
            limits.append(np.linalg.lstsq(np.stack([np.ones_like(x), x, x * x], axis=1), part["scaled_error"].to_numpy(float), rcond=None)[0][0])
        mean, error = float(np.mean(limits)), float(np.std(limits, ddof=1) / len(limits) ** 0.5)
        return pd.DataFrame({"estimator": [g["estimator"].iloc[0]], "c0": [mean], "digits": [-np.log10(error / mean)]})

    return parts.groupBy("estimator").applyInPandas(fit, "estimator string, c0 double, digits double")


def sample_state(k: int, n: float, rng: np.random.Generator, columns: int = 63) -> np.ndarray:
    """Row words of a state whose cells are independent: what a large count leaves."""
    q = -np.expm1(n * np.log1p(-(2.0 ** -np.minimum(np.arange(1, columns + 1), columns - 1)) / k))
    bits = rng.random((k, columns)) < q
    return (bits.astype(np.uint64) << np.arange(columns, dtype=np.uint64)).sum(axis=1, dtype=np.uint64).astype(np.int64)
