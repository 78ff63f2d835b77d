"""Distinct counting in one call."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from couponspark.functions.hashing import columns_of
from couponspark.operators import estimate as E
from couponspark.operators import state

METHODS = ("count_inverse", "code_length", "history", "register", "register_code_length", "register_history", "leftmost_gap", "exact")


def grow(words: DataFrame, df: DataFrame, ids, k: int = 4096, profile: str = "fast") -> DataFrame:
    """The matrix of all that ``words`` have seen and of ``df``: what falls into full columns is dropped before it is aggregated."""
    return state.merge(words, state.row_words(df, ids, (), k, profile, floor=state.saturation_floor(words, k)))


def distinct_estimate(df: DataFrame, ids, by: Sequence[str] = (), k: int = 4096, method: str = "count_inverse", order: Sequence[str] = (), profile: str = "fast", prior: DataFrame | None = None) -> DataFrame:
    """(by.., estimate) of the distinct ids of each group. ``history`` methods need a total ``order``; null ids don't count.

    ``prior``: matrix words (row_id, word) of ids seen before, for the matrix methods without groups. The estimate is of the union;
    columns that are full there are skipped in ``df``, which makes updates cheap once a sketch has seen some k ids (``grow``).
    """
    if method not in METHODS:
        raise ValueError(f"method must be one of {METHODS}")
    if method.endswith("history") and not order:
        raise ValueError("a history needs the order in which ids arrive")
    columns = columns_of(profile)
    if method == "exact":
        cols = [ids] if isinstance(ids, str) else list(ids)
        return df.groupBy(*by).agg(F.count_distinct(*cols).cast("double").alias("estimate"))
    if method.endswith("history"):
        arrivals = state.first_arrivals(df, ids, order, by, k, profile)
        return (E.est_history if method == "history" else E.est_register_history)(arrivals, by, k, columns).select(*by, "estimate")
    if prior is not None and (by or method not in ("count_inverse", "code_length", "leftmost_gap")):
        raise ValueError("prior words go with the matrix methods and without groups")
    words = state.row_words(df, ids, by, k, profile) if prior is None else grow(prior, df, ids, k, profile)
    if method == "count_inverse":
        out = E.est_count_inverse(words, by, k, columns)
    elif method == "code_length":
        out = E.est_code_length(words, by, k, columns)
    elif method == "leftmost_gap":
        out = E.est_leftmost_gap(words, by, k)
    elif method == "register":
        out = E.est_register(state.registers_direct(df, ids, by, k, profile), by, k)
    else:
        out = E.est_register_code_length(state.registers_direct(df, ids, by, k, profile), by, k, columns)
    return out.select(*by, "estimate")
