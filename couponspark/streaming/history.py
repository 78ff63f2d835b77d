"""History estimates of a stream: state per group holds the words, the sum, and the mass not collected (exact integers).

Rows are taken in arrival order within a micro-batch by ``order``; the result equals the batch estimate if batches arrive so.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from couponspark.functions import hashing as H


class History:
    """The incremental rule on one group."""

    def __init__(self, k: int, columns: int, words: dict[int, int] | None = None, total: float = 0.0, rest: int | None = None) -> None:
        self.k, self.columns, self.words, self.total = k, columns, words or {}, total
        self.rest = k << (columns - 1) if rest is None else rest

    def add(self, row: int, bit: int) -> None:
        old = self.words.get(row, 0)
        if old & bit:
            return
        self.total += (self.k << (self.columns - 1)) / self.rest
        self.rest -= 1 << (self.columns - 1 - min(bit.bit_length(), self.columns - 1))
        self.words[row] = old | bit


def history_stream(stream: DataFrame, ids, key: str, order: Sequence[str], k: int = 1024, profile: str = "fast") -> DataFrame:
    """(key, coupons, estimate) after each micro-batch (update mode)."""
    columns = H.columns_of(profile)
    row, bit = H.coupon(H.typed(stream, ids) if profile == "fast" else ids, k, profile)
    rows = stream.where(H.present(ids)).select(F.col(key).cast("string").alias(key), row.alias("row_id"), bit.alias("bit"), *order)

    def update(group: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        known, total, rest = state.get if state.exists else ([], 0.0, str(k << (columns - 1)))
        h = History(k, columns, {int(known[i]): int(known[i + 1]) for i in range(0, len(known), 2)}, float(total), int(rest))
        firsts = ["row_id", "bit"]
        new: pd.DataFrame | None = None
        for batch in batches:  # at most k * 63 rows are held, whatever the micro-batch has
            batch = batch if new is None else pd.concat([new, batch])
            new = batch.sort_values(list(order), kind="stable").drop_duplicates(firsts)
        for r, b in zip(new["row_id"], new["bit"], strict=True):
            h.add(int(r), int(b))
        state.update(([v for pair in h.words.items() for v in pair], h.total, str(h.rest)))
        yield pd.DataFrame({key: [group[0]], "coupons": [sum(w.bit_count() for w in h.words.values())], "estimate": [h.total]})

    return rows.groupBy(key).applyInPandasWithState(update, f"{key} string, coupons long, estimate double", "words array<long>, total double, rest string", "update", GroupStateTimeout.NoTimeout)
