"""The Arrow path: partitions keep whole sketches in numpy and send them compressed.

Of use only where tasks * groups * k row words would be too many to shuffle; the native path is the default. Updates wait in a
buffer of ``buffer`` coupons and are then or-ed into the state at once.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from couponspark.operators import state
from couponspark.operators.codec import decode_window, encode_window

BUFFER = 2000
HELD = 256 << 20  # bytes of states that a task keeps


class Buffered:
    """One sketch with a buffer of pending (row, bit) updates."""

    def __init__(self, k: int, buffer: int = BUFFER) -> None:
        self.words, self.pending, self.size, self.buffer = np.zeros(k, np.int64), [], 0, buffer

    def add(self, rows: np.ndarray, bits: np.ndarray) -> None:
        self.pending.append((rows, bits))
        self.size += len(rows)
        if self.size >= self.buffer:
            self.flush()

    def flush(self) -> None:
        for rows, bits in self.pending:
            np.bitwise_or.at(self.words, rows, bits)
        self.pending, self.size = [], 0


def partial_sketches(df: DataFrame, ids, by: str, k: int, profile: str = "fast", floor: int = 0, buffer: int = BUFFER) -> DataFrame:
    """(by, body): a compressed sketch of each group in each partition; ``by`` is one column, rendered as text."""
    rows = state.coupon_rows(df, ids, (), k, profile, extra=[F.col(by).cast("string").alias("g")])
    if floor:
        rows = rows.where(F.col("bit") >= F.lit(1 << floor))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict = {}

        def out() -> pa.RecordBatch:
            for sketch in held.values():
                sketch.flush()
            batch = pa.record_batch([pa.array([n[1:] if n else None for n in held], pa.string()), pa.array([encode_window(s.words) for s in held.values()], pa.binary())], names=[by, "body"])
            held.clear()
            return batch

        for batch in batches:
            if len(held) * k * 8 > HELD:  # many groups: what is there goes out, and merges later
                yield out()
            groups = batch.column(0).to_pylist()
            names, code = np.unique(np.array(["" if g is None else "=" + g for g in groups]), return_inverse=True)
            r, b = batch.column(1).to_numpy(zero_copy_only=False), batch.column(2).to_numpy(zero_copy_only=False)
            for i, n in enumerate(names):
                held.setdefault(n, Buffered(k, buffer)).add(r[code == i], b[code == i])
        yield out()

    return rows.select("g", "row_id", "bit").mapInArrow(run, f"{by} string, body binary")


def merge_bodies(parts: DataFrame, by: Sequence[str], fan: int = 64) -> DataFrame:
    """(by.., body) merged in two levels, so that no task gets the bodies of all partitions."""
    schema = ", ".join([*(f"{c} string" for c in by), "bin int, body binary"])

    def merge(table: pa.Table) -> pa.Table:
        words = None
        for b in table.column("body").to_pylist():
            w = decode_window(b)
            words = w if words is None else words | w
        return pa.table([*[table.column(c).slice(0, 1) for c in by], table.column("bin").slice(0, 1), pa.array([encode_window(words)], pa.binary())], names=[*by, "bin", "body"])

    once = parts.withColumn("bin", F.pmod(F.xxhash64("body"), F.lit(fan)).cast("int")).groupBy(*by, "bin").applyInArrow(merge, schema)
    return once.groupBy(*by).applyInArrow(merge, schema).drop("bin")


class Histories:
    """The incremental history of one stream in numpy: state, mass left in exact units, and the sum, a batch at a time."""

    def __init__(self, k: int, columns: int) -> None:
        self.words, self.columns, self.total, self.rest, self.sum = np.zeros(k, np.int64), columns, k << (columns - 1), k << (columns - 1), 0.0

    def add(self, rows: np.ndarray, bits: np.ndarray) -> None:
        """Ids in their order."""
        fresh = np.flatnonzero(self.words[rows] & bits == 0)
        if not len(fresh):
            return
        _, first = np.unique(np.stack([rows[fresh], bits[fresh]]), axis=1, return_index=True)
        for i in fresh[np.sort(first)].tolist():  # novelties only: few once a stream is long
            bit = int(bits[i])
            self.sum += self.total / self.rest
            self.rest -= 1 << (self.columns - 1 - min(bit.bit_length(), self.columns - 1))
            self.words[rows[i]] |= bit


def partition_histories(df: DataFrame, ids, k: int, profile: str = "fast") -> DataFrame:
    """(part, coupons, estimate, body): the history of each partition's ids, in the order that its rows have. Each is the history of
    that part alone; their states merge, their estimates don't."""
    columns = state.H.columns_of(profile)
    rows = state.coupon_rows(df, ids, (), k, profile, extra=[F.spark_partition_id().alias("part")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, part = Histories(k, columns), None
        for batch in batches:
            if batch.num_rows:
                part = batch.column(0)[0].as_py()
                held.add(batch.column(1).to_numpy(zero_copy_only=False).astype(np.int64), batch.column(2).to_numpy(zero_copy_only=False))
        if part is not None:
            coupons = int(np.bitwise_count(held.words.view(np.uint64)).sum())
            yield pa.record_batch([pa.array([part], pa.int32()), pa.array([coupons], pa.int64()), pa.array([held.sum]), pa.array([encode_window(held.words)], pa.binary())], names=["part", "coupons", "estimate", "body"])

    return rows.select("part", "row_id", "bit").mapInArrow(run, "part int, coupons long, estimate double, body binary")
