"""Sum-of-squares packing of token sequences.

Documents come in turn. Each is cut into whole windows and a rest; the rest goes into the fill level for which the sum of
squares of the numbers of open windows at each level grows least, tracked in an array of levels. That keeps the levels even,
so that most windows can be filled exactly. What is open at the end of a task is cut once more: the emptiest windows fill the
gaps of the fullest, and the last one falls into windows of powers of two, which need no padding. A task holds the ids of
open windows only. Each task packs what it reads, so nothing is shuffled; sequence ids hold the task's number in their high bits.

Edge cases: null text is empty and gives one piece, its end id; an empty table gives an empty result; repeated rows are packed
each; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import claim, column_bytes, give_back, slices
from .word_bpe import id_bpe

Piece = tuple  # doc_id, start, ids (bytes), tokens of the document


class Packer:
    """Online packing of one stream of documents; ``done`` gathers closed pieces."""

    def __init__(self, capacity: int, first_sequence: int = 0, with_ids: bool = True) -> None:
        self.capacity, self.with_ids = capacity, with_ids
        self.open = np.zeros(capacity + 1, np.int64)
        self.bins: list[list[list[Piece]]] = [[] for _ in range(capacity + 1)]
        self.sequence = first_sequence
        self.done: list[tuple] = []

    def level_for(self, size: int) -> int:
        """Fill level of the window that takes ``size`` tokens; 0 for a new one. Equal costs go to the fullest window."""
        c, n = self.capacity, self.open
        best, cost = 0, 2 * int(n[size]) + 1
        if n[c - size] and (exact := 1 - 2 * int(n[c - size])) <= cost:
            best, cost = c - size, exact
        here = n[1 : c - size]
        if len(here) and (there := np.flatnonzero(here)).size:
            change = 2 * (n[there + 1 + size] - here[there]) + 2
            k = len(change) - 1 - int(np.argmin(change[::-1]))
            if change[k] < cost or (change[k] == cost and there[k] + 1 > best):
                best = int(there[k]) + 1
        return best

    def close(self, pieces: list[Piece]) -> None:
        at = 0
        for doc, start, ids, total in pieces:
            n = len(ids) // 4
            self.done.append((doc, start, n, zlib.crc32(ids), total, self.sequence, at, ids if self.with_ids else None))
            at += n
        self.sequence += 1

    def add(self, doc, ids: bytes) -> None:
        c, total = self.capacity, len(ids) // 4
        whole = total - total % c
        for s in range(0, whole, c):
            self.close([(doc, s, ids[4 * s : 4 * (s + c)], total)])
        size = total - whole
        if not size:
            return
        level = self.level_for(size)
        pieces = self.bins[level].pop() if level else []
        self.open[level] -= 1 if level else 0
        pieces.append((doc, whole, ids[4 * whole :], total))
        if level + size == c:
            self.close(pieces)
        else:
            self.open[level + size] += 1
            self.bins[level + size].append(pieces)

    def finish(self) -> None:
        """Close what is open: cut again, without padding."""
        rest = [(level, b) for level in range(self.capacity, 0, -1) for b in self.bins[level]]
        self.open[:] = 0
        self.bins = [[] for _ in range(self.capacity + 1)]
        lo, hi = 0, len(rest) - 1
        spare: list[Piece] = []  # pieces of the emptiest window, to be used up first
        while lo <= hi:
            level, pieces = rest[lo]
            lo += 1
            while level < self.capacity and (spare or lo <= hi):
                if not spare:
                    spare = rest[hi][1][::-1]
                    hi -= 1
                doc, start, ids, total = spare.pop()
                n = min(len(ids) // 4, self.capacity - level)
                pieces.append((doc, start, ids[: 4 * n], total))
                level += n
                if len(ids) > 4 * n:
                    spare.append((doc, start + n, ids[4 * n :], total))
            if level == self.capacity:
                self.close(pieces)
            else:
                self._powers(pieces[::-1])
        while spare:
            pieces, level = [], 0
            while spare and level < self.capacity:
                doc, start, ids, total = spare.pop()
                n = min(len(ids) // 4, self.capacity - level)
                pieces.append((doc, start, ids[: 4 * n], total))
                level += n
                if len(ids) > 4 * n:
                    spare.append((doc, start + n, ids[4 * n :], total))
            if level == self.capacity:
                self.close(pieces)
            else:
                self._powers(pieces[::-1])

    def _powers(self, spare: list[Piece]) -> None:
        """The last tokens, as windows of powers of two (``spare`` is a stack)."""
        left = sum(len(p[2]) // 4 for p in spare)
        while left:
            room = 1 << left.bit_length() - 1
            left -= room
            pieces = []
            while room:
                doc, start, ids, total = spare.pop()
                n = min(len(ids) // 4, room)
                pieces.append((doc, start, ids[: 4 * n], total))
                room -= n
                if len(ids) > 4 * n:
                    spare.append((doc, start + n, ids[4 * n :], total))
            self.close(pieces)


FIELDS = [("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64())]
COLUMNS = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def _batch(done: list[tuple], with_ids: bool) -> pa.RecordBatch:
    cols = list(zip(*done, strict=True)) if done else [[] for _ in range(8)]
    arrays = [pa.array(c, t) for c, (_, t) in zip(cols, FIELDS, strict=False)]
    names = [n for n, _ in FIELDS]
    if with_ids:
        arrays.append(pa.array([np.frombuffer(x, "<u4").astype(np.int32) for x in cols[7]], pa.list_(pa.int32())))
        names.append("ids")
    return pa.record_batch(arrays, names=names)


def pack_documents(docs: DataFrame, tokenizer: str, capacity: int = 4096, end_id: int = 2, with_ids: bool = False) -> DataFrame:
    """One row a piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset (and the ids, ``with_ids``)."""
    end = end_id.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("ids", id_bpe.cache_clear)
        bpe, packer = id_bpe(tokenizer), Packer(capacity, TaskContext.get().partitionId() << 40, with_ids)
        give_back()
        for batch in slices(batches):
            for doc, text in zip(batch.column(0).to_pylist(), column_bytes(batch.column(1)), strict=True):
                packer.add(doc, bpe.encode_bytes(text.decode()) + end)
            yield _batch(packer.done, with_ids)
            packer.done = []
        packer.finish()
        yield _batch(packer.done, with_ids)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, COLUMNS + (", ids array<int>" if with_ids else ""))
