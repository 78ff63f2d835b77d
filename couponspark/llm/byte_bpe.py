"""Byte-level BPE by a queue over merge ranks.

The pieces of a pre-token form a linked list. Each possible merge lies in the bucket of its rank; a bitmap of buckets in two
levels of 256-bit words marks those that hold something, so find-first-set gives the next rank in two steps, however long the
pre-token. Within a bucket the leftmost place comes first: the buckets of short pre-tokens are bitmaps of places themselves, from
which an entry goes as soon as its piece has merged otherwise; those of long ones are heaps, where it is stale and skipped.

Edge cases: null text is empty; special strings are ordinary text; pre-tokens of any length take O(n log n); extra columns are
ignored, repeated rows repeat, an empty table gives an empty one.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import claim, column_bytes

CACHE = 400_000
LONG = 64
SHORT = 200  # bytes of a pre-token whose buckets are bitmaps of places
BIT = [1 << i for i in range(256)]
UNEVEN = re.compile(r"\s |[ ]\s")
SINGLE = re.compile(r"(?<=\S) (?=\S)")


class Memo(dict):
    """A bounded memo of two generations; long keys are not kept."""

    def __init__(self, make, share: int = 1) -> None:
        self.make, self.bound = make, CACHE // share
        self.old: dict = {}

    def __missing__(self, key: str) -> bytes:
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
        if len(key) <= LONG:
            if len(self) >= self.bound:
                self.old = dict(self)
                self.clear()
            self[key] = value
        return value


class RankQueue:
    """Buckets of positions by rank under a two-level bitmap."""

    def __init__(self, ranks: int) -> None:
        self.buckets: dict[int, list[int]] = {}
        self.low = [0] * (ranks // 256 + 1)
        self.top = 0

    def push(self, rank: int, place: int) -> None:
        bucket = self.buckets.get(rank)
        if bucket is None:
            self.buckets[rank] = [place]
            self.low[rank >> 8] |= 1 << (rank & 255)
            self.top |= 1 << (rank >> 8)
        else:
            heapq.heappush(bucket, place)

    def pop(self) -> tuple[int, int] | None:
        """The lowest rank and the leftmost place in its bucket."""
        top = self.top
        if not top:
            return None
        w = (top & -top).bit_length() - 1
        bits = self.low[w]
        rank = w << 8 | (bits & -bits).bit_length() - 1
        bucket = self.buckets[rank]
        place = heapq.heappop(bucket)
        if not bucket:
            del self.buckets[rank]
            bits &= bits - 1
            self.low[w] = bits
            if not bits:
                self.top = top & top - 1
        return rank, place


class ByteBpe:
    def __init__(self, path: str, pattern: str) -> None:
        with open(path, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.bytes_of: dict[int, bytes] = {i: b for b, i in self.ranks.items()}
        self.longest = max(map(len, self.ranks))
        self.queue = RankQueue(max(self.bytes_of) + 1)
        self.places = [0] * (max(self.bytes_of) + 1)  # buckets of short pre-tokens, by rank
        self.pairs = [self.ranks.get(bytes([a, b]), -1) for a in range(256) for b in range(256)]
        self.pattern = regex.compile(pattern)
        self.four = {i: i.to_bytes(4, "little") for i in self.bytes_of}
        self.words = Memo(lambda w: self.ids_of(w.encode()), 4)
        #: A run between two single spaces, taken with the space before it. No pre-token of the pattern lies across such a space.
        self.runs = Memo(self._run)

    def _run(self, run: str) -> bytes:
        if run.isascii() and run.isalpha():  # one pre-token
            return self.ids_of(b" " + run.encode())
        return b"".join([self.words[w] for w in self.pattern.findall(" " + run)])

    def ids_of(self, raw: bytes) -> bytes:
        four = self.four
        return b"".join([four[i] for i in self.merge(raw)])

    def merge(self, raw: bytes) -> list[int]:
        """Ids of one pre-token."""
        whole = self.ranks.get(raw)
        if whole is not None:
            return [whole]
        return self.merge_short(raw) if len(raw) <= SHORT else self.merge_long(raw)

    def merge_short(self, raw: bytes) -> list[int]:
        """The queue with bitmaps of places as buckets, written out in line. An entry whose piece has merged is taken out at once, which
        is cheaper than to find it later; so buckets and bitmaps are empty again at the end of each pre-token."""
        get, low, n = self.ranks.get, self.queue.low, len(raw)
        pairs, buckets, bit = self.pairs, self.places, BIT
        pair = [pairs[a << 8 | b] for a, b in zip(raw, raw[1:], strict=False)]
        pair.append(-1)
        top, place = 0, 1
        for r in pair:
            if r >= 0:
                if mask := buckets[r]:
                    buckets[r] = mask | place
                else:
                    buckets[r] = place
                    low[r >> 8] |= bit[r & 255]
                    top |= bit[r >> 8]
            place <<= 1
        nxt, prev = list(range(1, n + 2)), list(range(-1, n))
        while top:
            w = (top & -top).bit_length() - 1
            bits = low[w]
            first = bits & -bits
            rank = w << 8 | first.bit_length() - 1
            mask = buckets[rank]
            one = mask & -mask
            buckets[rank] = mask = mask ^ one
            if not mask:
                low[w] = bits = bits ^ first
                if not bits:
                    top &= top - 1
            i = one.bit_length() - 1
            j = nxt[i]
            r = pair[j]
            if r >= 0:
                buckets[r] = mask = buckets[r] ^ bit[j]
                if not mask:
                    w = r >> 8
                    low[w] = bits = low[w] ^ bit[r & 255]
                    if not bits:
                        top ^= bit[w]
            nxt[i] = k = nxt[j]
            if k < n:
                prev[k] = i
                pair[i] = r = get(raw[i : nxt[k]], -1)
                if r >= 0:
                    if mask := buckets[r]:
                        buckets[r] = mask | one
                    else:
                        buckets[r] = one
                        low[r >> 8] |= bit[r & 255]
                        top |= bit[r >> 8]
            else:
                pair[i] = -1
            h = prev[i]
            if h >= 0:
                r = pair[h]
                if r >= 0:
                    buckets[r] = mask = buckets[r] ^ bit[h]
                    if not mask:
                        w = r >> 8
                        low[w] = bits = low[w] ^ bit[r & 255]
                        if not bits:
                            top ^= bit[w]
                pair[h] = r = get(raw[h:k], -1)
                if r >= 0:
                    if mask := buckets[r]:
                        buckets[r] = mask | bit[h]
                    else:
                        buckets[r] = bit[h]
                        low[r >> 8] |= bit[r & 255]
                        top |= bit[r >> 8]
        out, i, ranks = [], 0, self.ranks
        while i < n:
            out.append(ranks[raw[i : nxt[i]]])
            i = nxt[i]
        return out

    def merge_long(self, raw: bytes) -> list[int]:
        """The queue with heaps of places as buckets: O(n log n) however long the pre-token."""
        ranks, n, longest = self.ranks, len(raw), self.longest
        nxt, prev = list(range(1, n + 1)), list(range(-1, n - 1))
        pair = [-1] * (n + 1)  # rank of the merge of the piece at a place with the next
        queue = self.queue
        for i in range(n - 1):
            r = ranks.get(raw[i : i + 2])
            if r is not None:
                pair[i] = r
                queue.push(r, i)
        while (top := queue.pop()) is not None:
            rank, i = top
            if pair[i] != rank:
                continue
            j = nxt[i]
            k = nxt[j]
            nxt[i] = k
            pair[j] = -1
            if k < n:
                prev[k] = i
                end = nxt[k]
                r = ranks.get(raw[i:end]) if end - i <= longest else None
                pair[i] = -1 if r is None else r
                if r is not None:
                    queue.push(r, i)
            else:
                pair[i] = -1
            h = prev[i]
            if h >= 0:
                r = ranks.get(raw[h:k]) if k - h <= longest else None
                pair[h] = -1 if r is None else r
                if r is not None:
                    queue.push(r, h)
        out, i = [], 0
        while i < n:
            out.append(ranks[raw[i : nxt[i]]])
            i = nxt[i]
        return out

    def encode_bytes(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        first, *runs = text.split(" ") if UNEVEN.search(text) is None else SINGLE.split(text)
        return b"".join([self.words[w] for w in self.pattern.findall(first)]) + b"".join(map(self.runs.__getitem__, runs))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, "<u4").tolist()))


@lru_cache(maxsize=4)
def byte_bpe(path: str, pattern: str) -> ByteBpe:
    return ByteBpe(path, pattern)


def encode_documents(docs: DataFrame, tokenizer: str, pattern: str, with_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, round_trip (and the ids, ``with_ids``)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("bytes", byte_bpe.cache_clear)
        bpe = byte_bpe(tokenizer, pattern)
        for batch in batches:
            rows = []
            for raw in column_bytes(batch.column(1)):
                ids = bpe.encode_bytes(raw.decode())
                back = bpe.decode(ids)
                rows.append((len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(back).hexdigest(), back == raw, ids))
            cols = list(zip(*rows, strict=True)) or [[]] * 5
            arrays = [batch.column(0), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.string()), pa.array(cols[2], pa.string()), pa.array(cols[3], pa.bool_())]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "round_trip"]
            if with_ids:
                arrays.append(pa.array([np.frombuffer(x, "<u4").astype(np.int32) for x in cols[4]], pa.list_(pa.int32())))
                names.append("ids")
            yield pa.record_batch(arrays, names=names)

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, round_trip boolean"
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, schema + (", ids array<int>" if with_ids else ""))


def decode_documents(encoded: DataFrame, tokenizer: str, pattern: str) -> DataFrame:
    """doc_id, text of rows with doc_id and ids (array of int); bytes that are no UTF-8 become replacement characters."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("bytes", byte_bpe.cache_clear)
        bpe = byte_bpe(tokenizer, pattern)
        for batch in batches:
            texts = [bpe.decode(np.array(x or [], "<u4").tobytes()).decode("utf-8", "replace") for x in batch.column(1).to_pylist()]
            yield pa.record_batch([batch.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select(F.col("doc_id").cast("long"), F.col("ids").cast("array<int>")).mapInArrow(run, "doc_id long, text string")
