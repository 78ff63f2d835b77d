"""Exact removal of repeated byte strings by a distributed merge sort of suffixes.

A byte goes if a string of ``min_len`` bytes that covers it also starts in a document with a smaller id. Sorting every suffix
of the corpus would move many times the input, so only *anchored* suffixes are sorted: each window of ``min_len`` bytes holds
at least one anchor (a local minimum of the hashes of its ``GRAM``-byte substrings), chosen by the window's bytes alone, so
equal windows hold equal anchors at equal offsets. The steps, each one exchange of messages between blocks of documents and
buckets of anchor hashes:

1. every block sends the distinct anchor hashes it has; a bucket answers with one bit a hash: also in another document?
2. blocks sort the suffixes at anchors that are left, front-code these runs (shared prefix length and the rest) and send them;
3. a bucket merges its runs by a loser tree whose nodes carry the prefix length shared with the last winner: a comparison
   starts behind it and mostly ends at the two lengths. The merged lengths give, for each offset of a window from its anchor,
   classes of equal windows and the smallest document of each;
4. blocks collect the covered intervals and cut them.

Exact copies of whole documents are found first, by digest, and only the first of them takes part. Within a block equal
contexts travel once, with the smallest id, so that a passage in a third of all documents is one entry a block.

Edge cases: null text is empty; texts shorter than ``min_len`` keep all; rows without an id never match and keep all; rows
that repeat an id are cut each by its own text, and only by strictly smaller ids, so never by one another; an empty table gives
an empty result; other columns, whatever their names, pass through unchanged in ``mode="text"`` and are ignored otherwise.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from .common import TextHash, claim, column_bytes, pack_arrays, salted_join, total_bytes, unpack_arrays, unused

GRAM = 24
CHUNK = 1 << 17
BLOCK_MOST = 64 << 20
MESSAGE = "block int, kind int, bucket int, payload binary"
MSG = pa.schema([("block", pa.int32()), ("kind", pa.int32()), ("bucket", pa.int32()), ("payload", pa.binary())])
HASH = TextHash(11)
COPIES, BITS, RUN, CUTS = 0, 1, 2, 3
KEY = "__block"


# ---- anchors -------------------------------------------------------------------------------------------------------------


def _slide(values: np.ndarray, width: int, op) -> np.ndarray:
    out, step = values, 1
    while step * 2 <= width:
        out = op(out[:-step], out[step:])
        step *= 2
    if step < width:
        out = op(out[: len(out) - (width - step)], out[width - step :])
    return out


def anchors(buf: np.ndarray, starts: np.ndarray, min_len: int) -> tuple[np.ndarray, np.ndarray]:
    """Anchor positions in a buffer of joined texts that begin at ``starts``, and the hashes of their grams."""
    n, width = len(buf), min_len - GRAM + 1
    if n < min_len:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    h = HASH.windows(HASH.prefixes(buf), GRAM)
    low = np.maximum(h.astype(np.uint32), 1)  # 0 stands for places that are no gram of one text
    least = np.array(_slide(low, width, np.minimum))
    for s in starts:  # windows across two texts do not count
        least[max(0, s - min_len + 1) : s] = 0
    padded = np.zeros(n - GRAM + width, np.uint32)
    padded[width - 1 : width - 1 + len(least)] = least
    most = _slide(padded, width, np.maximum)
    at = np.flatnonzero(most[: len(low)] == low)
    return at, h[at]


def _chunks(texts: list[bytes], min_len: int) -> Iterator[tuple[list[int], bytes, np.ndarray]]:
    """Texts long enough to match, joined to buffers of about CHUNK bytes: their indexes, the buffer, the starts."""
    some: list[int] = []
    size = 0
    for i, x in enumerate(texts):
        if len(x) >= min_len:
            some.append(i)
            size += len(x)
        if some and (size >= CHUNK or i == len(texts) - 1):
            ends = np.cumsum([len(texts[j]) for j in some])
            yield some, b"".join(texts[j] for j in some), np.r_[0, ends[:-1]].astype(np.int64)
            some, size = [], 0
    if some:
        ends = np.cumsum([len(texts[j]) for j in some])
        yield some, b"".join(texts[j] for j in some), np.r_[0, ends[:-1]].astype(np.int64)


def _block_anchors(texts: list[bytes], min_len: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For all anchors of a block: text index, position in the text, hash."""
    docs, places, hashes = [], [], []
    for some, joined, starts in _chunks(texts, min_len):
        at, h = anchors(np.frombuffer(joined, np.uint8), starts, min_len)
        k = np.searchsorted(starts, at, side="right") - 1
        docs.append(np.array(some)[k])
        places.append(at - starts[k])
        hashes.append(h)
    if not docs:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)
    return np.concatenate(docs), np.concatenate(places), np.concatenate(hashes)


def _bucket_of(h: np.ndarray, buckets: int) -> np.ndarray:
    return ((h >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int64)


def _rows(block: list[int], kind: int, bucket: list[int], payload: list[bytes]) -> pa.Table:
    return pa.table([pa.array(block, pa.int32()), pa.array([kind] * len(block), pa.int32()), pa.array(bucket, pa.int32()), pa.array(payload, pa.binary())], schema=MSG)


class Block:
    """The documents of one block and what came back for it."""

    def __init__(self, table: pa.Table, messages: pa.Table | None, min_len: int, key: str) -> None:
        claim("suffixes")
        self.min_len = min_len
        self.block = table.column(key)[0].as_py() if key in table.column_names else -1
        self.ids = table.column("doc_id").to_pylist()
        self.texts = column_bytes(table.column("text"))
        self.messages = messages
        self.marks = np.zeros(len(self.ids), np.int64)  # tells the texts of a repeated id apart, whatever order rows come in
        rows: dict[int, list[int]] = {}
        for i, d in enumerate(self.ids):
            rows.setdefault(d, []).append(i)
        for same in rows.values():
            if len(same) > 1:
                place = {x: k for k, x in enumerate(sorted({self.texts[i] for i in same}))}
                self.marks[same] = [place[self.texts[i]] for i in same]
        named: dict[int, set[str]] = {}
        if messages is not None:
            for kind, payload in zip(messages.column("kind").to_pylist(), messages.column("payload").to_pylist(), strict=True):
                if kind == COPIES:
                    for entry in payload.decode().split(","):
                        d, digest = entry.split(":")
                        named.setdefault(int(d), set()).add(digest)
        #: whether each row's whole text stands in a document with a smaller id
        self.copy = [d in named and hashlib.sha256(x).hexdigest() in named[d] for d, x in zip(self.ids, self.texts, strict=True)]

    def of_kind(self, kind: int) -> Iterator[tuple[int, bytes]]:
        m = self.messages
        for k, b, p in zip(m.column("kind").to_pylist(), m.column("bucket").to_pylist(), m.column("payload").to_pylist(), strict=True):
            if k == kind:
                yield b, p

    def sources(self) -> list[bytes]:
        """Texts that take part: no copy of an earlier document."""
        return [b"" if copy else x for copy, x in zip(self.copy, self.texts, strict=True)]

    def distinct(self) -> tuple[np.ndarray, ...]:
        doc, at, h = _block_anchors(self.sources(), self.min_len)
        keys, inverse = np.unique(h, return_inverse=True)
        ids = np.array(self.ids, np.int64)[doc] if len(doc) else np.zeros(0, np.int64)
        return doc, at, h, keys, inverse, ids


# ---- step 1: which anchor hashes lie in several documents -----------------------------------------------------------------


def _names(min_len: int, key: str, buckets: int):
    def run(docs: pa.Table, messages: pa.Table) -> pa.Table:
        if not docs.num_rows:
            return MSG.empty_table()
        b = Block(docs, messages, min_len, key)
        _, _, _, keys, inverse, ids = b.distinct()
        low = np.full(len(keys), np.iinfo(np.int64).max)
        high = np.full(len(keys), np.iinfo(np.int64).min)
        np.minimum.at(low, inverse, ids)
        np.maximum.at(high, inverse, ids)
        several = (low != high).astype(np.uint8)
        cuts = np.searchsorted(_bucket_of(keys, buckets), np.arange(buckets + 1))
        out = [(i, pack_arrays((keys[lo:hi] & np.uint64(0xFFFFFFFF)).astype(np.uint32), (keys[lo:hi] >> np.uint64(32)).astype(np.uint32), np.packbits(several[lo:hi]))) for i, (lo, hi) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)) if hi > lo]
        return _rows([b.block] * len(out), BITS, [x[0] for x in out], [x[1] for x in out])

    return run


def _answers(table: pa.Table) -> pa.Table:
    """One bit for each hash of each block: it lies in two documents at least."""
    blocks, bucket = table.column("block").to_pylist(), table.column("bucket")[0].as_py()
    parts, flags = [], []
    for p in table.column("payload").to_pylist():
        lo, hi, several = unpack_arrays(p)
        parts.append(lo.astype(np.uint64) | hi.astype(np.uint64) << np.uint64(32))
        flags.append(np.unpackbits(several)[: len(lo)])
    keys, inverse, count = np.unique(np.concatenate(parts), return_inverse=True, return_counts=True)
    shared = count > 1
    shared[inverse[np.concatenate(flags) > 0]] = True
    bits = shared[inverse]
    cuts = np.cumsum([0] + [len(x) for x in parts])
    return _rows(blocks, BITS, [bucket] * len(blocks), [pack_arrays(np.packbits(bits[lo:hi]), np.array([hi - lo])) for lo, hi in zip(cuts[:-1], cuts[1:], strict=True)])


# ---- step 2: sorted, front-coded runs of suffixes -------------------------------------------------------------------------


def front_code(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted rows of bytes as shared prefix lengths and the rest of each row."""
    if not len(rows):
        return np.zeros(0, np.uint8), np.zeros(0, np.uint8)
    same = rows[1:] == rows[:-1]
    lcp = np.r_[0, np.where(same.all(axis=1), rows.shape[1], same.argmin(axis=1))].astype(np.uint8)
    return lcp, rows[np.arange(rows.shape[1])[None, :] >= lcp[:, None]]


def front_decode(lcp: np.ndarray, rest: np.ndarray, width: int) -> np.ndarray:
    out = np.zeros((len(lcp), width), np.uint8)
    fresh = np.arange(width)[None, :] >= lcp[:, None]
    out[fresh] = rest
    # a byte that a row lacks is that of the last row which has it
    last = np.maximum.accumulate(np.where(fresh, np.arange(len(lcp))[:, None], 0), axis=0)
    return np.take_along_axis(out, last, axis=0) if len(lcp) else out


def _contexts(texts: list[bytes], doc: np.ndarray, at: np.ndarray, min_len: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows of suffix (min_len bytes) then reversed left side (min_len - GRAM bytes), zero padded, and the two real lengths."""
    left = min_len - GRAM
    used, inverse = np.unique(doc, return_inverse=True)
    gap = bytes(min_len)
    joined = np.frombuffer(gap + gap.join(texts[i] for i in used) + gap, np.uint8)
    size = np.array([len(texts[i]) for i in used], np.int64)
    start = np.cumsum(np.r_[0, size[:-1] + min_len]) + min_len if len(used) else np.zeros(0, np.int64)
    here, room = start[inverse] + at, size[inverse] - at
    right = joined[here[:, None] + np.arange(min_len)[None, :]]
    before = joined[here[:, None] - 1 - np.arange(left)[None, :]]
    return np.concatenate([right, before], axis=1), np.minimum(room, min_len).astype(np.uint8), np.minimum(at, left).astype(np.uint8)


def _runs(min_len: int, key: str, buckets: int):
    def run(docs: pa.Table, messages: pa.Table) -> pa.Table:
        if not docs.num_rows:
            return MSG.empty_table()
        b = Block(docs, messages, min_len, key)
        doc, at, h, keys, inverse, ids = b.distinct()
        live = np.zeros(len(keys), bool)
        cuts = np.searchsorted(_bucket_of(keys, buckets), np.arange(buckets + 1))
        for i, p in b.of_kind(BITS):
            bits, n = unpack_arrays(p)
            live[cuts[i] : cuts[i + 1]] = np.unpackbits(bits)[: n[0]].astype(bool)
        keep = live[inverse] if len(keys) else np.zeros(0, bool)
        doc, at, h, ids = doc[keep], at[keep], h[keep], ids[keep]
        marks = b.marks
        sent_blocks, sent_buckets, sent, own = [], [], [], []
        where = _bucket_of(h, buckets)
        order = np.argsort(where, kind="stable")
        edges = np.flatnonzero(np.r_[True, np.diff(where[order]) > 0, True]) if len(order) else np.zeros(1, np.int64)
        for lo, hi in zip(edges[:-1], edges[1:], strict=True):
            part = order[lo:hi]
            rows, right, left = _contexts(b.texts, doc[part], at[part], min_len)
            words = rows.view(np.dtype((np.void, rows.shape[1]))).ravel()
            pick = np.lexsort((at[part], ids[part], right, left, words))
            part, rows, right, left = part[pick], rows[pick], right[pick], left[pick]
            same = (rows[1:] == rows[:-1]).all(axis=1) & (right[1:] == right[:-1]) & (left[1:] == left[:-1])
            new = np.r_[True, ~same]
            group = np.cumsum(new) - 1
            heads = np.flatnonzero(new)
            first = ids[part][heads]
            mine = ids[part] == first[group]  # places in the first document of each context; the others are settled here
            late = np.flatnonzero(~mine)
            if len(late):
                # every window around the anchor also starts in the first document: cut from the leftmost to the rightmost
                q = part[late]
                lo_off = np.maximum(min_len - right[late].astype(np.int64), 0)
                hi_off = left[late].astype(np.int64)
                ok = hi_off >= lo_off
                own.append((ids[q][ok], marks[doc[q]][ok], (at[q] - hi_off)[ok], (at[q] - lo_off + min_len)[ok]))
            lcp, rest = front_code(rows[heads][:, :min_len])
            p = part[mine]
            counts = np.bincount(group[mine], minlength=len(heads))
            sent.append(pack_arrays(lcp, rest, rows[heads][:, min_len:].ravel(), right[heads], left[heads], first, counts.astype(np.int32), at[p].astype(np.int32), marks[doc[p]]))
            sent_blocks.append(b.block)
            sent_buckets.append(int(where[part[0]]))
        out = [_rows(sent_blocks, RUN, sent_buckets, sent)]
        if own:
            cat = [np.concatenate(x) for x in zip(*own, strict=True)]
            out.append(_rows([b.block], CUTS, [0], [pack_arrays(*merge_cuts(*cat))]))
        return pa.concat_tables(out)

    return run


def merge_cuts(ids: np.ndarray, marks: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, ...]:
    """Overlapping or touching intervals of each text as one."""
    if not len(ids):
        return ids, marks, start, end
    o = np.lexsort((start, marks, ids))
    ids, marks, start, end = ids[o], marks[o], start[o], end[o]
    text = np.cumsum(np.r_[0, (ids[1:] != ids[:-1]) | (marks[1:] != marks[:-1])])
    shift = np.int64(1) << 40  # lifts each text above the one before, so one running maximum serves all
    reach = np.maximum.accumulate(end + text * shift)
    new = np.r_[True, start[1:] + text[1:] * shift > reach[:-1]]
    heads = np.flatnonzero(new)
    tails = np.r_[heads[1:] - 1, len(ids) - 1]
    return ids[heads], marks[heads], start[heads], reach[tails] - text[heads] * shift


# ---- step 3: loser tree ---------------------------------------------------------------------------------------------------


def merge_runs(runs: list[tuple[list[int], list[int]]], width: int) -> tuple[list[int], list[int]]:
    """Merge sorted runs of ``width``-byte strings (as integers, with the prefix lengths shared with the string before).

    Returns the order, as run numbers (each run is consumed in turn), and the merged prefix lengths. Each inner node keeps
    the loser and its prefix length with the winner that passed. Of two candidates with unequal lengths the longer one is
    smaller and the loser's length stays; of two equal ones only what lies behind that length is compared.
    """
    bits = 8 * width
    leaves = 1
    while leaves < len(runs):
        leaves *= 2
    end = 1 << (bits + 1)  # above all strings
    heads = [r[0][0] if r[0] else end for r in runs] + [end] * (leaves - len(runs))
    place, sizes = [0] * len(runs), [len(r[0]) for r in runs]
    loser, shared = [0] * leaves, [0] * leaves
    at = [0] * leaves  # prefix length of each head with the last winner

    def build(node: int) -> int:
        if node >= leaves:
            return node - leaves
        a, b = build(2 * node), build(2 * node + 1)
        if heads[b] < heads[a]:
            a, b = b, a
        loser[node] = b
        x = heads[a] ^ heads[b]
        shared[node] = (bits - x.bit_length()) >> 3 if heads[b] != end else -1
        return a

    win = build(1)
    order, lcps = [], []
    total, now = sum(sizes), 0
    for _ in range(total):
        order.append(win)
        lcps.append(now)
        place[win] += 1
        if place[win] < sizes[win]:
            heads[win], l = runs[win][0][place[win]], runs[win][1][place[win]]
        else:
            heads[win], l = end, -1
        node = (win + leaves) >> 1
        while node:
            m = shared[node]
            if m > l:
                loser[node], win = win, loser[node]
                shared[node], l = l, m
            elif m == l and m >= 0:
                other = loser[node]
                x, y = heads[win], heads[other]
                if l < width:
                    common = (bits - (x ^ y).bit_length()) >> 3
                    if y < x:
                        loser[node], win = win, other
                    shared[node] = common
                # equal whole strings: the order between runs is free, both lengths stay
            node >>= 1
        now = l
    return order, lcps


def _resolve(left_rows: np.ndarray, rlen: np.ndarray, llen: np.ndarray, lcp: np.ndarray, ids: np.ndarray, min_len: int) -> tuple[np.ndarray, np.ndarray]:
    """Smallest and largest offset at which the window around each anchor also starts in a smaller document (-1: none)."""
    n, width = len(ids), min_len - GRAM
    low, high = np.full(n, -1, np.int64), np.full(n, -1, np.int64)
    left_id = np.zeros(n, np.int64)
    rank = np.unique(ids, return_inverse=True)[1].astype(np.int64)
    for o in range(width + 1):
        if o:
            left_id = np.unique(left_id << 8 | left_rows[:, o - 1], return_inverse=True)[1].astype(np.int64)
        ok = np.flatnonzero((rlen >= min_len - o) & (llen >= o))
        if len(ok) < 2:
            continue
        right_id = np.cumsum(lcp < min_len - o)[ok]
        key = right_id << 32 | left_id[ok]
        by = np.argsort(key, kind="stable")
        sorted_key = key[by]
        heads = np.flatnonzero(np.r_[True, sorted_key[1:] != sorted_key[:-1]])
        if len(heads) == len(ok):
            continue
        least = np.minimum.reduceat(rank[ok][by], heads)
        sizes = np.diff(np.r_[heads, len(ok)])
        hit = ok[by][rank[ok][by] > np.repeat(least, sizes)]
        high[hit] = o
        fresh = hit[low[hit] < 0]
        low[fresh] = o
    return low, high


def _merge_bucket(min_len: int):
    def run(table: pa.Table) -> pa.Table:
        if table.column("kind")[0].as_py() == CUTS:
            return table.select(MSG.names)
        width = min_len - GRAM
        blocks, runs, raw = table.column("block").to_pylist(), [], []
        for p in table.column("payload").to_pylist():
            lcp, rest, left, rlen, llen, first, counts, at, marks = unpack_arrays(p)
            rows = front_decode(lcp, rest, min_len)
            body = rows.tobytes()
            runs.append(([int.from_bytes(body[i : i + min_len], "big") for i in range(0, len(body), min_len)], lcp.tolist()))
            raw.append((left.reshape(-1, width), rlen, llen, first, counts, at, marks))
        order, lcps = merge_runs(runs, min_len)
        order, lcps = np.array(order, np.int64), np.array(lcps, np.int64)
        base = np.cumsum([0] + [len(r[0]) for r in runs])
        by_run = np.argsort(order, kind="stable")  # the i-th row of a run is its i-th place in the merged order
        flat = np.empty(len(order), np.int64)
        flat[by_run] = np.arange(len(order))
        left, rlen, llen, first, counts = (np.concatenate([x[k] for x in raw]) for k in range(5))
        low, high = _resolve(left[flat], rlen[flat], llen[flat], lcps, first[flat], min_len)
        lo_row, hi_row = np.empty_like(low), np.empty_like(high)
        lo_row[flat], hi_row[flat] = low, high
        out_b, out_p = [], []
        for i, block in enumerate(blocks):
            lo, hi = lo_row[base[i] : base[i + 1]], hi_row[base[i] : base[i + 1]]
            c, at, marks = raw[i][4], raw[i][5], raw[i][6]
            ids, a, z = np.repeat(raw[i][3], c), np.repeat(hi, c), np.repeat(lo, c)
            ok = z >= 0
            if ok.any():
                out_b.append(block)
                out_p.append(pack_arrays(*merge_cuts(ids[ok], marks[ok], at[ok] - a[ok], at[ok] - z[ok] + min_len)))
        return _rows(out_b, CUTS, [0] * len(out_b), out_p)

    return run


# ---- step 4: cut ----------------------------------------------------------------------------------------------------------


def char_spans(text: bytes, spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Spans shrunk to whole UTF-8 characters."""
    out = []
    for s, e in spans:
        while s < e and text[s] & 0xC0 == 0x80:
            s += 1
        while e > s and e < len(text) and text[e] & 0xC0 == 0x80:
            e -= 1
        if e > s:
            out.append((s, e))
    return out


def keep_bytes(text: bytes, spans: list[tuple[int, int]], gap: bytes = b"") -> bytes:
    """What the spans leave; ``gap`` stands where a cut would join two sides into a word that neither had."""
    out, last = [], 0
    for s, e in spans:
        out.append(text[last:s])
        if gap and s and e < len(text) and not text[s - 1 : s].isspace() and not text[e : e + 1].isspace():
            out.append(gap)
        last = e
    out.append(text[last:])
    return b"".join(out)


def _cut(min_len: int, key: str, mode: str, schema: pa.Schema):
    def run(docs: pa.Table, messages: pa.Table | None) -> pa.Table:
        if not docs.num_rows:
            return schema.empty_table()
        b = Block(docs, messages, min_len, key)
        cuts: dict[tuple[int, int], list[tuple[int, int]]] = {}
        parts = [unpack_arrays(p) for _, p in b.of_kind(CUTS)] if messages is not None else []
        if parts:
            merged = merge_cuts(*(np.concatenate(x) for x in zip(*parts, strict=True)))
            for d, m, s, e in zip(*(x.tolist() for x in merged), strict=True):
                cuts.setdefault((d, m), []).append((s, e))
        spans = [([(0, len(x))] if len(x) >= min_len else []) if copy else cuts.get((d, m), []) for d, m, x, copy in zip(b.ids, b.marks.tolist(), b.texts, b.copy, strict=True)]
        if mode == "text":
            kept = [keep_bytes(x, char_spans(x, s), b"\n").decode() for x, s in zip(b.texts, spans, strict=True)]
            kept = [None if old is None else new for old, new in zip(docs.column("text").to_pylist(), kept, strict=True)]
            columns = {n: docs.column(n) for n in schema.names}
            columns["text"] = pa.array(kept, schema.field("text").type)
            if "n_chars" in columns:
                columns["n_chars"] = pa.array([len(x or "") for x in kept], schema.field("n_chars").type)
            return pa.table([columns[n] for n in schema.names], schema=schema)
        return pa.table(
            [
                pa.array(b.ids, pa.int64()), pa.array([len(x) for x in b.texts], pa.int64()), pa.array([sum(e - s for s, e in v) for v in spans], pa.int64()), pa.array([len(v) for v in spans], pa.int64()),
                pa.array([hashlib.sha256(keep_bytes(x, v)).hexdigest() for x, v in zip(b.texts, spans, strict=True)], pa.string()),
            ],
            schema=schema,
        )

    return run


DIGEST_SQL = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
DIGEST = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string())])


def suffix_dedup(docs: DataFrame, min_len: int = 50, mode: str = "digest", block_bytes: int | None = None) -> DataFrame:
    """Cut repeated strings of ``min_len`` bytes out of ``docs`` (doc_id, text, others).

    ``mode="digest"``: doc_id, n_bytes, n_removed, n_spans, kept_sha256 of each row. ``mode="text"``: the rows with their
    text cut (spans shrunk to whole characters, a line break where a cut would join two words) and n_chars set anew. Blocks
    have ``block_bytes`` of text; the default grows with the root of the input, so that neither blocks nor messages become
    too many, up to BLOCK_MOST, which a task must hold. Beyond that there are more blocks, and still as many buckets.
    """
    if min_len < 2 * GRAM:
        raise ValueError(f"min_len must be {2 * GRAM} at least")
    size = total_bytes(docs)
    root = block_bytes or max(4 << 20, int(math.sqrt(size * 1024)))
    blocks, buckets = max(32, math.ceil(size / min(root, BLOCK_MOST))), max(32, math.ceil(size / root))
    key = unused(docs, KEY)
    names = docs.columns if mode == "text" else ["doc_id", "text"]
    block = F.pmod(F.xxhash64(F.col("doc_id").cast("long")), F.lit(blocks)).cast("int")
    known, unknown = docs.where("doc_id is not null"), docs.where("doc_id is null")
    placed = known.select(*(F.col(f"`{c}`") for c in names), block.alias(key))
    digests = known.select(F.col("doc_id").cast("long").alias("doc_id"), F.sha2(F.col("text").cast("binary"), 256).alias("d")).where("d is not null")
    firsts = digests.groupBy("d").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).where("last > first").select("d", "first")
    copies = salted_join(digests, firsts, ["d"], "doc_id").where("doc_id > first")
    copies = copies.select(block.alias("block"), F.concat_ws(":", F.col("doc_id").cast("string"), "d").alias("copy"))
    copies = copies.groupBy("block").agg(F.collect_set("copy").alias("ids")).select("block", F.lit(COPIES).alias("kind"), F.lit(0).alias("bucket"), F.concat_ws(",", "ids").cast("binary").alias("payload"))

    def with_docs(messages: DataFrame, run, schema) -> DataFrame:
        return placed.groupBy(key).cogroup(messages.groupBy("block")).applyInArrow(run, schema)

    shared = with_docs(copies, _names(min_len, key, buckets), MESSAGE).groupBy("bucket").applyInArrow(_answers, MESSAGE)
    runs = with_docs(shared.union(copies), _runs(min_len, key, buckets), MESSAGE)
    # intervals settled inside a block go back as they are, each under a group of its own
    route = F.when(F.col("kind") == RUN, F.col("bucket")).otherwise(-1 - F.col("block"))
    cuts = runs.withColumn("route", route).groupBy("route").applyInArrow(_merge_bucket(min_len), MESSAGE)
    arrow, result = (to_arrow_schema(docs.schema), docs.schema) if mode == "text" else (DIGEST, DIGEST_SQL)
    finish = _cut(min_len, key, mode, arrow)

    def alone(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield from finish(pa.Table.from_batches([batch]), None).to_batches()

    # rows without an id meet nobody: they need no block
    return with_docs(cuts.union(copies), finish, result).union(unknown.select(*(F.col(f"`{c}`") for c in names)).mapInArrow(alone, result))
