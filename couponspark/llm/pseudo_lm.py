"""Pseudo-likelihood of texts under a bidirectional window network.

Every word is predicted from two words on each side: the contexts' vectors add up to a hidden layer, whose output is a
distribution over classes of words, and, inside a class of frequent words, another over its words. The ``OWN_CLASS`` most
frequent words are classes by themselves; the next ``GROUPS * GROUP`` lie in groups that the network tells apart; all others lie in
bands of equal mass, where a word has its share of the band by corpus counts. The sum of the conditional log probabilities of
all words scores a text.

What the model knows comes from the whole corpus. The exact count of each word is a row of a distributed table that grows with
the corpus, in parts by hash; a block of documents asks it for the words that it holds. Only the network's inputs are hashed: beyond the
``OWN_CONTEXT`` most frequent words, words beside the one predicted share slots. Texts are dealt over shards by their hash, so that
neither shards nor results depend on how the input is split. The network starts from the first words of one shard; then the shards
of each round train copies of it, which are averaged by their words. A last pass scores.

Edge cases: null or blank text has no words, sum 0 and no mean; a corpus without words gives each text 0; a word that the corpus
does not hold counts half; a very long text is a block of its own; extra columns are ignored; repeated rows repeat; an empty table
gives an empty one.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import TextHash, claim, column_bytes, mark, pack_arrays, stage, sweep, total_bytes, unpack_arrays

BUCKETS = 1 << 16  # of the network's inputs only
OWN_CLASS, GROUPS, GROUP, BANDS = 32, 32, 64, 32
CLASSES, TOP = OWN_CLASS + GROUPS + BANDS, OWN_CLASS + GROUPS * GROUP
RARE, ONCE = -1, -2  # in place of a word's place in its group: words of a band, and those that the corpus holds once
CONTEXTS, OWN_CONTEXT = 1024, 768
HIDDEN, SIDES = 16, (-2, -1, 1, 2)
BATCH = 8192
PORTION = 1 << 18  # words whose windows are laid out at once
BLOCK = 4 << 20  # bytes of text that ask for their words together
SHARE = 16 << 20  # bytes of text for each part of the word table
SHARD, SHARDS = 8 << 20, 4  # bytes of text that train one copy; least number of shards
START_WORDS, START_SEEN, START_PASSES = 1 << 19, 3 << 19, 12  # the common start: different words, words in all passes, most passes
ROUNDS = 2  # averages; each shard takes part in one
SLICES, FAN = 16, 256
HASH = TextHash(31)
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True


def split(texts: list[bytes]) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """The distinct words of all texts, the number among them of each word, and how many words each text has."""
    buf = np.frombuffer(b" ".join(texts) + b" ", np.uint8)
    gap = _SPACE[buf]
    word = ~gap
    start = np.flatnonzero(word & np.r_[True, gap[:-1]])
    end = np.flatnonzero(gap & np.r_[False, word[:-1]])
    sizes = np.diff(np.r_[0, np.searchsorted(start, np.cumsum([len(t) + 1 for t in texts]))]) if texts else np.zeros(0, np.int64)
    offsets = np.r_[0, np.cumsum(end - start)].astype(np.int64)
    all_words = pa.Array.from_buffers(pa.large_binary(), len(start), [None, pa.py_buffer(offsets), pa.py_buffer(buf[word])])
    coded = all_words.dictionary_encode()
    return coded.dictionary, coded.indices.to_numpy().astype(np.int64), sizes.astype(np.int64)


def spans(words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all words, and where each ends."""
    at = np.frombuffer(words.buffers()[1], np.int64)[words.offset : words.offset + len(words) + 1] if len(words) else np.zeros(1, np.int64)
    return (np.frombuffer(words.buffers()[2], np.uint8)[at[0] : at[-1]] if at[-1] > at[0] else np.zeros(0, np.uint8)), at[1:] - at[0]


def hashes(words: pa.Array) -> np.ndarray:
    buf, ends = spans(words)
    out, lo = [np.zeros(0, np.uint64)], 0
    while lo < len(ends):
        first = int(ends[lo - 1]) if lo else 0
        hi = max(lo + 1, int(np.searchsorted(ends, first + (1 << 18), "right")))
        near = np.r_[first, ends[lo:hi]] - first
        out.append(HASH.spans(HASH.prefixes(buf[first : int(ends[hi - 1])]), near[:-1], near[1:]))
        lo = hi
    return np.concatenate(out)


def tokenize(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Input bucket of each word of all texts, and how many words each text has."""
    words, ids, sizes = split(texts)
    return (hashes(words) % np.uint64(BUCKETS)).astype(np.int64)[ids], sizes


@dataclass
class Lexicon:
    """Classes, shares and context numbers of words, from their exact counts. Nothing here grows with the corpus but ``level``
    and ``above``, which have an entry for each count that some word has."""

    top: list[bytes]  # the TOP most frequent words
    level: np.ndarray  # counts that words beyond these have, falling
    above: np.ndarray  # words in the text that belong to larger counts than the level, and to all at the end
    total: np.ndarray | None = None  # of each class
    inner: np.ndarray | None = None  # counts of the words of the groups

    def klass(self, words: pa.Array, counts: np.ndarray) -> np.ndarray:
        """Of distinct words: the most frequent have their own, the next ones lie in groups; all others lie in bands of about equal mass by falling count, equal counts by hash."""
        rank = self.rank(words)
        part = (hashes(words) >> np.uint64(40)).astype(np.float64) / (1 << 24)
        at = np.searchsorted(-self.level, -counts)
        lo, hi = self.above[np.minimum(at, len(self.level))], self.above[np.minimum(at + 1, len(self.level))]
        band = ((lo + part * (hi - lo)) / max(self.above[-1], 1) * BANDS).astype(np.int64)
        band = OWN_CLASS + GROUPS + np.clip(band, 0, BANDS - 1)
        return np.where(rank < OWN_CLASS, rank, np.where(rank < TOP, OWN_CLASS + (rank - OWN_CLASS) // GROUP, band))

    def place(self, words: pa.Array, counts: np.ndarray) -> np.ndarray:
        """Place in the group; RARE or ONCE of words in bands; 0 of words that are a class."""
        rank = self.rank(words)
        return np.where(rank < OWN_CLASS, 0, np.where(rank < TOP, (rank - OWN_CLASS) % GROUP, np.where(counts == 1, ONCE, RARE)))

    def rank(self, words: pa.Array) -> np.ndarray:
        found = pc.index_in(words, value_set=pa.array(self.top, pa.large_binary()))
        return pc.fill_null(found, len(self.top) + BUCKETS).to_numpy(zero_copy_only=False).astype(np.int64)

    def log_share(self, klass: np.ndarray, counts: np.ndarray) -> np.ndarray:
        return np.log(np.maximum(counts, 0.5) / np.maximum(self.total[klass], 0.5)).astype(np.float32)

    @property
    def log_prior(self) -> np.ndarray:
        weight = np.maximum(self.total, 0.5)
        return np.log(weight / weight.sum()).astype(np.float32)

    def context(self, words: pa.Array) -> np.ndarray:
        rank = self.rank(words)
        slot = (hashes(words) % np.uint64(BUCKETS)).astype(np.int64) % (CONTEXTS - OWN_CONTEXT)
        return np.where(rank < OWN_CONTEXT, rank, OWN_CONTEXT + slot)


def windows(ids: np.ndarray, sizes: np.ndarray, context: np.ndarray) -> np.ndarray:
    """Context numbers beside every word; CONTEXTS beyond a text's ends."""
    # texts laid end to end with a gap as wide as the farthest side between them
    gap = max(map(abs, SIDES))
    at = np.arange(len(ids)) + gap * (np.repeat(np.arange(len(sizes)), sizes) + 1)
    padded = np.full(len(ids) + gap * (len(sizes) + 1), CONTEXTS, np.int64)
    padded[at] = context[ids]
    return np.stack([padded[at + d] for d in SIDES])


class Net:
    SHAPES = (("side", (len(SIDES), CONTEXTS + 1, HIDDEN)), ("hide", (HIDDEN,)), ("out", (HIDDEN, CLASSES)), ("bias", (CLASSES,)), ("inner", (GROUPS, HIDDEN, GROUP)), ("inner_bias", (GROUPS, GROUP)))
    SIZE = sum(int(np.prod(s)) for _, s in SHAPES)

    def __init__(self, flat: np.ndarray) -> None:
        self.flat = flat.astype(np.float32)
        self.views(self.flat, self)

    @staticmethod
    def views(flat: np.ndarray, on) -> None:
        """The parts of a flat array of weights, as attributes."""
        at = 0
        for name, shape in Net.SHAPES:
            n = int(np.prod(shape))
            setattr(on, name, flat[at : at + n].reshape(shape))
            at += n

    @staticmethod
    def start(lexicon: Lexicon, seed: int = 1) -> Net:
        net = Net(np.random.default_rng(seed).standard_normal(Net.SIZE) * 0.1)
        net.bias[:] = lexicon.log_prior
        net.hide[:] = 0
        net.inner_bias[:] = np.log(np.maximum(lexicon.inner, 0.5)).astype(np.float32)
        return net

    def hidden(self, around: np.ndarray) -> np.ndarray:
        h = self.hide + self.side[0][around[0]]
        for k in range(1, len(SIDES)):
            h += self.side[k][around[k]]
        return np.tanh(h, out=h)

    def grouped(self, klass: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        """Rows whose word lies in each group."""
        order = np.argsort(klass.astype(np.int16), kind="stable")
        edges = np.searchsorted(klass[order], np.arange(OWN_CLASS, OWN_CLASS + GROUPS + 1))
        for g in np.flatnonzero(np.diff(edges)).tolist():
            yield g, order[edges[g] : edges[g + 1]]

    def learn(self, around: np.ndarray, klass: np.ndarray, place: np.ndarray, rate: float, memory: np.ndarray) -> None:
        """One Adagrad pass over the words given, in batches."""
        flat = np.empty(self.SIZE, np.float32)
        grad = SimpleNamespace()
        self.views(flat, grad)
        for lo in range(0, len(klass), BATCH):
            a, y, z = around[:, lo : lo + BATCH], klass[lo : lo + BATCH], place[lo : lo + BATCH]
            flat[:] = 0
            h = self.hidden(a)
            part = h * np.float32(1 / len(y))  # the mean over the batch
            d = _surplus(h, self.out, self.bias, y)
            back = d @ self.out.T
            np.matmul(part.T, d, out=grad.out)
            grad.bias[:] = d.sum(axis=0) / len(y)
            for g, rows in self.grouped(y):
                e = _surplus(h[rows], self.inner[g], self.inner_bias[g], z[rows])
                back[rows] += e @ self.inner[g].T
                np.matmul(part[rows].T, e, out=grad.inner[g])
                grad.inner_bias[g] = e.sum(axis=0) / len(y)
            h *= h
            back *= (1 - h) / np.float32(len(y))
            grad.hide[:] = back.sum(axis=0)
            for k in range(len(SIDES)):
                order = np.argsort(a[k].astype(np.int16), kind="stable")
                slots, heads = np.unique(a[k][order], return_index=True)
                grad.side[k][slots] = np.add.reduceat(back[order], heads, axis=0)
            memory += flat * flat
            self.flat -= rate * flat / (np.sqrt(memory) + 1e-6)

    def log_probability(self, context: np.ndarray, sizes: np.ndarray, klass: np.ndarray, place: np.ndarray, log_share: np.ndarray) -> np.ndarray:
        """Of each word given both its sides."""
        around = windows(context, sizes, np.arange(CONTEXTS))
        out = np.where(place < 0, log_share, 0).astype(np.float32)
        for lo in range(0, len(klass), BATCH):
            y, z, here = klass[lo : lo + BATCH], place[lo : lo + BATCH], out[lo : lo + BATCH]
            h = self.hidden(around[:, lo : lo + BATCH])
            here += _chosen(h, self.out, self.bias, y)
            for g, rows in self.grouped(y):
                here[rows] += _chosen(h[rows], self.inner[g], self.inner_bias[g], z[rows])
        return out


def _surplus(h: np.ndarray, out: np.ndarray, bias: np.ndarray, target: np.ndarray) -> np.ndarray:
    """Softmax of each row, less one at its target."""
    p = h @ out
    p += bias
    p -= p.max(axis=1, keepdims=True)
    np.exp(p, out=p)
    p *= 1 / p.sum(axis=1, keepdims=True)
    p[np.arange(len(p)), target] -= 1
    return p


def _chosen(h: np.ndarray, out: np.ndarray, bias: np.ndarray, target: np.ndarray) -> np.ndarray:
    """Log probability of each row's target."""
    logit = h @ out
    logit += bias
    logit -= logit.max(axis=1, keepdims=True)
    own = logit[np.arange(len(logit)), target]
    return own - np.log(np.exp(logit, out=logit).sum(axis=1))


# ---- the corpus -----------------------------------------------------------------------------------------------------------

MESSAGE = "slice int, part int, payload binary"


def _message(values: np.ndarray, weight: float, part: int) -> pa.RecordBatch:
    pieces = np.array_split(values, SLICES)
    return pa.record_batch([pa.array(range(SLICES), pa.int32()), pa.array([part] * SLICES, pa.int32()), pa.array([pack_arrays(p.astype(np.float64), np.array([weight])) for p in pieces], pa.binary())], names=["slice", "part", "payload"])


def _add(table: pa.Table) -> pa.Table:
    total, weight = None, 0.0
    for _, p in sorted(zip(table.column("part").to_pylist(), table.column("payload").to_pylist(), strict=True), key=lambda x: x[0]):  # sums don't depend on the order of arrival
        v, w = unpack_arrays(p)
        total = v.copy() if total is None else total + v
        weight += float(w[0])
    return pa.table([pa.array([table.column("slice")[0].as_py()], pa.int32()), pa.array([table.column("part")[0].as_py() // FAN], pa.int32()), pa.array([pack_arrays(total, np.array([weight]))], pa.binary())], names=["slice", "part", "payload"])


def _sum(messages: DataFrame, parts: int) -> tuple[np.ndarray, float]:
    """Sum of what all shards sent: in levels, each of at most FAN messages a task; a fixed number of floats returns."""
    while True:
        messages = messages.withColumn("bin", F.expr(f"part div {FAN}")).groupBy("slice", "bin").applyInArrow(_add, MESSAGE)
        parts = -(-parts // FAN)
        if parts == 1:
            break
    got = {r["slice"]: unpack_arrays(bytes(r["payload"])) for r in messages.collect()}
    return (np.concatenate([got[i][0] for i in range(SLICES)]), float(got[0][1][0])) if got else (np.zeros(0), 0.0)


PACKED = "shard int, block long, docs binary, words binary"


def pack_words(words: pa.Array, *more: np.ndarray) -> bytes:
    buf, ends = spans(words)
    return pack_arrays(buf, np.diff(ends, prepend=0).astype(np.int32), *more)


def unpack_words(message: bytes) -> list:
    """The words as an Arrow array, then the arrays that lie with them."""
    raw, sizes, *more = unpack_arrays(message)
    return [pa.Array.from_buffers(pa.large_binary(), len(sizes), [None, pa.py_buffer(np.r_[0, np.cumsum(sizes, dtype=np.int64)]), pa.py_buffer(raw)]), *more]


def pack_texts(docs: DataFrame, parts: int, shards: int) -> DataFrame:
    """A row for every block: its documents as numbers of words, and its distinct words with counts, ordered by their part of the word table.
    A block lies in one shard; which texts it has, and in which order, hangs on ids and texts alone."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("lm")
        now, number, size = -1, 0, 0
        ids, texts = [], []

        def flush() -> pa.RecordBatch:
            words, at, sizes = split(texts)
            part = (hashes(words) >> np.uint64(16)) % np.uint64(parts)
            order = np.argsort(part, kind="stable")
            place = np.empty(len(words), np.int32)
            place[order] = np.arange(len(words), dtype=np.int32)
            n = np.bincount(at, minlength=len(words))[order]
            body = pack_arrays(np.array([i or 0 for i in ids], np.int64), np.array([i is None for i in ids], np.int8), sizes, place[at])
            held = pack_words(words.take(pa.array(order)), n, np.bincount(part.astype(np.int64), minlength=parts))
            return pa.record_batch([pa.array([now], pa.int32()), pa.array([now << 32 | number], pa.int64()), pa.array([body], pa.binary()), pa.array([held], pa.binary())], names=["shard", "block", "docs", "words"])

        for batch in batches:
            for i, shard, text in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), column_bytes(batch.column(1)), strict=True):
                if texts and (shard != now or size + len(text) > BLOCK):
                    yield flush()
                    number, size, ids, texts = number + 1 if shard == now else 0, 0, [], []
                now = shard
                ids.append(i)
                texts.append(text)
                size += len(text)
        if texts:
            yield flush()

    number = F.col("doc_id").cast("long") if "doc_id" in docs.columns else F.lit(None).cast("long")
    rows = docs.select(number.alias("doc_id"), F.col("text").cast("string").alias("text"))
    rows = rows.withColumn("shard", F.pmod(F.xxhash64("doc_id", "text"), F.lit(shards)).cast("int"))
    rows = rows.repartitionById(shards, "shard").sortWithinPartitions("shard", F.xxhash64("text"), "doc_id", "text")
    return stage(rows.select("doc_id", "text", "shard").mapInArrow(run, PACKED), "lm-texts")


def _ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(part, block, words) of every block."""
    for batch in batches:
        for block, message in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            words, n, sizes = unpack_words(message)
            ends = np.cumsum(sizes)
            sent = [(p, pack_words(words.slice(hi - m, m), n[hi - m : hi])) for p, (m, hi) in enumerate(zip(sizes.tolist(), ends.tolist(), strict=True)) if m]
            yield pa.record_batch([pa.array([p for p, _ in sent], pa.int32()), pa.array([block] * len(sent), pa.int64()), pa.array([x for _, x in sent], pa.binary())], names=["part", "block", "words"])


def asked(packed: DataFrame) -> DataFrame:
    return packed.select("block", "words").mapInArrow(_ask, "part int, block long, words binary")


def _merge(table: pa.Table) -> pa.Table:
    claim("lm")
    sent = [unpack_words(x) for x in table.column("words").to_pylist()]
    coded = pa.chunked_array([w for w, _ in sent]).combine_chunks().dictionary_encode()
    n = np.bincount(coded.indices.to_numpy(), np.concatenate([n for _, n in sent])).astype(np.int64)
    return pa.table([pa.array([table.column("part")[0].as_py()], pa.int32()), pa.array([pack_words(coded.dictionary, n)], pa.binary())], names=["part", "held"])


def merge_words(packed: DataFrame) -> DataFrame:
    """(part, held): all words of a part of the word table with their exact counts."""
    return stage(asked(packed).groupBy("part").applyInArrow(_merge, "part int, held binary"), "lm-words")


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for message in batch.column(0).to_pylist():
            words, n = unpack_words(message)
            for lo in range(0, len(words), 1 << 16):
                yield pa.record_batch([words.slice(lo, 1 << 16).cast(pa.binary()), pa.array(n[lo : lo + (1 << 16)])], names=["word", "n"])


def word_counts(held: DataFrame) -> DataFrame:
    """(word, n): a row for every word of the corpus."""
    return held.select("held").mapInArrow(_rows, "word binary, n long")


def lexicon_of(counts: DataFrame) -> Lexicon | None:
    spark = counts.sparkSession
    first = counts.orderBy(F.desc("n"), "word").limit(TOP).collect()
    if not first:
        return None
    levels = {r["n"]: r["m"] * r["n"] for r in counts.groupBy("n").agg(F.count("*").alias("m")).collect()}
    for r in first:
        levels[r["n"]] -= r["n"]
    level = np.array(sorted((n for n, m in levels.items() if m), reverse=True), np.int64)
    lexicon = Lexicon([bytes(r["word"]) for r in first], level, np.r_[0, np.cumsum([levels[n] for n in level.tolist()])].astype(np.float64))
    lexicon.inner = np.zeros(GROUPS * GROUP)
    lexicon.inner[: max(0, len(first) - OWN_CLASS)] = [r["n"] for r in first[OWN_CLASS:]]
    lexicon.inner = lexicon.inner.reshape(GROUPS, GROUP)
    shared = spark.sparkContext.broadcast(lexicon)

    def totals(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(CLASSES)
        for batch in batches:
            n = batch.column(1).to_numpy()
            total += np.bincount(shared.value.klass(batch.column(0).cast(pa.large_binary()), n), n, CLASSES)
        yield pa.record_batch([pa.array(range(CLASSES), pa.int32()), pa.array(total)], names=["class", "n"])

    sums = {r["class"]: r["n"] for r in counts.mapInArrow(totals, "class int, n double").groupBy("class").agg(F.sum("n").alias("n")).collect()}
    lexicon.total = np.array([sums[c] for c in range(CLASSES)])
    return lexicon


ANSWER = pa.schema([("block", pa.int64()), ("part", pa.int32()), ("codes", pa.binary())])
CODED = "shard int, block long, docs binary, codes binary"


def encode(packed: DataFrame, held: DataFrame, lexicon: Lexicon) -> DataFrame:
    """Blocks with context number, class and log share of each of their words, which the word table sends them."""
    shared = packed.sparkSession.sparkContext.broadcast(lexicon)

    def answer(asks: pa.Table, table: pa.Table) -> pa.Table:
        claim("lm")
        if not asks.num_rows:
            return ANSWER.empty_table()
        code = lambda words, n: (shared.value.context(words).astype(np.int16), k := shared.value.klass(words, n), shared.value.log_share(k, n), shared.value.place(words, n).astype(np.int8))
        sent = [unpack_words(x)[0] for x in asks.column("words").to_pylist()]
        words = pa.concat_arrays(sent)
        known, n = unpack_words(table.column("held")[0].as_py()) if table.num_rows else (words.slice(0, 0), np.zeros(0, np.int64))
        at = pc.index_in(words, value_set=known)
        new = np.flatnonzero(at.is_null().to_numpy(zero_copy_only=False))
        at = pc.fill_null(at, 0).to_numpy().astype(np.int64)
        at[new] = len(known) + np.arange(len(new))
        codes = [np.r_[a, b][at] for a, b in zip(code(known, n), code(words.take(pa.array(new)), np.zeros(len(new), np.int64)), strict=True)]
        ends = np.cumsum([len(w) for w in sent])
        out = [pack_arrays(codes[0][hi - len(w) : hi], codes[1][hi - len(w) : hi].astype(np.int16), *(c[hi - len(w) : hi] for c in codes[2:])) for w, hi in zip(sent, ends.tolist(), strict=True)]
        return pa.table([asks.column("block"), asks.column("part"), pa.array(out, pa.binary())], schema=ANSWER)

    def join(docs: pa.Table, codes: pa.Table) -> pa.Table:
        claim("lm")
        parts = [unpack_arrays(x) for _, x in sorted(zip(codes.column("part").to_pylist(), codes.column("codes").to_pylist(), strict=True))]
        kinds = (np.int16, np.int16, np.float32, np.int8)
        whole = pack_arrays(*(np.concatenate([np.zeros(0, kind), *(p[i] for p in parts)]) for i, kind in enumerate(kinds)))
        return pa.table([docs.column("shard"), docs.column("block"), docs.column("docs").cast(pa.binary()), pa.array([whole], pa.binary())], names=["shard", "block", "docs", "codes"])

    answers = asked(packed).groupBy("part").cogroup(held.groupBy("part")).applyInArrow(answer, "block long, part int, codes binary")
    return stage(packed.select("shard", "block", "docs").groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(join, CODED), "lm-coded")


def portions(docs: Iterable[bytes], codes: Iterable[bytes]) -> Iterator[tuple[np.ndarray, ...]]:
    """Ids, whether they are null, sizes, contexts, classes, places and log shares of some hundred texts or one long one at a time: window arrays take many times the text."""
    for body, code in zip(docs, codes, strict=True):
        ids, null, sizes, place = unpack_arrays(body)
        context, klass, share, inner = unpack_arrays(code)
        ends, lo = np.r_[0, np.cumsum(sizes)], 0
        while lo < len(sizes):
            hi = max(lo + 1, int(np.searchsorted(ends, ends[lo] + PORTION, "right")) - 1)
            at = place[ends[lo] : ends[hi]]
            yield ids[lo:hi], null[lo:hi], sizes[lo:hi], context[at].astype(np.int64), klass[at].astype(np.int64), inner[at].astype(np.int64), share[at]
            lo = hi


@dataclass
class Model:
    held: DataFrame  # the word table
    parts: int
    lexicon: Lexicon
    flat: np.ndarray


def train(coded: DataFrame, lexicon: Lexicon, shards: int, seed: int = 1, rate: float = 0.1) -> np.ndarray:
    """Weights of the network, from all documents."""
    spark = coded.sparkSession
    net = Net.start(lexicon, seed)

    def learn(net: Net, memory: np.ndarray, table: pa.Table, most: float = math.inf) -> int:
        """One pass over the blocks of a shard in their order; returns how many words were seen."""
        rows = sorted(range(table.num_rows), key=table.column("block").to_pylist().__getitem__)
        docs, codes = (table.column(c) for c in ("docs", "codes"))
        seen = 0
        for _, _, sizes, context, klass, place, _ in portions((docs[i].as_py() for i in rows), (codes[i].as_py() for i in rows)):
            around = windows(context, sizes, np.arange(CONTEXTS))
            mix = np.random.default_rng(zlib.crc32(context.tobytes())).permutation(len(klass))[: int(min(len(klass), most - seen))]  # words of one text do not come in a row
            net.learn(around[:, mix], klass[mix], place[mix], rate, memory)
            seen += len(mix)
            if seen >= most:
                break
        return seen

    def begin(table: pa.Table) -> pa.Table:
        claim("lm")
        mine, memory = Net(net.flat.copy()), np.full(Net.SIZE, 1e-6, np.float32)
        seen = 0
        for _ in range(START_PASSES):
            new = learn(mine, memory, table, START_WORDS)
            seen += new
            if not new or seen >= START_SEEN:
                break
        return pa.table([pa.array([pack_arrays(mine.flat, memory)], pa.binary())], names=["start"])

    # the smallest shard that is there; its first words are a fixed number
    first = coded.agg(F.min("shard").alias("shard")).first()["shard"]
    flat, memory = unpack_arrays(bytes(coded.where(F.col("shard") == first).groupBy("shard").applyInArrow(begin, "start binary").first()["start"]))

    def copies(shared):  # noqa: ANN001, ANN202
        def run(table: pa.Table) -> pa.Table:
            claim("lm")
            flat, memory = shared.value
            mine, memory = Net(flat.copy()), memory.copy()
            seen = learn(mine, memory, table)
            return pa.Table.from_batches([_message(mine.flat.astype(np.float64) * seen, float(seen), table.column("shard")[0].as_py() // ROUNDS)])

        return run

    for turn in range(ROUNDS):
        run = copies(spark.sparkContext.broadcast((flat, memory)))
        total, seen = _sum(coded.where(F.col("shard") % ROUNDS == turn).groupBy("shard").applyInArrow(run, MESSAGE), -(-shards // ROUNDS))
        flat = (total / seen).astype(np.float32) if seen else flat
    return flat


def _score(coded: DataFrame, lexicon: Lexicon, flat: np.ndarray) -> DataFrame:
    shared = coded.sparkSession.sparkContext.broadcast((lexicon.log_prior, flat))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("lm")
        prior, flat = shared.value
        net = Net(flat)
        for batch in batches:
            for ids, null, sizes, context, klass, place, share in portions(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ends = np.cumsum(sizes)
                sums = []
                for logp in (net.log_probability(context, sizes, klass, place, share), prior[klass] + share, (place == ONCE)):
                    upto = np.r_[0.0, np.cumsum(logp, dtype=np.float64)]
                    sums.append(upto[ends] - upto[ends - sizes])
                mean = pa.array([t / c if c else None for t, c in zip(sums[0].tolist(), sizes.tolist(), strict=True)], pa.float64())
                yield pa.record_batch([pa.array(ids, pa.int64(), mask=null.astype(bool)), pa.array(sizes, pa.int64()), pa.array(sums[0]), mean, pa.array(sums[1]), pa.array(sums[2].astype(np.int64))], names=NAMES)

    return coded.select("docs", "codes").mapInArrow(run, SCORES)


SCORES = "doc_id long, n_tokens long, log_probability double, mean_log_probability double, unigram_log_probability double, n_once long"
NAMES = [part.split()[0] for part in SCORES.split(", ")]


def _unknown(docs: DataFrame) -> DataFrame:
    """Scores under a corpus without words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            _, _, n = split(column_bytes(batch.column(1)))
            zero = np.zeros(len(n))
            mean = pa.array([0.0 if c else None for c in n], pa.float64())
            yield pa.record_batch([batch.column(0), pa.array(n), pa.array(zero), mean, pa.array(zero), pa.array(np.zeros(len(n), np.int64))], names=NAMES)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, SCORES)


def _sizes(docs: DataFrame) -> tuple[int, int]:
    """Parts of the word table and shards of the texts."""
    size = total_bytes(docs)
    return max(16, size // SHARE), max(SHARDS, -(-size // SHARD))


def _fit(docs: DataFrame, seed: int, rate: float) -> tuple[Model, DataFrame] | None:
    spark, since, (parts, shards) = docs.sparkSession, mark(), _sizes(docs)
    packed = pack_texts(docs, parts, shards)
    held = merge_words(packed)
    lexicon = lexicon_of(word_counts(held))
    if lexicon is None:
        return None
    coded = encode(packed, held, lexicon)
    sweep(spark, since, held, coded)
    return Model(held, parts, lexicon, train(coded, lexicon, shards, seed, rate)), coded


def fit(docs: DataFrame, seed: int = 1, rate: float = 0.1) -> Model | None:
    """The model of a corpus (a column ``text``); None if it has no word."""
    fitted = _fit(docs, seed, rate)
    return fitted and fitted[0]


def score(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, n_tokens, log_probability (sum over words), mean_log_probability, unigram_log_probability, n_once (words that the
    corpus holds once)."""
    if model is None:
        return _unknown(docs)
    return _score(encode(pack_texts(docs, model.parts, _sizes(docs)[1]), model.held, model.lexicon), model.lexicon, model.flat)


def pseudo_likelihood(docs: DataFrame) -> DataFrame:
    """Fit on all of ``docs`` (doc_id, text) and score each row."""
    fitted = _fit(docs, 1, 0.1)
    return _unknown(docs) if fitted is None else _score(fitted[1], fitted[0].lexicon, fitted[0].flat)
