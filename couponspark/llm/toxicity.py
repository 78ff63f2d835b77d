"""Toxicity of texts by a bidirectional gated recurrent network with attention pooling.

A word's input joins a word part and a character part: log odds of the word and of its character n-grams (from one half of the
labelled sample), and learned vectors of hashed words and n-grams. Overlapping windows of words run through a GRU in both
directions; attention pools the states to one logit a window; the text's score is that of its worst window. Training is by hand
in numpy: each round scores all windows of the other half of the sample, takes the worst window of each text and follows its
gradient back through time. Scoring covers every window of every text, some thousand windows at a time.

The sample has at most ``SAMPLE`` labelled texts of each class, those with the smallest hashes of their id. Neither ids, nor
sources, nor languages are inputs. Edge cases: null, empty and blank text gets the score of an empty window; with no labelled
text of one of the classes every score is 0; extra columns are ignored; repeated rows repeat; an empty table gives an empty one.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import TextHash, claim, column_bytes, one_each, slices

SAMPLE = 1200  # labelled texts of each class that the fit reads at most
WINDOW, STRIDE = 32, 24
HIDDEN, VECTOR = 8, 6
WORDS, GRAMS = 1 << 16, 1 << 16  # buckets of log odds
ROWS = 1 << 14  # buckets of learned vectors
INPUTS = 3 + 2 * VECTOR
TABLES, DECAY = 0.05, 0.1  # learned vectors move slowly, and all weights shrink, or else single words are learned by heart
SLICE = 4096  # windows at a time
PIECE = 200_000  # words at a time
CHUNK = 30_000  # distinct words at a time
HASH = TextHash(23)


# ---- words to inputs ------------------------------------------------------------------------------------------------------


@dataclass
class Vocabulary:
    """Distinct words of some texts: a hash each, and the hashes of their n-grams (3 to 5 characters, edges marked) end to end."""

    word: np.ndarray
    gram: np.ndarray
    first: np.ndarray  # where each word's n-grams begin

    @staticmethod
    def of(words: list[bytes]) -> Vocabulary:
        if len(words) > CHUNK:  # arrays of n-grams stay small on the way
            parts = [Vocabulary.of(words[i : i + CHUNK]) for i in range(0, len(words), CHUNK)]
            base = np.cumsum([0] + [len(p.gram) for p in parts[:-1]])
            return Vocabulary(np.concatenate([p.word for p in parts]), np.concatenate([p.gram for p in parts]), np.concatenate([p.first + b for p, b in zip(parts, base, strict=True)]))
        joined = np.frombuffer(b"".join(b"^" + w + b"$" for w in words), np.uint8)
        size = np.fromiter(map(len, words), np.int64, len(words)) + 2
        start = np.cumsum(size) - size
        prefix = HASH.prefixes(joined)
        whole = HASH.spans(prefix, start, start + size)
        owner = np.repeat(np.arange(len(words)), size)
        left = np.repeat(start + size, size) - np.arange(len(joined))  # bytes up to the word's end
        grams, owners = [], []
        for n in (3, 4, 5):
            if len(joined) < n:
                continue
            h = HASH.windows(prefix, n) + np.uint64(n)
            ok = left[: len(h)] >= n
            grams.append(h[ok])
            owners.append(owner[: len(h)][ok])
        gram, own = np.concatenate(grams), np.concatenate(owners)
        by = np.argsort(own, kind="stable")  # each word has one of 3 at least
        return Vocabulary(whole, gram[by], np.searchsorted(own[by], np.arange(len(words))))


def split_words(raw: bytes) -> list[bytes]:
    return raw.lower().split()


def number(texts: list[list[bytes]]) -> tuple[list[bytes], np.ndarray]:
    """Distinct words of texts, and the number of each word in turn."""
    distinct = list(dict.fromkeys(w for t in texts for w in t))
    index = {w: i for i, w in enumerate(distinct)}
    return distinct, np.fromiter((index[w] for t in texts for w in t), np.int64, sum(map(len, texts)))


def window_table(sizes: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """For all windows of all texts: places of their words in the joined texts (-1: none), and the text of each."""
    starts, ends, owner, at = [], [], [], 0
    for i, n in enumerate(sizes):
        for s in range(0, max(1, n - (WINDOW - STRIDE)), STRIDE):
            starts.append(at + s)
            ends.append(at + n)
            owner.append(i)
        at += n
    place = np.array(starts, np.int64)[:, None] + np.arange(WINDOW)[None, :]
    return np.where(place < np.array(ends, np.int64)[:, None], place, -1), np.array(owner, np.int64)


# ---- the network ----------------------------------------------------------------------------------------------------------


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


@dataclass
class Network:
    word_odds: np.ndarray = field(default_factory=lambda: np.zeros(WORDS, np.float32))
    gram_odds: np.ndarray = field(default_factory=lambda: np.zeros(GRAMS, np.float32))
    weights: dict[str, np.ndarray] = field(default_factory=dict)
    constant: bool = False

    def start(self, seed: int = 1) -> None:
        rng = np.random.default_rng(seed)
        w = lambda *shape, s=0.3: (rng.standard_normal(shape) * s).astype(np.float32)
        self.weights = {"word": w(ROWS, VECTOR, s=0.05), "gram": w(ROWS, VECTOR, s=0.05), "attend": w(2 * HIDDEN), "out": w(2 * HIDDEN), "bias": np.array([-1.0], np.float32)}
        for d in ("f", "b"):
            self.weights |= {f"w{d}": w(INPUTS, 3 * HIDDEN), f"u{d}": w(HIDDEN, 3 * HIDDEN), f"c{d}": np.zeros(3 * HIDDEN, np.float32)}

    def inputs(self, v: Vocabulary) -> np.ndarray:
        """Input of each distinct word."""
        if len(v.word) > CHUNK:
            cuts = np.r_[v.first, len(v.gram)]
            spans = [(i, min(i + CHUNK, len(v.word))) for i in range(0, len(v.word), CHUNK)]
            return np.concatenate([self.inputs(Vocabulary(v.word[a:z], v.gram[cuts[a] : cuts[z]], v.first[a:z] - cuts[a])) for a, z in spans])
        n = np.diff(np.r_[v.first, len(v.gram)])[:, None]
        odds = self.gram_odds[v.gram % np.uint64(GRAMS)]
        chars = np.add.reduceat(self.weights["gram"][v.gram % np.uint64(ROWS)], v.first, axis=0) / n
        return np.concatenate([self.word_odds[v.word % np.uint64(WORDS)][:, None], np.maximum.reduceat(odds, v.first)[:, None], (np.add.reduceat(odds, v.first) / n[:, 0])[:, None], self.weights["word"][v.word % np.uint64(ROWS)], chars], axis=1).astype(np.float32)

    def run(self, gates: dict[str, np.ndarray], ids: np.ndarray, keep: bool = False):
        """Logits of windows; ``ids`` are rows of the gate inputs, -1 for no word. With ``keep`` also what the way back needs."""
        w, n = self.weights, len(ids)
        mask = (ids >= 0).astype(np.float32)
        states = np.zeros((n, WINDOW, 2 * HIDDEN), np.float32)
        trace = {"f": [], "b": []}
        for d, order, lo in (("f", range(WINDOW), 0), ("b", range(WINDOW - 1, -1, -1), HIDDEN)):
            h, u, table = np.zeros((n, HIDDEN), np.float32), w[f"u{d}"], gates[d]
            for t in order:
                m = mask[:, t : t + 1]
                g, q = table[ids[:, t]], h @ u
                zr = _sigmoid(g[:, : 2 * HIDDEN] + q[:, : 2 * HIDDEN])
                z, r = zr[:, :HIDDEN], zr[:, HIDDEN:]
                c = np.tanh(g[:, 2 * HIDDEN :] + r * q[:, 2 * HIDDEN :])
                new = c + z * (h - c)
                new = h + m * (new - h)
                if keep:
                    trace[d].append((t, h, z, r, c, q[:, 2 * HIDDEN :], m))
                h = new
                states[:, t, lo : lo + HIDDEN] = h
        score = states @ w["attend"] + (mask - 1) * 1e4
        e = np.exp(score - score.max(axis=1, keepdims=True))
        alpha = e / e.sum(axis=1, keepdims=True)
        pooled = (alpha[:, :, None] * states).sum(axis=1)
        logit = pooled @ w["out"] + w["bias"][0]
        return (logit, states, alpha, pooled, trace) if keep else logit

    def gates(self, x: np.ndarray) -> dict[str, np.ndarray]:
        """Gate inputs of each distinct word and, as the last row, of none (which is masked)."""
        none = np.zeros((1, 3 * HIDDEN), np.float32)
        return {d: np.concatenate([x @ self.weights[f"w{d}"] + self.weights[f"c{d}"], none]) for d in ("f", "b")}

    def gradient(self, v: Vocabulary, x: np.ndarray, ids: np.ndarray, target: np.ndarray, weight: np.ndarray) -> tuple[dict[str, np.ndarray], float]:
        """Gradient of the weighted cross-entropy of some windows."""
        w = self.weights
        logit, states, alpha, pooled, trace = self.run(self.gates(x), ids, keep=True)
        p = _sigmoid(logit)
        loss = -float((weight * (target * np.log(p + 1e-9) + (1 - target) * np.log(1 - p + 1e-9))).mean())
        d_logit = (weight * (p - target) / len(ids)).astype(np.float32)
        grad = {"out": pooled.T @ d_logit, "bias": np.array([d_logit.sum()], np.float32)}
        d_pooled = d_logit[:, None] * w["out"][None, :]
        d_alpha = (states * d_pooled[:, None, :]).sum(axis=2)
        d_score = alpha * (d_alpha - (alpha * d_alpha).sum(axis=1, keepdims=True))
        grad["attend"] = (d_score[:, :, None] * states).sum(axis=(0, 1))
        d_states = alpha[:, :, None] * d_pooled[:, None, :] + d_score[:, :, None] * w["attend"]
        d_x = np.zeros((len(x) + 1, INPUTS), np.float32)
        for d, lo in (("f", 0), ("b", HIDDEN)):
            u, d_h = w[f"u{d}"], np.zeros((len(ids), HIDDEN), np.float32)
            gu, d_gates = np.zeros_like(u), np.zeros((len(x) + 1, 3 * HIDDEN), np.float32)
            for t, h, z, r, c, q, m in reversed(trace[d]):
                d_h = d_h + d_states[:, t, lo : lo + HIDDEN]
                d_new, d_old = d_h * m, d_h * (1 - m)
                d_c = d_new * (1 - z) * (1 - c * c)
                d_z = d_new * (h - c) * z * (1 - z)
                d_r = d_c * q * r * (1 - r)
                own = np.concatenate([d_z, d_r, d_c], axis=1)
                through = np.concatenate([d_z, d_r, d_c * r], axis=1)
                gu += h.T @ through
                np.add.at(d_gates, ids[:, t], own)
                d_h = d_old + d_new * z + through @ u.T
            d_gates[-1] = 0
            grad |= {f"u{d}": gu, f"w{d}": x.T @ d_gates[:-1], f"c{d}": d_gates.sum(axis=0)}
            d_x[:-1] += d_gates[:-1] @ w[f"w{d}"].T
        words, chars = np.zeros_like(w["word"]), np.zeros_like(w["gram"])
        used = np.unique(ids[ids >= 0])
        np.add.at(words, v.word[used] % np.uint64(ROWS), d_x[used, 3 : 3 + VECTOR])
        ends = np.r_[v.first[1:], len(v.gram)]
        n = ends[used] - v.first[used]
        at = np.repeat(v.first[used] - np.r_[0, np.cumsum(n)[:-1]], n) + np.arange(n.sum())
        np.add.at(chars, v.gram[at] % np.uint64(ROWS), np.repeat(d_x[used, 3 + VECTOR :] / n[:, None], n, axis=0))
        return grad | {"word": words, "gram": chars}, loss

    def logits(self, texts: list[bytes]) -> np.ndarray:
        """The logit of the worst window of each text."""
        out = np.full(len(texts), -np.inf, np.float32)
        part: list[list[bytes]] = []
        first, size = 0, 0
        for i, raw in enumerate(texts):
            part.append(split_words(raw))
            size += len(part[-1])
            if size >= PIECE or i == len(texts) - 1:
                distinct, ids = number(part)
                table, owner = window_table([len(p) for p in part])
                gates = self.gates(self.inputs(Vocabulary.of(distinct))) if distinct else {d: np.zeros((1, 3 * HIDDEN), np.float32) for d in ("f", "b")}
                ids = np.r_[ids, -1]
                for lo in range(0, len(table), SLICE):
                    logit = self.run(gates, ids[table[lo : lo + SLICE]])
                    np.maximum.at(out, first + owner[lo : lo + SLICE], logit)
                first, part, size = i + 1, [], 0
        return out

    def scores(self, texts: list[bytes]) -> np.ndarray:
        if self.constant:
            return np.zeros(len(texts))
        return _sigmoid(self.logits(texts).astype(np.float64)) if texts else np.zeros(0)


# ---- training -------------------------------------------------------------------------------------------------------------


def _odds(texts: list[list[bytes]], toxic: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Log odds of hashed words and n-grams by the number of texts that hold them, as far from 0 as is sure."""
    kinds: list[tuple[np.ndarray, np.ndarray]] = [(np.zeros(WORDS), np.zeros(WORDS)), (np.zeros(GRAMS), np.zeros(GRAMS))]
    for words, bad in zip(texts, toxic, strict=True):
        v = Vocabulary.of(list(dict.fromkeys(words))) if words else None
        if v is not None:
            for (yes, no), h, size in ((kinds[0], v.word, WORDS), (kinds[1], v.gram, GRAMS)):
                (yes if bad else no)[np.unique(h % np.uint64(size)).astype(np.int64)] += 1
    out = []
    for yes, no in kinds:
        raw = np.log((yes + 0.5) / (toxic.sum() + 1)) - np.log((no + 0.5) / ((~toxic).sum() + 1))
        sure = np.abs(raw) - 2 * np.sqrt(1 / (yes + 0.5) + 1 / (no + 0.5))  # what is left two standard errors nearer to 0
        out.append((np.sign(raw) * np.clip(sure, 0, 4)).astype(np.float32))
    return out[0], out[1]


def train(texts: list[bytes], toxic: np.ndarray, rounds: int = 12, batch: int = 128, rate: float = 0.015, seed: int = 1, threshold: float = 0.3) -> Network:
    """Fit on texts and labels; the bias is set last, so that ``threshold`` separates the classes best."""
    net, toxic = Network(), np.asarray(toxic, bool)
    if not toxic.any() or toxic.all():
        net.constant = True
        return net
    rng = np.random.default_rng(seed)
    net.start(seed)
    words = [split_words(t) for t in texts]
    half = np.zeros(len(texts), bool)
    for side in (np.flatnonzero(toxic), np.flatnonzero(~toxic)):
        half[rng.permutation(side)[: (len(side) + 1) // 2]] = True
    if not toxic[~half].any():
        half[:] = True
    net.word_odds, net.gram_odds = _odds([words[i] for i in np.flatnonzero(half)], toxic[half])
    rest = np.flatnonzero(~half) if (~half).any() else np.flatnonzero(half)
    mine, y = [words[i] for i in rest], toxic[rest].astype(np.float32)
    distinct, ids = number(mine)
    v = Vocabulary.of(distinct)
    table, owner = window_table([len(m) for m in mine])
    table = np.r_[ids, -1][table]
    weight = np.where(y > 0, 0.5 / max(y.mean(), 1e-3), 0.5 / max(1 - y.mean(), 1e-3)).astype(np.float32)
    moment = {k: (np.zeros_like(a), np.zeros_like(a)) for k, a in net.weights.items()}
    step = 0
    heads = np.searchsorted(owner, np.arange(len(rest)))
    parts = max(1, len(rest) // batch, 6)
    for _ in range(max(rounds, 240 // parts)):
        x = net.inputs(v)
        gates = net.gates(x)
        logit = np.concatenate([net.run(gates, table[lo : lo + SLICE]) for lo in range(0, len(table), SLICE)])
        worst = np.array([lo + int(np.argmax(logit[lo:hi])) for lo, hi in zip(heads, np.r_[heads[1:], len(owner)], strict=True)])
        for chosen in np.array_split(rng.permutation(len(rest)), parts):
            if not len(chosen):
                continue
            local, small = np.unique(table[worst[chosen]], return_inverse=True)
            small = small.reshape(len(chosen), WINDOW)
            if local[0] < 0:
                local, small = local[1:], small - 1
            part = _pick(v, local)
            grad, _ = net.gradient(part, net.inputs(part), small, y[chosen], weight[chosen])
            step += 1
            for k, g in grad.items():
                m, s = moment[k]
                m += 0.1 * (g - m)
                s += 0.01 * (g * g - s)
                slow = TABLES if k in ("word", "gram") else 1.0
                net.weights[k] *= 1 - DECAY * rate
                net.weights[k] -= (slow * rate * (m / (1 - 0.9**step)) / (np.sqrt(s / (1 - 0.99**step)) + 1e-6)).astype(np.float32)
    _set_bias(net, [texts[i] for i in rest], y > 0, threshold)
    return net


def _pick(v: Vocabulary, words: np.ndarray) -> Vocabulary:
    n = np.r_[v.first[1:], len(v.gram)][words] - v.first[words]
    first = np.cumsum(n) - n
    return Vocabulary(v.word[words], v.gram[np.repeat(v.first[words] - first, n) + np.arange(n.sum())], first)


def _set_bias(net: Network, texts: list[bytes], toxic: np.ndarray, threshold: float) -> None:
    """Shift the bias so that ``threshold`` is the middle of the cuts with the best F1."""
    logit = net.logits(texts)
    by = np.argsort(-logit)
    hit = np.cumsum(toxic[by])
    f1 = 2 * hit / (np.arange(1, len(by) + 1) + toxic.sum())
    k = int(np.argmax(f1))
    above, below = float(logit[by[k]]), float(logit[by[k + 1]]) if k + 1 < len(by) else float(logit[by[k]]) - 1
    net.weights["bias"] = net.weights["bias"] + np.float32(np.log(threshold / (1 - threshold)) - (above + below) / 2)


def held_out(doc_id: Column) -> Column:
    """Rows whose labels are never learned from."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, text, toxic of at most ``sample`` labelled ids of each class, none of them held out. An id that several rows have
    gives one of its texts; one that is labelled both ways counts as toxic."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("doc_id is not null and toxic in (0, 1)").where(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    picked = [known.where(F.col("toxic") == c).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample) for c in (0, 1)]
    picked = picked[0].union(picked[1])
    return one_each(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(picked), "doc_id"), "doc_id").select("doc_id", "text", "toxic")


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Network:
    """Train on ``training_rows``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("toxicity")
        found = [(d, t, x) for b in batches for d, x, t in zip(b.column(0).to_pylist(), column_bytes(b.column(1)), b.column(2).to_pylist(), strict=True)]
        found.sort()
        net = train([x for _, _, x in found], np.array([t == 1 for _, t, _ in found], bool))
        yield pa.record_batch([pa.array([pickle.dumps(net)], pa.binary())], names=["net"])

    # one task trains on the bounded sample; the driver gets the network alone
    made = training_rows(docs, labels, sample).repartition(1).mapInArrow(run, "net binary").collect()
    return pickle.loads(bytes(made[0]["net"])) if made else Network(constant=True)


def score(docs: DataFrame, net: Network) -> DataFrame:
    """doc_id, score of each row of ``docs``."""
    shared = docs.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("toxicity")
        for batch in batches:
            yield pa.record_batch([batch.column(0), pa.array(shared.value.scores(column_bytes(batch.column(1))), pa.float64())], names=["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")


def toxicity(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, sample: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, score, predicted of each row."""
    scored = score(docs, fit(docs, labels, sample))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_clean(docs: DataFrame, net: Network, threshold: float = 0.3) -> DataFrame:
    """The rows of ``docs`` with a lower score, all columns as they are."""
    shared, schema = docs.sparkSession.sparkContext.broadcast(net), docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("toxicity")
        for batch in slices(batches, 1 << 30):
            at = batch.schema.get_field_index("text")
            yield batch.filter(pa.array(shared.value.scores(column_bytes(batch.column(at))) < threshold, pa.bool_()))

    return docs.mapInArrow(run, schema)
