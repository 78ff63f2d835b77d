"""Quality rules learned as a decision list.

Counted features of a text feed a sequential covering learner: each rule for "bad" grows condition by condition by information
gain on two thirds of the labelled rows that are left, is pruned on the other third, and takes the rows it covers away. The
list becomes one ordered Spark expression, so judging a corpus is a projection. Labelled rows for the fit are at most
``SAMPLE`` (those with the smallest hashes of their id); features and verdicts cover every row.

Edge cases: null text has no words; rows without labels are judged only; with no labelled bad row, or none at all, the list is
empty and only the base rule decides; extra columns are ignored, repeated rows repeat, an empty table gives an empty one.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import column_bytes, one_each

SAMPLE = 20_000  # labelled rows that the fit reads at most
SYMBOLS = re.compile(rb"[#*$%&|<>]")
SPACE = re.compile(rb"[\x20\x09-\x0D]")
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
#: Shares that rules may test.
SHARES = ["mean_word", "symbol_share", "dup_line_share", "repeat_share", "upper_share", "bang_share", "digit_share", "distinct_share", "top_share", "stop_share"]
UPPER, BANG, DIGIT = re.compile(rb"[A-Z]"), re.compile(rb"[!?]"), re.compile(rb"[0-9]")


def repeat_words(words: list[bytes], width: int = 5) -> int:
    """Words in windows of ``width`` words that occur twice or more, each place counted once."""
    n = len(words)
    if n <= width:
        return 0
    h = np.fromiter(map(hash, words), np.int64, n).view(np.uint64)
    key = np.zeros(n - width + 1, np.uint64)
    for i in range(width):
        key = key * np.uint64(0x9E3779B97F4A7C15) + h[i : n - width + 1 + i]
        key ^= key >> np.uint64(31)
    by = np.argsort(key, kind="stable")
    k = key[by]
    same = k[1:] == k[:-1]
    if not same.any():
        return 0
    twice = np.zeros(len(k), bool)
    twice[1:] |= same
    twice[:-1] |= same
    mark = np.zeros(n + 1, np.int64)
    np.add.at(mark, by[twice], 1)
    np.add.at(mark, by[twice] + width, -1)
    return int((np.cumsum(mark)[:n] > 0).sum())


def measure(raw: bytes) -> list[float]:
    """COUNTS then SHARES of a text."""
    words = raw.split()
    n = len(words)
    if not n:
        return [0] * len(COUNTS) + [0.0] * len(SHARES)
    joined = b"".join(words)
    chars = len(joined) if joined.isascii() else len(joined.decode())
    lines, seen, dup, full = raw.split(b"\n"), set(), 0, 0
    for line in lines:
        if line.strip():
            full += 1
            if line in seen:
                dup += 1
            else:
                seen.add(line)
    symbols, repeated = len(SYMBOLS.findall(joined)), repeat_words(words)
    distinct: dict[bytes, int] = {}
    for w in words:
        distinct[w] = distinct.get(w, 0) + 1
    top = max(distinct.values())
    short = sum(c for w, c in distinct.items() if len(w) <= 3 and w.isalpha())
    shares = [chars / n, symbols / chars, dup / full, repeated / n, len(UPPER.findall(joined)) / chars, len(BANG.findall(joined)) / chars, len(DIGIT.findall(joined)) / chars, len(distinct) / n, top / n, short / n]
    return [n, chars, symbols, dup, repeated, *shares]


def features(docs: DataFrame) -> DataFrame:
    """doc_id, the counts (long) and the shares (double) of each row's whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [measure(x) for x in column_bytes(batch.column(1))]
            cols = list(zip(*rows, strict=True)) or [[] for _ in COUNTS + SHARES]
            arrays = [pa.array(list(map(int, c)), pa.int64()) for c in cols[: len(COUNTS)]] + [pa.array(c, pa.float64()) for c in cols[len(COUNTS) :]]
            yield pa.record_batch([batch.column(0), *arrays], names=["doc_id", *COUNTS, *SHARES])

    schema = ", ".join(["doc_id long", *(f"{c} long" for c in COUNTS), *(f"{c} double" for c in SHARES)])
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, schema)


# ---- the learner ----------------------------------------------------------------------------------------------------------

Condition = tuple  # feature index, "<=" or ">=", threshold


def _covers(rule: list[Condition], x: np.ndarray) -> np.ndarray:
    out = np.ones(len(x), bool)
    for f, op, t in rule:
        out &= x[:, f] <= t if op == "<=" else x[:, f] >= t
    return out


def _best_condition(x: np.ndarray, y: np.ndarray) -> tuple[float, Condition | None]:
    """The condition with the largest gain in bits for the positives it keeps."""
    p0, n0 = int(y.sum()), int(len(y) - y.sum())
    base = np.log2(p0 / (p0 + n0))
    best: tuple[float, Condition | None] = (0.0, None)
    for f in range(x.shape[1]):
        by = np.argsort(x[:, f], kind="stable")
        v, pos = x[by, f], np.cumsum(y[by])
        edge = np.flatnonzero(v[1:] != v[:-1])
        if not len(edge):
            continue
        mid = (v[edge] + v[edge + 1]) / 2
        low_p, low_n = pos[edge], edge + 1
        for op, p, n in (("<=", low_p, low_n), (">=", p0 - low_p, len(y) - low_n)):
            with np.errstate(divide="ignore", invalid="ignore"):
                gain = np.where(p > 0, p * (np.log2(p / n) - base), 0.0)
            k = int(np.argmax(gain))
            if gain[k] > best[0] + 1e-9:
                best = (float(gain[k]), (f, op, float(mid[k])))
    return best


def learn(x: np.ndarray, y: np.ndarray, precision: float = 0.9, longest: int = 4, rules: int = 12, seed: int = 1) -> list[list[Condition]]:
    """An ordered list of conjunctions that mark bad rows (``y`` true)."""
    rng, out = np.random.default_rng(seed), []
    left = np.arange(len(y))
    least = max(2, int(0.01 * y.sum()))
    while len(out) < rules and y[left].sum() >= least:
        mixed = rng.permutation(left)
        grow, prune = mixed[: 2 * len(mixed) // 3], mixed[2 * len(mixed) // 3 :]
        rule: list[Condition] = []
        inside = grow
        while len(rule) < longest and 0 < y[inside].sum() < len(inside):
            _, condition = _best_condition(x[inside], y[inside])
            if condition is None:
                break
            rule.append(condition)
            inside = inside[_covers([condition], x[inside])]

        def worth(r: list[Condition], rows: np.ndarray = prune) -> float:
            c = _covers(r, x[rows])
            p = int(y[rows][c].sum())
            return (2 * p - int(c.sum())) / max(1, int(c.sum()))

        best = max(range(1, len(rule) + 1), key=lambda k: (worth(rule[:k]), -k), default=0)
        rule = rule[:best]
        hit = _covers(rule, x[left]) if rule else np.zeros(len(left), bool)
        if not hit.any() or y[left][hit].mean() < precision or y[left][hit].sum() < least:
            break
        out.append(rule)
        left = left[~hit]
    return out


def verdict(rules: list[list[Condition]], names: list[str]) -> Column:
    """The number of the first rule that marks a row as bad; 0 for none."""
    out: Column | None = None
    for i, rule in enumerate(rules, 1):
        test = reduce(lambda a, b: a & b, [F.col(names[f]) <= t if op == "<=" else F.col(names[f]) >= t for f, op, t in rule])
        out = F.when(test, i) if out is None else out.when(test, i)
    return F.lit(0) if out is None else out.otherwise(0)


def fit_rules(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> list[list[Condition]]:
    """Rules from at most ``sample`` labelled ids (``labels``: doc_id, quality with 0 for bad). An id that several rows have gives the
    features of one of them; one that is labelled both ways counts as bad."""
    known = labels.where("doc_id is not null and quality is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min(F.col("quality").cast("int")).alias("quality"))
    picked = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    rows = one_each(features(docs.join(F.broadcast(picked.select("doc_id")), "doc_id", "left_semi")), "doc_id").join(F.broadcast(picked), "doc_id").toPandas()
    if not len(rows):
        return []
    rows = rows.sort_values("doc_id", kind="stable")
    return learn(rows[SHARES].to_numpy(float), rows["quality"].to_numpy() == 0)


def judge(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, counts, base_failed, rule (0: none), kept of every row."""
    rules = fit_rules(docs, labels, sample)
    base = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    out = features(docs).withColumn("base_failed", base).withColumn("rule", verdict(rules, SHARES))
    return out.select("doc_id", *COUNTS, "base_failed", "rule", (~F.col("base_failed") & (F.col("rule") == 0)).alias("kept"))
