"""Exact token counts of texts and of all their prefixes.

The table of a text holds, for each pre-token, the count up to its end; a prefix that ends inside one adds that word's own
prefix count, which the same dynamic program gives. So "how many tokens has text[:i]" and "how much of the text fits a
budget" need no second encoding.

Edge cases: null text is empty and has 0 tokens; special strings inside a text count as one token (the library's default);
very long words are solved in linear time and not kept in memory; extra columns are ignored; repeated rows give repeated
rows; an empty table gives an empty one.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import claim, column_bytes
from .word_bpe import WordBpe, word_bpe


class PrefixTable:
    """Token counts at every prefix of one text (offsets are those of the text after NFC and lower-casing).

    ``ends`` holds the count up to the end of each piece: a run between white space, or a pre-token of a text that needs the
    library's own splitting.
    """

    def __init__(self, bpe: WordBpe, text: str) -> None:
        self.bpe, folded = bpe, bpe.fold(text)
        self.by_runs = folded is not None
        if folded is not None:
            self.folded: bytes | None = folded
            self.pieces: list = folded.split()
            each = np.fromiter(map(bpe.run_counts.__getitem__, self.pieces), np.int64, len(self.pieces))
        else:
            self.pieces = bpe.words(text)
            each = np.fromiter((1 if w in bpe.special else bpe.counts[w] for w in self.pieces), np.int64, len(self.pieces))
            parts, at = [], 0  # special strings are not normalised
            for m in bpe.special_pattern.finditer(text) if bpe.special_pattern is not None else ():
                parts += [bpe.library.normalizer.normalize_str(text[at : m.start()]), m.group()]
                at = m.end()
            self.folded = "".join([*parts, bpe.library.normalizer.normalize_str(text[at:])]).encode()
        self.ends = np.cumsum(each)
        self._places: tuple[list[int], list[int], str] | None = None

    @property
    def total(self) -> int:
        return int(self.ends[-1]) if len(self.ends) else 0

    def _piece(self, k: int) -> str:
        return self.pieces[k].decode() if self.by_runs else self.pieces[k]

    def places(self, upto: int | None = None) -> tuple[list[int], list[int]]:
        """Start and end of each piece, in characters (of the first ``upto`` only, if given)."""
        if self._places is not None:
            return self._places[:2]
        text, at, a, z = self.folded.decode(), 0, [], []
        for k in range(len(self.pieces) if upto is None else min(upto, len(self.pieces))):
            w = self._piece(k)
            i = text.find(w, at)
            at = i + len(w)
            a.append(i)
            z.append(at)
        if upto is None:
            self._places = (a, z, text)
        return a, z

    def _inside(self, piece: str, m: int) -> int:
        """Tokens of the first ``m`` characters of a piece."""
        out = 0
        for w in self.bpe.pattern.finditer(piece):
            if w.end() <= m:
                out += self.bpe.counts[w.group()]
            else:
                return out + (self.bpe.prefix_counts(w.group())[m - w.start() - 1] if m > w.start() else 0)
        return out

    def count_at(self, i: int) -> int:
        """Tokens of the first ``i`` characters, encoded as a text of their own."""
        starts, ends = self.places()
        k = bisect_right(ends, i)
        before = int(self.ends[k - 1]) if k else 0
        if k == len(self.pieces) or i <= starts[k]:
            return before
        piece = self._piece(k)
        if piece in self.bpe.special:  # a cut special string is ordinary text and may join the symbols before it
            k0 = k - 1 if k and ends[k - 1] == starts[k] and self.pieces[k - 1] not in self.bpe.special else k
            before = int(self.ends[k0 - 1]) if k0 else 0
            tail = "".join(self.pieces[k0:k]) + piece[: i - starts[k]]
            return before + sum(self.bpe.counts[w] for w in self.bpe.plain_words(tail))
        return before + self._inside(piece, i - starts[k])

    def cut(self, budget: int) -> int:
        """Length of the longest prefix, up to the first piece that breaks the budget, with ``budget`` tokens at most."""
        if self.total <= budget:
            return self.places()[1][-1] if self.pieces else 0
        k = int(np.searchsorted(self.ends, budget, side="right"))
        starts, ends = self.places(k + 1)
        before = int(self.ends[k - 1]) if k else 0
        piece, best = self._piece(k), ends[k - 1] if k else 0
        if piece in self.bpe.special:
            return best
        counts: list[int] = []
        for w in self.bpe.pattern.finditer(piece):
            base = counts[-1] if counts else 0
            counts += [base + c for c in self.bpe.prefix_counts(w.group())]
        inside = [m for m, c in enumerate(counts, 1) if before + c <= budget]
        return starts[k] + inside[-1] if inside else best


def token_counts(docs: DataFrame, tokenizer: str, limit: int = 2048) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit, n_pieces, cut_chars (how much of the text fits ``limit`` tokens)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("words", word_bpe.cache_clear)
        bpe = word_bpe(tokenizer)
        for batch in batches:
            raw = column_bytes(batch.column(1))
            rows = []
            for x in raw:
                table = PrefixTable(bpe, x.decode())
                over = table.total > limit
                rows.append((len(x), table.total, over, len(table.pieces), table.cut(limit) if over else None))
            cols = list(zip(*rows, strict=True)) or [[]] * 5
            yield pa.record_batch([batch.column(0), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.bool_()), pa.array(cols[3], pa.int64()), pa.array(cols[4], pa.int64())], names=["doc_id", "n_bytes", "n_tokens", "over_limit", "n_pieces", "cut_chars"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean, n_pieces long, cut_chars long")
