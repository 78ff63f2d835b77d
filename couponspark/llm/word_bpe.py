"""Word-level BPE by dynamic programming over prefixes.

For every prefix of a word the last token of its encoding is unique: it is the token that ends there and is compatible with
the last token of the prefix before it. One pass over a word so gives its ids and the exact token count of every prefix.
Two neighbouring tokens are compatible if no merge fires across their border: a symbol on the right edge of the first and
one on the left edge of the second would have to merge before either is absorbed into its own token.

The vocabulary file of the ``tokenizers`` library (BPE with an end-of-word suffix) is read, never copied or trained.
"""

from __future__ import annotations

import json
import unicodedata
from functools import cached_property, lru_cache

import numpy as np
import regex
import tiktoken
from tokenizers import Tokenizer

#: Characters whose classes and case no recent Unicode version has changed; other texts go through the library's own steps.
SETTLED = regex.compile("[^\x00-\u017E\u0391-\u03A9\u03B1-\u03C9\u0410-\u044F\u2010-\u2027\u2030-\u205E\u20AC\u2122\u3041-\u3096\u30A1-\u30FA\u4E00-\u9FA5\uAC00-\uD7A3]")
NEVER = 1 << 60
END = b"\xff"
CACHE = 200_000
LONG = 64


def byte_symbols() -> list[str]:
    """The printable character that byte-level vocabularies use for each byte (a published rule)."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out, extra = [""] * 256, 0
    for b in plain:
        out[b] = chr(b)
    for b in range(256):
        if not out[b]:
            out[b] = chr(256 + extra)
            extra += 1
    return out


class _Cache(dict):
    """A bounded memo of two generations: when the new one is full it becomes the old one; long words are not kept."""

    def __init__(self, make, share: int = 1) -> None:
        self.make, self.bound = make, CACHE // share
        self.old: dict = {}

    def __missing__(self, key):
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
        if len(key) <= LONG:
            if len(self) >= self.bound:
                self.old = dict(self)
                self.clear()
            self[key] = value
        return value


class WordBpe:
    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.suffix = model["end_of_word_suffix"]
        self.vocab: dict[str, int] = model["vocab"]
        self.path = path
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.special_pattern = regex.compile("|".join(regex.escape(x) for x in sorted(self.special, key=len, reverse=True))) if self.special else None
        split = spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]
        self.pattern = regex.compile(split)
        self.symbols = byte_symbols()
        self.merge: dict[tuple[int, int], tuple[int, int]] = {}
        self.parts: dict[int, tuple[int, int, int]] = {}
        for rank, pair in enumerate(model["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            new = self.vocab[a + b]
            self.merge[self.vocab[a], self.vocab[b]] = (rank, new)
            self.parts.setdefault(new, (rank, self.vocab[a], self.vocab[b]))
        # by the bytes they stand for, inside a word and at its end
        back = {s: i for i, s in enumerate(self.symbols)}
        self.inner: dict[bytes, int] = {}
        self.final: dict[bytes, int] = {}
        self.text_of: dict[int, tuple[bytes, bool]] = {}
        for s, i in self.vocab.items():
            ends = s.endswith(self.suffix)
            raw = bytes(back[c] for c in (s[: -len(self.suffix)] if ends else s))
            (self.final if ends else self.inner)[raw] = i
            self.text_of[i] = (raw, ends)
        self.longest = max(map(len, [*self.inner, *self.final]))
        # longest token by its last two bytes
        self.back_inner: dict[bytes, int] = {}
        self.back_final: dict[bytes, int] = {}
        for raw in self.inner:
            self.back_inner[raw[-2:]] = max(self.back_inner.get(raw[-2:], 0), len(raw))
        for raw in self.final:
            self.back_final[raw[-2:]] = max(self.back_final.get(raw[-2:], 0), len(raw))
        self._edge_memo: dict[tuple[int, bool], list[tuple[int, int]]] = {}
        self._fits: dict[tuple[int, int], bool] = {}
        self._whole: dict[int, bool] = {}
        self._piece, self.four = None, []
        self.counts = _Cache(self._count, 4)
        # for whole runs between white space, which most texts repeat: one look-up a run
        self.run_ids = _Cache(self._run_ids)
        self.run_counts = _Cache(self._run_counts)

    @cached_property
    def library(self) -> Tokenizer:
        """The library's own steps, for texts whose characters are not settled; loaded when the first of them comes."""
        return Tokenizer.from_file(self.path)

    # ---- compatibility

    def _edge(self, token: int, right: bool) -> list[tuple[int, int]]:
        """The symbols on one edge of a token while it is built, each with the rank of the merge that absorbs it."""
        key = (token, right)
        if key not in self._edge_memo:
            out, until = [], NEVER
            while True:
                out.append((token, until))
                if token not in self.parts:
                    break
                until, a, b = self.parts[token]
                token = b if right else a
            self._edge_memo[key] = out
        return self._edge_memo[key]

    def fits(self, a: int, b: int) -> bool:
        key = (a, b)
        if key not in self._fits:
            if len(self._fits) > 500_000:
                self._fits.clear()
            merge = self.merge
            self._fits[key] = not any((m := merge.get((x, y))) and m[0] < gone_x and m[0] <= gone_y for x, gone_x in self._edge(a, True) for y, gone_y in self._edge(b, False))
        return self._fits[key]

    def whole(self, token: int) -> bool:
        """Encoding the token's own text gives the token."""
        if token not in self._whole:
            if token not in self.parts:
                self._whole[token] = True
            else:
                rank, a, b = self.parts[token]
                early = any((m := self.merge.get((x, y))) and m[0] < rank and m[0] < gx and m[0] <= gy for x, gx in self._edge(a, True) for y, gy in self._edge(b, False) if (x, y) != (a, b))
                self._whole[token] = not early and self.whole(a) and self.whole(b)
        return self._whole[token]

    # ---- words

    def solve(self, word: str, prefixes: bool = True) -> tuple[list[int], list[int]]:
        """Token counts of all prefixes of a word (by characters, each as a word of its own), and the word's ids.

        Without ``prefixes`` only the last count is there.
        """
        raw = word.encode()
        n = len(raw)
        last, back, size = [0] * (n + 1), [0] * (n + 1), [0] * (n + 1)
        counts: list[int] = []
        inner, final, fits = self.inner, self.final, self.fits
        end, end_at = 0, 0
        back_inner, back_final, memo = self.back_inner, self.back_final, self._fits
        for i in range(1, n + 1):
            tail = raw[i - 2 : i] if i > 1 else raw[:1]
            if i < n:
                for j in range(max(0, i - back_inner.get(tail, 1)), i):
                    t = inner.get(raw[j:i])
                    if t is not None:
                        if not j:
                            ok = self.whole(t)
                        else:
                            ok = memo.get(key := (last[j], t))
                            if ok is None:
                                ok = fits(*key)
                        if ok:
                            last[i], back[i], size[i] = t, j, size[j] + 1
                            break
                else:
                    raise ValueError("the vocabulary lacks a byte")
            if i == n or prefixes and raw[i] & 0xC0 != 0x80:
                for j in range(max(0, i - back_final.get(tail, 1)), i):
                    t = final.get(raw[j:i])
                    if t is not None:
                        if not j:
                            ok = self.whole(t)
                        else:
                            ok = memo.get(key := (last[j], t))
                            if ok is None:
                                ok = fits(*key)
                        if ok:
                            end, end_at = t, j
                            counts.append(size[j] + 1)
                            break
                else:
                    raise ValueError("the vocabulary lacks a final byte")
        ids = [end]
        while end_at:
            ids.append(last[end_at])
            end_at = back[end_at]
        return counts, ids[::-1]

    def _count(self, word: str) -> int:
        """Tokens of a word: the same program from its end, which asks only for the prefixes that some token leaves."""
        raw = word.encode()
        n = len(raw)
        if n > LONG:
            return self.solve(word, prefixes=False)[0][-1]
        inner, whole, memo, fits, reach = self.inner, self.whole, self._fits, self.fits, self.back_inner
        last, size = [-1] * n, [0] * n

        def prefix(i: int) -> int:
            for j in range(max(0, i - reach.get(raw[i - 2 : i] if i > 1 else raw[:1], 1)), i):
                t = inner.get(raw[j:i])
                if t is None:
                    continue
                if not j:
                    ok = whole(t)
                else:
                    a = last[j]
                    if a < 0:
                        a = prefix(j)
                    ok = memo.get(key := (a, t))
                    if ok is None:
                        ok = fits(a, t)
                if ok:
                    last[i], size[i] = t, size[j] + 1
                    return t
            raise ValueError("the vocabulary lacks a byte")

        final = self.final
        for j in range(max(0, n - self.back_final.get(raw[n - 2 :], 1)), n):
            t = final.get(raw[j:])
            if t is None:
                continue
            if not j:
                if whole(t):
                    return 1
            else:
                a = last[j] if last[j] >= 0 else prefix(j)
                ok = memo.get(key := (a, t))
                if ok is None:
                    ok = fits(a, t)
                if ok:
                    return size[j] + 1
        raise ValueError("the vocabulary lacks a final byte")

    def _merger(self):
        """The same merges for tiktoken: a byte that no UTF-8 text holds ends the word, and joins the last byte first.

        tiktoken merges any two pieces whose bytes are a token's. Inside a token's own bytes the pieces are always those of the
        token alone, so for tokens that encoding their own text gives, that is the merge of the vocabulary; others are left out.
        """
        single = {bytes([b]): b for b in range(256) if b != 255} | {END: 256}
        ranks, out = dict(single), np.zeros(513 + len(self.merge), np.int64)
        for b in range(256):
            out[b] = self.inner[bytes([b])]
            ranks[bytes([b]) + END] = 257 + b
            out[257 + b] = self.final[bytes([b])]
        for token, (rank, _, _) in self.parts.items():
            if self.whole(token):
                raw, ends = self.text_of[token]
                ranks[raw + END if ends else raw] = 513 + rank
                out[513 + rank] = token
        core = tiktoken.Encoding("words", pat_str=r"\S+", mergeable_ranks=ranks, special_tokens={})
        return core._core_bpe.encode_single_piece, [int(i).to_bytes(4, "little") for i in out]

    def split(self, raw: bytes) -> bytes:
        """The ids of a word as bytes, without counts."""
        if self._piece is None:
            self._piece, self.four = self._merger()
        four = self.four
        return b"".join([four[t] for t in self._piece(raw + END)])

    def _run_ids(self, run: bytes) -> bytes:
        if run.isalpha():  # ASCII letters: one pre-token
            return self.split(run)
        return b"".join([self.split(w.encode()) for w in self.pattern.findall(run.decode())])

    def _run_counts(self, run: bytes) -> int:
        return sum([self.counts[w] for w in self.pattern.findall(run.decode())])

    def prefix_counts(self, word: str) -> list[int]:
        """Exact counts of all prefixes of one pre-token; a cut contraction falls apart into two pre-tokens."""
        counts = list(self.solve(word)[0])
        if word[:1] == "'" and word[1:2].isalpha():
            for i in range(1, len(word)):
                counts[i - 1] = sum(self.counts[p] for p in self.pattern.findall(word[:i]))
        return counts

    # ---- texts

    def fold(self, text: str) -> bytes | None:
        """The normalised text, if ASCII white space then splits it as the pattern does; None sends it the long way."""
        if self.special_pattern is not None and "<|" in text and self.special_pattern.search(text):
            return None
        if text.isascii():
            return text.lower().encode()
        if SETTLED.search(text) is None:
            return unicodedata.normalize("NFC", text).replace("Σ", "σ").lower().replace("\x85", " ").replace("\xa0", " ").encode()
        return None

    def plain_words(self, text: str) -> list[str]:
        """Pre-tokens of a text without special strings, by the library's own steps."""
        done = self.library.normalizer.normalize_str(text)
        back = {s: i for i, s in enumerate(self.symbols)}
        return [bytes(back[c] for c in p).decode() for p, _ in self.library.pre_tokenizer.pre_tokenize_str(done)]

    def words(self, text: str) -> list[str]:
        """Pre-tokens of a text; special strings stay whole, as the library's default has it."""
        folded = self.fold(text)
        if folded is not None:
            return self.pattern.findall(folded.decode())
        out, at = [], 0
        for m in self.special_pattern.finditer(text) if self.special_pattern is not None else ():
            out += self.plain_words(text[at : m.start()])
            out.append(m.group())
            at = m.end()
        return out + self.plain_words(text[at:])

    def encode_bytes(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        folded = self.fold(text)
        if folded is not None:
            return b"".join(map(self.run_ids.__getitem__, folded.split()))
        return b"".join([self.special[w].to_bytes(4, "little") if w in self.special else self.split(w.encode()) for w in self.words(text)])


@lru_cache(maxsize=4)
def word_bpe(path: str) -> WordBpe:
    """One instance a worker process."""
    return WordBpe(path)


@lru_cache(maxsize=4)
def id_bpe(path: str) -> WordBpe:
    """One that only encodes: the tables that its merger was made from, and that counts need, are dropped."""
    out = WordBpe(path)
    out._piece, out.four = out._merger()
    for name in ("merge", "parts", "vocab", "text_of", "inner", "final", "back_inner", "back_final", "_edge_memo", "_fits", "_whole"):
        setattr(out, name, {})
    return out
