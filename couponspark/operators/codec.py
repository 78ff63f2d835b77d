"""Lossless codecs of one sketch: k row words to bytes and back.

``window_zstd``: leading full columns are an offset; 32 columns from there form a window of four bytes a row; beyond it single
coupons are listed; rows are rotated by one place once more than 3.3 k coupons are there (the leftmost column, nearly full,
then lies beside the empty right end, and bytes repeat more); bytes are laid out column by column and compressed. The others:
``golomb`` (gaps of the rarer value in each column), ``arithmetic`` (range coding with the masses at the estimated count),
``prefix`` (a Huffman code of the eight columns of most entropy, the rest as gaps), and for registers ``register_zstd`` and
``register_nybble`` (four bits above the least register, exceptions listed).
"""

from __future__ import annotations

import heapq
import math
import struct
from collections.abc import Callable

import numpy as np
import pyarrow as pa

ROTATE_ABOVE = 3.3
WINDOW = 32


def _zstd(data: bytes, level: int = 1) -> bytes:
    return pa.Codec("zstd", compression_level=level).compress(data, asbytes=True)


def _unzstd(data: bytes, size: int) -> bytes:
    return pa.Codec("zstd").decompress(data, decompressed_size=size, asbytes=True)


def _bits(words: np.ndarray, columns: int) -> np.ndarray:
    return (words.astype(np.uint64)[:, None] >> np.arange(columns, dtype=np.uint64)) & np.uint64(1) > 0


def _words(bits: np.ndarray) -> np.ndarray:
    return (bits.astype(np.uint64) << np.arange(bits.shape[1], dtype=np.uint64)).sum(axis=1, dtype=np.uint64).astype(np.int64)


def leading_full(words: np.ndarray) -> int:
    every = int(np.bitwise_and.reduce(words.astype(np.uint64))) if len(words) else 0
    n = 0
    while every >> n & 1:
        n += 1
    return n


# ---- windowed zstd

def encode_window(words: np.ndarray, level: int = 1, rotate: bool | None = None, by_column: bool = True) -> bytes:
    w, k = words.astype(np.uint64), len(words)
    offset = min(leading_full(words), 63)
    shifted = w >> np.uint64(offset)
    low = (shifted & np.uint64(0xFFFFFFFF)).astype(np.uint32)
    beyond = shifted >> np.uint64(WINDOW)
    rows, cols = np.nonzero(_bits(beyond, 32))
    if rotate is None:
        rotate = int(np.bitwise_count(w).sum()) > ROTATE_ABOVE * k
    if rotate:
        low = (low >> np.uint32(1)) | (low << np.uint32(31))
    raw = low.view(np.uint8).reshape(k, 4)
    body = _zstd((np.ascontiguousarray(raw.T) if by_column else raw).tobytes(), level)
    return struct.pack("<IBBBI", k, offset, bool(rotate), by_column, len(rows)) + rows.astype("<u4").tobytes() + cols.astype(np.uint8).tobytes() + body


def decode_window(data: bytes) -> np.ndarray:
    k, offset, rotate, by_column, n = struct.unpack_from("<IBBBI", data)
    at = struct.calcsize("<IBBBI")
    rows, cols = np.frombuffer(data, "<u4", n, at), np.frombuffer(data, np.uint8, n, at + 4 * n)
    raw = np.frombuffer(_unzstd(data[at + 5 * n :], 4 * k), np.uint8)
    low = np.ascontiguousarray(raw.reshape(4, k).T if by_column else raw.reshape(k, 4)).view(np.uint32).ravel()
    if rotate:
        low = (low << np.uint32(1)) | (low >> np.uint32(31))
    w = low.astype(np.uint64)
    np.bitwise_or.at(w, rows, np.uint64(1) << (np.uint64(WINDOW) + cols.astype(np.uint64)))
    return ((w << np.uint64(offset)) | np.uint64((1 << offset) - 1)).astype(np.int64)


# ---- bit streams

class BitWriter:
    def __init__(self) -> None:
        self.parts: list[str] = []

    def write(self, value: int, width: int) -> None:
        if width:
            self.parts.append(format(value, f"0{width}b"))

    def unary(self, n: int) -> None:
        self.parts.append("1" * n + "0")

    def bytes(self) -> bytes:
        s = "".join(self.parts)
        return int(s + "0" * (-len(s) % 8) or "0", 2).to_bytes((len(s) + 7) // 8, "big") if s else b""


class BitReader:
    def __init__(self, data: bytes) -> None:
        self.s = format(int.from_bytes(data, "big"), f"0{8 * len(data)}b") if data else ""
        self.at = 0

    def read(self, width: int) -> int:
        v = int(self.s[self.at : self.at + width] or "0", 2) if width else 0
        self.at += width
        return v

    def unary(self) -> int:
        end = self.s.index("0", self.at)
        n = end - self.at
        self.at = end + 1
        return n


def _rice(n: int, k: int) -> int:
    """Rice parameter for gaps between ``n`` ones among ``k`` places."""
    return 0 if n == 0 else max(0, math.floor(math.log2(max(1.0, 0.6931 * k / n))))


def _write_gaps(out: BitWriter, places: np.ndarray, k: int) -> None:
    out.write(len(places), 20)
    r, last = _rice(len(places), k), -1
    for p in places.tolist():
        gap = p - last - 1
        out.unary(gap >> r)
        out.write(gap & (1 << r) - 1, r)
        last = p


def _read_gaps(src: BitReader, k: int) -> np.ndarray:
    n = src.read(20)
    r, last, out = _rice(n, k), -1, []
    for _ in range(n):
        q = src.unary()
        last += 1 + (q << r | src.read(r))
        out.append(last)
    return np.array(out, np.int64)


def encode_golomb(words: np.ndarray, columns: int = 63) -> bytes:
    bits, out = _bits(words, columns), BitWriter()
    top = int(np.flatnonzero(bits.any(axis=0))[-1]) + 1 if bits.any() else 0
    out.write(top, 6)
    for j in range(top):
        flip = bits[:, j].mean() > 0.5
        out.write(int(flip), 1)
        _write_gaps(out, np.flatnonzero(bits[:, j] != flip), len(words))
    return struct.pack("<I", len(words)) + out.bytes()


def decode_golomb(data: bytes) -> np.ndarray:
    (k,), src = struct.unpack_from("<I", data), BitReader(data[4:])
    top = src.read(6)
    bits = np.zeros((k, max(top, 1)), bool)
    for j in range(top):
        bits[:, j] = src.read(1)
        at = _read_gaps(src, k)
        bits[at, j] = ~bits[at, j]
    return _words(bits)


# ---- arithmetic coding (integer range coder for binary symbols)

def _model(words_or_c: int, k: int, columns: int) -> np.ndarray:
    """Chance, in 1/65536, that a cell of each column is collected at the count that ``c`` coupons suggest."""
    p = np.array([2.0 ** -min(j, columns - 1) / k for j in range(1, columns + 1)])
    lo, hi = 0.0, math.log2(k) + 62
    for _ in range(60):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if k * -np.expm1(2.0**mid * np.log1p(-p)).sum() < words_or_c else (lo, mid)
    q = -np.expm1(2.0 ** ((lo + hi) / 2) * np.log1p(-p))
    return np.clip(np.rint(q * 65536), 1, 65535).astype(np.int64)


def encode_arithmetic(words: np.ndarray, columns: int = 63) -> bytes:
    k = len(words)
    c = int(np.bitwise_count(words.astype(np.uint64)).sum())
    bits, model = _bits(words, columns), _model(c, k, columns).tolist()
    low, span, digits = 0, 1 << 32, 0
    cells = bits.T
    for j in range(columns):
        if model[j] <= 1 and not cells[j:].any():
            break
        one = model[j]
        for b in cells[j].tolist():
            cut = (span >> 16) * one
            if b:
                span = cut
            else:
                low += cut
                span -= cut
            while span < 1 << 24:
                low, span, digits = low << 8, span << 8, digits + 1
    # carries are left to big integers: ``low`` holds every digit
    size = digits + 5
    return struct.pack("<IQBI", k, c, columns, size) + low.to_bytes(size, "big")


def decode_arithmetic(data: bytes) -> np.ndarray:
    k, c, columns, size = struct.unpack_from("<IQBI", data)
    raw = data[struct.calcsize("<IQBI") :]
    model = _model(c, k, columns).tolist()
    value, at = int.from_bytes(raw[:5], "big"), 5
    span, bits, left = 1 << 32, np.zeros((k, columns), bool), c
    for j in range(columns):
        one = model[j]
        if left == 0 and one <= 1:
            break
        column = np.zeros(k, bool)
        for i in range(k):
            cut = (span >> 16) * one
            if value < cut:
                span, column[i] = cut, True
            else:
                value -= cut
                span -= cut
            while span < 1 << 24:
                value = value << 8 | (raw[at] if at < size else 0)
                at += 1
                span <<= 8
        left -= int(column.sum())
        bits[:, j] = column
    return _words(bits)


# ---- prefix code of the eight columns with most entropy

def _huffman(weights: np.ndarray) -> dict[int, str]:
    heap = [(float(w), i, (i,)) for i, w in enumerate(weights)]
    codes = {i: "" for i in range(len(weights))}
    heapq.heapify(heap)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        for i in a[2]:
            codes[i] = "0" + codes[i]
        for i in b[2]:
            codes[i] = "1" + codes[i]
        heapq.heappush(heap, (a[0] + b[0], min(a[1], b[1]), a[2] + b[2]))
    return codes


def _prefix_model(c: int, k: int, columns: int) -> tuple[int, dict[int, str]]:
    q = _model(c, k, columns) / 65536
    h = -(q * np.log2(q) + (1 - q) * np.log2(1 - q))
    first = int(np.argmax([h[j : j + 8].sum() for j in range(columns - 7)]))
    patterns = (np.arange(256)[:, None] >> np.arange(8)) & 1
    chance = np.where(patterns > 0, q[first : first + 8], 1 - q[first : first + 8]).prod(axis=1)
    return first, _huffman(chance)


def encode_prefix(words: np.ndarray, columns: int = 63) -> bytes:
    k = len(words)
    c = int(np.bitwise_count(words.astype(np.uint64)).sum())
    first, codes = _prefix_model(c, k, columns)
    out = BitWriter()
    out.parts += [codes[b] for b in ((words.astype(np.uint64) >> np.uint64(first)) & np.uint64(255)).tolist()]
    bits = _bits(words, columns)
    odd = np.concatenate([~bits[:, :first], bits[:, first + 8 :]], axis=1)  # surprises: missing on the left, present on the right
    _write_gaps(out, np.flatnonzero(odd.ravel()), max(odd.size, 1))
    return struct.pack("<IQB", k, c, columns) + out.bytes()


def decode_prefix(data: bytes) -> np.ndarray:
    k, c, columns = struct.unpack_from("<IQB", data)
    first, codes = _prefix_model(c, k, columns)
    back, src = {v: i for i, v in codes.items()}, BitReader(data[struct.calcsize("<IQB") :])
    bits = np.zeros((k, columns), bool)
    middle = np.zeros(k, np.int64)
    for i in range(k):
        end = src.at + 1
        while src.s[src.at : end] not in back:
            end += 1
        middle[i] = back[src.s[src.at : end]]
        src.at = end
    bits[:, first : first + 8] = (middle[:, None] >> np.arange(8)) & 1 > 0
    odd = np.zeros((k, columns - 8), bool)
    odd.ravel()[_read_gaps(src, max(odd.size, 1))] = True
    bits[:, :first], bits[:, first + 8 :] = ~odd[:, :first], odd[:, first:]
    return _words(bits)


# ---- registers

def registers_of(words: np.ndarray) -> np.ndarray:
    w = words.astype(np.uint64)
    return np.array([int(x).bit_length() for x in w], np.uint8)


def encode_register_zstd(regs: np.ndarray) -> bytes:
    return struct.pack("<I", len(regs)) + _zstd(regs.astype(np.uint8).tobytes())


def decode_register_zstd(data: bytes) -> np.ndarray:
    (k,) = struct.unpack_from("<I", data)
    return np.frombuffer(_unzstd(data[4:], k), np.uint8)


def encode_register_nybble(regs: np.ndarray) -> bytes:
    low = int(regs.min())
    rel = np.minimum(regs.astype(np.int64) - low, 15).astype(np.uint8)
    odd = np.flatnonzero(rel == 15)
    padded = np.append(rel, np.zeros(len(rel) % 2, np.uint8))
    return struct.pack("<IBI", len(regs), low, len(odd)) + odd.astype("<u4").tobytes() + regs[odd].astype(np.uint8).tobytes() + (padded[::2] | padded[1::2] << 4).tobytes()


def decode_register_nybble(data: bytes) -> np.ndarray:
    k, low, n = struct.unpack_from("<IBI", data)
    at = struct.calcsize("<IBI")
    odd, values = np.frombuffer(data, "<u4", n, at), np.frombuffer(data, np.uint8, n, at + 4 * n)
    packed = np.frombuffer(data, np.uint8, offset=at + 5 * n)
    regs = (np.stack([packed & 15, packed >> 4], axis=1).ravel()[:k] + low).astype(np.uint8)
    regs[odd] = values
    return regs


CODECS: dict[str, tuple[Callable, Callable]] = {"window_zstd": (encode_window, decode_window), "golomb": (encode_golomb, decode_golomb), "arithmetic": (encode_arithmetic, decode_arithmetic), "prefix": (encode_prefix, decode_prefix)}
REGISTER_CODECS: dict[str, tuple[Callable, Callable]] = {"register_zstd": (encode_register_zstd, decode_register_zstd), "register_nybble": (encode_register_nybble, decode_register_nybble)}
