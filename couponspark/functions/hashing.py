"""From identifiers to coupons: two hash profiles, row and column of the coupon matrix, masses.

``fast`` hashes with xxhash64 under two seeds and takes the column as the lowest set bit, so that the coupon's bit needs no
column number. ``portable`` slices md5 of the rendered id, which any SQL engine can repeat. Both give column j mass 2^-j/k,
truncated so that all masses sum to 1. A matrix row is one BIGINT: bit j-1 stands for column j.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PORTABLE_COLUMNS = 61  # leading zeros of 60 bits, 0..60
FAST_COLUMNS = 63
FAST_SEED = 0x5BD1E995


def columns_of(profile: str) -> int:
    """Number of columns of a profile's matrix."""
    return {"portable": PORTABLE_COLUMNS, "fast": FAST_COLUMNS}[profile]


def as_columns(ids: str | Column | Sequence[str | Column]) -> list[Column]:
    ids = [ids] if isinstance(ids, str | Column) else list(ids)
    return [F.col(c) if isinstance(c, str) else c for c in ids]


def shift_left(value: Column, places: Column) -> Column:
    return F.call_function("shiftleft", value, places.cast("int"))


def present(ids: str | Column | Sequence[str | Column]) -> Column:
    """No part of the id is null (as in ``count(distinct ...)``)."""
    out = F.lit(True)
    for c in as_columns(ids):
        out = out & c.isNotNull()
    return out


def canonical(c: Column, kind: str) -> Column:
    """One value for equal ids whatever type holds them: integers widened, negative zero as zero, text free of its length."""
    if kind in ("tinyint", "smallint", "int"):
        return c.cast("bigint")
    if kind in ("float", "double"):
        return F.when(c == 0, F.lit(0.0)).otherwise(c.cast("double"))
    if kind.startswith(("varchar", "char")):
        return c.cast("string")
    return c


def typed(df: DataFrame, ids: str | Column | Sequence[str | Column]) -> list[Column]:
    """The id columns of ``df`` in one rendering, so that a sketch of INT ids merges with one of BIGINT ids."""
    cols = as_columns(ids)
    return [canonical(c, f.dataType.simpleString()) for c, f in zip(cols, df.select(*cols).schema, strict=True)]


def portable_pair(ids: str | Column | Sequence[str | Column], seed: str | Column | None = None) -> tuple[Column, Column]:
    """(hi, lo): 60 bits for the column and 60 for the row. Parts of an id are joined by ``|``, as SQL twins do: parts that may hold
    that sign themselves need the fast profile."""
    parts = [c.cast("string") for c in as_columns(ids)]
    if seed is not None:
        parts = [(F.lit(seed) if isinstance(seed, str) else seed).cast("string"), *parts]
    digest = F.md5(F.concat_ws("|", *parts) if len(parts) > 1 else parts[0])
    number = lambda at: F.conv(F.substring(digest, at, 15), 16, 10).cast("bigint")
    return number(1), number(18)


def fast_pair(ids: str | Column | Sequence[str | Column], seed: Column | None = None) -> tuple[Column, Column]:
    """Two 64-bit words; a leading literal starts another chain of seeds."""
    cols = as_columns(ids) if seed is None else [seed, *as_columns(ids)]
    return F.xxhash64(F.lit(FAST_SEED), *cols), F.xxhash64(*cols)


def row_of(h: Column, k: int) -> Column:
    return (h.bitwiseAND(F.lit(k - 1)) if k & (k - 1) == 0 else F.pmod(h, F.lit(k))).cast("int")


def leading_column(hi: Column, width: int = 60) -> Column:
    """1 + leading zeros of a ``width``-bit number."""
    return F.when(hi == 0, F.lit(width + 1)).otherwise(F.lit(width + 1) - F.length(F.bin(hi))).cast("int")


def lowest_bit(h: Column) -> Column:
    """The lowest set bit of a word, with bit 62 as a guard: a BIGINT with one bit."""
    guarded = h.bitwiseAND(F.lit((1 << 62) - 1)).bitwiseOR(F.lit(1 << 62))
    return guarded.bitwiseAND(-guarded)


def column_number(bit: Column) -> Column:
    return F.length(F.bin(bit)).cast("int")


def coupon(ids: str | Column | Sequence[str | Column], k: int, profile: str = "fast", seed: str | Column | None = None) -> tuple[Column, Column]:
    """(row_id, word bit) of an id."""
    if profile == "portable":
        hi, lo = portable_pair(ids, seed)
        return row_of(lo, k), shift_left(F.lit(1).cast("bigint"), leading_column(hi) - 1)
    hi, lo = fast_pair(ids, F.lit(seed) if isinstance(seed, str) else seed)
    return row_of(lo, k), lowest_bit(hi)


def mass_units(col_id: Column, columns: int) -> Column:
    """Mass of a coupon in exact units of 2^(1-columns)/k, as DECIMAL: the k*columns masses sum to k*2^(columns-1)."""
    exponent = F.lit(columns - 1) - F.least(col_id, F.lit(columns - 1))
    low = F.least(exponent, F.lit(31))
    return (shift_left(F.lit(1).cast("bigint"), low).cast("decimal(19,0)") * shift_left(F.lit(1).cast("bigint"), exponent - low).cast("decimal(18,0)")).cast("decimal(38,0)")
