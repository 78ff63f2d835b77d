"""Small helpers shared by the corpus operators."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import itertools
import tempfile
import uuid
import weakref
from collections.abc import Callable, Iterator, Sequence
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_SEQ = itertools.count()


@lru_cache(maxsize=1)
def _local_dir() -> str:
    return "file://" + tempfile.mkdtemp(prefix="couponspark-")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``, or a local one where it is unset (tests)."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        if not (spark.sparkContext.master == "local" or spark.sparkContext.master.startswith("local[")):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        where = _local_dir()
    return where.rstrip("/")


_STAGED: list[str] = []
_PATHS: weakref.WeakKeyDictionary[DataFrame, str] = weakref.WeakKeyDictionary()


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write an intermediate table to the shared folder and read it back: lineage ends there."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}-{next(_SEQ)}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    _STAGED.append(path)
    _PATHS[out] = path
    return out


def mark() -> int:
    """The number of tables staged so far, for ``sweep``."""
    return len(_STAGED)


def sweep(spark: SparkSession, since: int, *keep: DataFrame) -> None:
    """Delete the tables staged after ``since`` but for those in ``keep``: whatever was made from them has been written."""
    stay = {_PATHS.get(df) for df in keep}
    jvm = spark.sparkContext._jvm
    for path in [p for p in _STAGED[since:] if p not in stay]:
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
        _STAGED.remove(path)


def unused(df: DataFrame, name: str) -> str:
    """A column name that ``df`` does not have, in any case of its letters."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


SALTS = 16
HOT = 4096  # rows of a key from which ``dealt_join`` spreads it


def salted_join(many: DataFrame, one: DataFrame, on: Sequence[str], by: str, how: str = "inner") -> DataFrame:
    """Join rows that may share a key very often (``many``, told apart by column ``by``) with at most one row a key (``one``, which
    should be few): each key is dealt over SALTS tasks. Never broadcast: Spark's estimate of ``one`` knows neither the salts nor
    how far ids unfold in memory, and the driver would hold them all."""
    spread = one.withColumn("__salt", F.explode(F.array(*map(F.lit, range(SALTS)))))
    return many.withColumn("__salt", F.pmod(F.hash(by), F.lit(SALTS))).join(spread.hint("merge"), [*on, "__salt"], how).drop("__salt")


def dealt_join(many: DataFrame, one: DataFrame, on: Sequence[str], by: str, count: str, how: str = "inner") -> DataFrame:
    """``salted_join`` for a ``one`` that may have as many keys as ``many`` has rows: its column ``count`` tells how many rows of
    ``many`` a key has, and only keys of more than HOT rows are repeated. ``one`` should be staged."""
    hot = F.col(count) > HOT
    heavy = one.where(hot).select(*on, F.lit(True).alias("__hot"))
    if not heavy.limit(1).count():
        return many.join(one.hint("merge"), [*on], how)
    salts = F.array(*map(F.lit, range(SALTS)))
    spread = one.withColumn("__salt", F.explode(F.when(hot, salts).otherwise(F.array(F.lit(0)))))
    marked = salted_join(many, heavy, on, by, "left").withColumn("__salt", F.when(F.col("__hot"), F.pmod(F.hash(by), F.lit(SALTS))).otherwise(0))
    return marked.join(spread.hint("merge"), [*on, "__salt"], how).drop("__salt", "__hot")


def one_each(df: DataFrame, key: str) -> DataFrame:
    """One row of each value of ``key``, the one whose other columns have the least hash: however many rows share a value, each
    task sends one of them."""
    rest = [c for c in df.columns if c != key]
    least = F.min(F.struct(F.xxhash64(*rest).alias("__hash"), *rest))
    return df.groupBy(key).agg(least.alias("__one")).select(key, *(f"__one.{c}" for c in rest))


_HELD: dict[str, Callable[[], None]] = {}


@lru_cache(maxsize=1)
def _libc() -> ctypes.CDLL | None:
    """The C library, told to give arrays of some megabytes back as soon as they are freed (fixed value: M_MMAP_THRESHOLD = -3)."""
    with contextlib.suppress(OSError, AttributeError):
        libc = ctypes.CDLL(None)
        libc.mallopt(-3, 4 << 20)
        return libc
    return None


def claim(operator: str, drop: Callable[[], None] = lambda: None) -> None:
    """Say at a task's start which operator uses this Python worker. What another one has kept in it (memos, vocabularies) is
    dropped, and freed memory goes back to the system, so that a chain of operators needs no more than the largest of them."""
    for other in [k for k in _HELD if k != operator]:
        _HELD.pop(other)()
        gc.collect()
    _HELD[operator] = drop
    give_back()


def give_back() -> None:
    """Freed memory of this worker goes back to the system."""
    pa.default_memory_pool().release_unused()
    if _libc() is not None:
        _libc().malloc_trim(0)


def slices(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    """The same rows in small batches, so that a task holds the Python objects of few texts at once; at the end of the task the worker,
    which may stay idle while others work, keeps no more than it must."""
    try:
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                yield batch.slice(at, rows)
    finally:
        batch = None
        gc.collect()
        give_back()


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def total_bytes(docs: DataFrame, text: str = "text") -> int:
    """UTF-8 bytes of all texts: one number, used only to size blocks."""
    return int(docs.agg(F.sum(F.octet_length(F.col(text)))).first()[0] or 0)


def column_bytes(column: pa.ChunkedArray | pa.Array) -> list[bytes]:
    """A string column as UTF-8 bytes; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], column.type)
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return [x or b"" for x in column.cast(kind).to_pylist()]


def pack_arrays(*arrays: np.ndarray) -> bytes:
    """Arrays as one compressed message."""
    head = np.array([len(arrays)] + [v for a in arrays for v in (ord(a.dtype.char), a.size)], np.int64)
    raw = head.tobytes() + b"".join(np.ascontiguousarray(a).tobytes() for a in arrays)
    body = pa.Codec("zstd", compression_level=1).compress(raw, asbytes=True)
    return np.int64(len(raw)).tobytes() + body


def unpack_arrays(message: bytes) -> list[np.ndarray]:
    size = int(np.frombuffer(message, np.int64, 1)[0])
    raw = pa.Codec("zstd").decompress(message[8:], decompressed_size=size, asbytes=True)
    n = int(np.frombuffer(raw, np.int64, 1)[0])
    head = np.frombuffer(raw, np.int64, 2 * n, 8)
    at, out = 8 + 16 * n, []
    for i in range(n):
        kind = np.dtype(chr(head[2 * i]))
        out.append(np.frombuffer(raw, kind, int(head[2 * i + 1]), at))
        at += int(head[2 * i + 1]) * kind.itemsize
    return out


class TextHash:
    """Hashes of substrings by prefix sums modulo 2^64: hash(s) depends on the bytes of s alone."""

    BASE = 0x9E3779B97F4A7C15

    def __init__(self, seed: int = 7) -> None:
        self.table = np.random.default_rng(seed).integers(0, 1 << 64, 256, dtype=np.uint64)
        self.up, self.down = np.ones(1, np.uint64), np.ones(1, np.uint64)

    @staticmethod
    def _powers(base: int, n: int) -> np.ndarray:
        out, m = np.empty(n, np.uint64), 1
        out[0] = 1
        while m < n:
            c = min(m, n - m)
            out[m : m + c] = out[:c] * np.uint64(pow(base, m, 1 << 64))
            m += c
        return out

    def _reach(self, n: int) -> None:
        if len(self.up) <= n:
            size = max(1 << 16, 1 << int(n).bit_length())
            self.up, self.down = self._powers(self.BASE, size), self._powers(pow(self.BASE, -1, 1 << 64), size)

    def prefixes(self, buf: np.ndarray) -> np.ndarray:
        n = len(buf)
        self._reach(n)
        out = np.zeros(n + 1, np.uint64)
        np.cumsum(self.table[buf] * self.up[:n], out=out[1:])
        return out

    @staticmethod
    def mix(h: np.ndarray) -> np.ndarray:
        h = h ^ (h >> np.uint64(29))
        h *= np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(32)
        h *= np.uint64(0x94D049BB133111EB)
        h ^= h >> np.uint64(29)
        return h

    def windows(self, prefix: np.ndarray, size: int) -> np.ndarray:
        """Hash of every window of ``size`` bytes."""
        raw = (prefix[size:] - prefix[:-size]) * self.down[: len(prefix) - size]
        return self.mix(raw)

    def spans(self, prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return self.mix((prefix[end] - prefix[start]) * self.down[start])

