"""Packed sketches as a table: one row a group, the body compressed, partitioned by the group's columns."""

from __future__ import annotations

import tempfile
from collections.abc import Sequence
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from couponspark.operators.codec import decode_window, encode_window


@lru_cache(maxsize=1)
def _local_dir() -> str:
    return "file://" + tempfile.mkdtemp(prefix="couponspark-")


def scratch(spark: SparkSession) -> str:
    """A folder that all executors see: the session's checkpoint folder; a local one where it is unset (tests)."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        if not (spark.sparkContext.master == "local" or spark.sparkContext.master.startswith("local[")):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        where = _local_dir()
    return where.rstrip("/")


def pack(words: DataFrame, by: Sequence[str], k: int, columns: int, profile: str = "portable") -> DataFrame:
    """(by.., k, profile, columns, coupons, body): the words of each group, at most k rows, in one compressed value."""
    gathered = words.groupBy(*by).agg(F.sum(F.bit_count("word")).alias("coupons"), F.collect_list(F.struct("row_id", "word")).alias("rows"))

    @F.pandas_udf("binary")
    def body(rows, words):  # noqa: ANN001, ANN202
        out = []
        for r, v in zip(rows, words, strict=True):
            w = np.zeros(k, np.int64)
            w[np.asarray(r, np.int64)] = v
            out.append(encode_window(w))
        return pd.Series(out)

    return gathered.select(*by, F.lit(k).alias("k"), F.lit(profile).alias("profile"), F.lit(columns).alias("columns"), "coupons", body("rows.row_id", "rows.word").alias("body"))


def unpacked_size(words: DataFrame, by: Sequence[str], k: int, encode) -> DataFrame:  # noqa: ANN001
    """(by.., coupons, size): bytes that a codec needs for the words of each group, at most k rows."""
    gathered = words.groupBy(*by).agg(F.sum(F.bit_count("word")).alias("coupons"), F.collect_list(F.struct("row_id", "word")).alias("rows"))

    @F.pandas_udf("long")
    def size(rows, found):  # noqa: ANN001, ANN202
        out = []
        for r, v in zip(rows, found, strict=True):
            w = np.zeros(k, np.int64)
            w[np.asarray(r, np.int64)] = v
            out.append(len(encode(w)))
        return pd.Series(out)

    return gathered.select(*by, "coupons", size("rows.row_id", "rows.word").alias("size"))


def unpack(sketches: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """(by.., row_id, word) of packed sketches."""
    keep = [f for f in sketches.schema if f.name in by]
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in keep), "row_id int, word long"])

    def run(batches):  # noqa: ANN001, ANN202
        for batch in batches:
            words = [decode_window(b) for b in batch.column(batch.num_columns - 1).to_pylist()]
            rows = [np.flatnonzero(w) for w in words]
            at = pa.array(np.repeat(np.arange(len(rows)), [len(r) for r in rows]))
            cols = [batch.column(i).take(at) for i in range(len(keep))]
            flat = np.concatenate(rows) if rows else np.zeros(0, np.int64)
            vals = np.concatenate([w[r] for w, r in zip(words, rows, strict=True)]) if rows else np.zeros(0, np.int64)
            yield pa.record_batch([*cols, pa.array(flat.astype(np.int32)), pa.array(vals)], names=[*(f.name for f in keep), "row_id", "word"])

    return sketches.select(*[f.name for f in keep], "body").mapInArrow(run, schema)


def check_same(a: DataFrame, b: DataFrame) -> None:
    """Sketches of unequal shape don't merge: said before anything of size runs."""
    shape = lambda s: {tuple(r) for r in s.select("k", "profile", "columns").distinct().limit(2).collect()}
    if len(shape(a) | shape(b)) > 1:
        raise ValueError("sketches of different k, profile or columns can't be merged")


def write_sketches(words: DataFrame, by: Sequence[str], path: str, k: int, columns: int, profile: str = "portable") -> None:
    """New groups replace old ones of the same partition; others stay."""
    pack(words, by, k, columns, profile).write.partitionBy(*by).mode("overwrite").option("partitionOverwriteMode", "dynamic").parquet(path)


def read_sketches(spark: SparkSession, path: str, by: Sequence[str] = ()) -> DataFrame:
    return unpack(spark.read.parquet(path), by)
