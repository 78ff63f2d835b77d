"""Ids from files of several kinds, with the schema given and only the columns asked for."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession

KINDS = ("parquet", "csv", "json", "text", "orc")


def read_ids(spark: SparkSession, path: str, columns: Sequence[str], kind: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    """The id and group columns of a file set. csv and json need a schema, so that no pass infers one; text has ``value``."""
    if kind not in KINDS:
        raise ValueError(f"kind must be one of {KINDS}")
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    reader = spark.read.options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    return reader.format(kind).load(path).select(*columns)


def stream_ids(spark: SparkSession, path: str, columns: Sequence[str], schema: str, kind: str = "parquet", **options: str) -> DataFrame:
    return spark.readStream.schema(schema).options(**options).format(kind).load(path).select(*columns)


def rate_ids(spark: SparkSession, rows_per_second: int = 1000) -> DataFrame:
    """A stream of distinct numbers, for load tests: timestamp, value."""
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
