"""Near-duplicate vectors by p-stable hashing and exact cosine.

Unit vectors at cosine c lie sqrt(2 - 2c) apart, so quantised random projections put close vectors into one bucket. Each of
several tables joins some projections to a key. The number of projections lets a bucket of unrelated vectors grow with the root
of the input, which keeps matrix products a small share and the tables few: their number follows from the recall wanted at the
threshold itself. In each bucket all pairs are
compared by matrix products in double precision. A pair counts in the first table where both keys agree, so no pair is sent or
counted twice, and none is emitted: a bucket returns how many links each vector has there, and a spanning forest of them. Vectors
travel in the precision that they came in and without keys: a bucket works out the keys of those that have a link there.

Equal vectors are one point with a weight. A bucket of more than ``BLOCK`` points is cut into blocks, and pairs of blocks are
separate tasks, so that no bucket is ever gathered in one place.

Edge cases: vectors that are null, empty, zero or hold null or non-finite components link with nothing; so do vectors of
different lengths; rows without an id are returned with no link; extra columns are ignored; an empty table gives an empty one.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import FloatType

from .common import dealt_join, stage
from .components import Forest, chain, components

BLOCK = 512
WIDTH_FACTOR = 4.0  # bucket width, in distances at the threshold


def _phi(x: float) -> float:
    return 0.5 * (1 + math.erf(x / math.sqrt(2)))


def collide(distance: float, width: float) -> float:
    """Chance that one quantised Gaussian projection agrees for two points at a distance."""
    if distance <= 0:
        return 1.0
    r = width / distance
    return 1 - 2 * _phi(-r) - 2 / (math.sqrt(2 * math.pi) * r) * (1 - math.exp(-r * r / 2))


def plan(points: int, threshold: float, recall: float, bucket: int = 0) -> tuple[float, int, int]:
    """Bucket width, projections a table, tables. ``bucket``: unrelated vectors in one bucket, the root of ``points`` but BLOCK at least."""
    bucket = bucket or max(BLOCK, math.isqrt(points))
    near = math.sqrt(2 - 2 * threshold)
    width = WIDTH_FACTOR * near
    far = collide(math.sqrt(2), width)  # vectors that have nothing to do with each other
    k = max(2, math.ceil(math.log(max(2.0, points / bucket)) / -math.log(far)))
    together = collide(near, width) ** k
    return width, k, max(1, math.ceil(math.log(1 - recall) / math.log1p(-together)))


def _projections(dim: int, k: int, tables: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng([seed, dim])
    return rng.standard_normal((dim, k * tables)), rng.random(k * tables)


def table_keys(x: np.ndarray, width: float, k: int, tables: int, seed: int) -> np.ndarray:
    """64-bit key of each unit vector in each table."""
    a, shift = _projections(x.shape[1], k, tables, seed)
    # one vector after the other in a fixed order of sums: equal vectors get equal keys in whatever company
    cells = np.floor(np.einsum("ij,jk->ik", x, a) / width + shift).astype(np.int64).view(np.uint64).reshape(len(x), tables, k)
    h = np.full((len(x), tables), np.uint64(0x9E3779B97F4A7C15))
    for i in range(k):
        h = (h ^ cells[:, :, i]) * np.uint64(0xFF51AFD7ED558CCD)
        h ^= h >> np.uint64(32)
    return h


def _vectors(column: pa.ChunkedArray) -> list[np.ndarray | None]:
    out: list[np.ndarray | None] = []
    for v in column.to_pylist():
        x = None if v is None or any(c is None for c in v) else np.array(v, np.float64)
        if x is not None and (not len(x) or not np.isfinite(x).all() or not x.any()):
            x = None
        out.append(x)
    return out


def _points(single: bool):
    """Usable vectors as bytes; those in double precision are scaled, so that no square overflows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [None if x is None else (x.astype(np.float32) if single else x / np.abs(x).max()).tobytes() for x in _vectors(pa.chunked_array([batch.column(1)]))]
            yield pa.record_batch([batch.column(0), pa.array(rows, pa.binary())], names=["vec_id", "x"])

    return run


def units(raw: list[bytes], single: bool) -> np.ndarray:
    """Vectors of one length, normalised in double precision."""
    x = np.array([np.frombuffer(v, np.float32 if single else np.float64) for v in raw], np.float64)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _keyed(width: float, k: int, tables: int, seed: int, single: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw = batch.column(1).to_pylist()
            keys: list[np.ndarray | None] = [None] * len(raw)
            for size in {len(x) for x in raw}:
                at = [i for i, x in enumerate(raw) if len(x) == size]
                h = table_keys(units([raw[i] for i in at], single), width, k, tables, seed)
                for i, row in zip(at, h, strict=True):
                    keys[i] = (row ^ np.uint64(size)).view(np.int64)
            yield pa.record_batch([batch.column(0), pa.array(keys, pa.list_(pa.int64()))], names=["rep", "buckets"])

    return run


def _pairs(threshold: float, width: float, k: int, tables: int, seed: int, single: bool):
    """Links between the two sides of a task (block a and block b of a bucket; both the same for the diagonal)."""

    def run(table: pa.Table) -> pa.Table:
        number = table.column("table")[0].as_py()
        a, b = table.column("a")[0].as_py(), table.column("b")[0].as_py()
        reps, side, weight = (table.column(c).to_numpy().astype(np.int64) for c in ("rep", "block", "weight"))
        x = units(table.column("x").to_pylist(), single)
        left = np.flatnonzero(side == a)
        right = left if a == b else np.flatnonzero(side == b)
        got, forest = np.zeros(len(reps), np.int64), Forest()
        near = x[left] @ x[right].T >= threshold
        if a == b:
            near = np.triu(near, 1)
        i, j = np.nonzero(near)
        i, j = left[i], right[j]
        if number and len(i):
            # a pair that an earlier table has in one bucket counts there
            ends, at = np.unique(np.r_[i, j], return_inverse=True)
            keys = table_keys(x[ends], width, k, tables, seed)[:, :number]
            fresh = np.ones(len(i), bool)
            for lo in range(0, len(i), 1 << 16):
                part = slice(lo, min(lo + (1 << 16), len(i)))
                fresh[part] = ~(keys[at[: len(i)][part]] == keys[at[len(i) :][part]]).any(axis=1)
            i, j = i[fresh], j[fresh]
        np.add.at(got, i, weight[j])
        np.add.at(got, j, weight[i])
        for p, q in zip(reps[i].tolist(), reps[j].tolist(), strict=True):
            forest.join(p, q)
        ids = np.flatnonzero(got)
        # a chain through each tree, so that no vector gets many links
        before = dict(chain((x, root) for x, root in forest.links() if x != root))
        return pa.table([pa.array(reps[ids]), pa.array(got[ids]), pa.array([before.get(r, r) for r in reps[ids].tolist()], pa.int64())], names=["rep", "links", "other"])

    return run


def near_vectors(vectors: DataFrame, threshold: float = 0.9, recall: float = 0.995, seed: int = 3) -> DataFrame:
    """vec_id, n_links, component_id, kept of each row of ``vectors`` (vec_id, embedding)."""
    single = isinstance(vectors.schema["embedding"].dataType.elementType, FloatType)
    rows = stage(vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding")).mapInArrow(_points(single), "vec_id long, x binary").withColumn("digest", F.unhex(F.sha2("x", 256))), "vectors")
    usable = rows.where("x is not null and vec_id is not null")
    points = stage(usable.groupBy("x", "digest").agg(F.min("vec_id").alias("rep"), F.count("*").alias("weight")).select("rep", "weight", "digest", "x"), "points")
    width, k, tables = plan(points.count(), threshold, recall)
    keyed = points.select("rep", "x").mapInArrow(_keyed(width, k, tables, seed, single), "rep long, buckets array<long>")
    slots = stage(keyed.select("rep", F.posexplode("buckets").alias("table", "bucket")), "slots")
    sizes = stage(slots.groupBy("table", "bucket").agg(F.count("*").alias("n")).where("n > 1"), "buckets")
    # buckets of several points; members of a large one are dealt over several keys on the way
    members = dealt_join(slots, sizes, ["table", "bucket"], "rep", "n").withColumn("blocks", F.ceil(F.col("n") / BLOCK).cast("int"))
    members = members.withColumn("block", F.pmod(F.hash("rep", "table"), F.col("blocks")).cast("int"))
    # block pairs (a, b) with a <= b that a member takes part in
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    tasks = members.withColumn("o", other).withColumn("a", F.least("block", "o")).withColumn("b", F.greatest("block", "o")).select("rep", "table", "bucket", "block", "a", "b")
    found = tasks.join(points.select("rep", "weight", "x").hint("merge"), "rep").withColumn("size", F.length("x")).groupBy("table", "bucket", "a", "b", "size").applyInArrow(_pairs(threshold, width, k, tables, seed, single), "rep long, links long, other long")
    found = stage(found, "vector-links")
    counts = found.groupBy("rep").agg(F.sum("links").alias("links"))
    labels = components(found.select(F.col("rep").alias("a"), F.col("other").alias("b"))).withColumnRenamed("id", "rep")
    # vectors of no link need no more than their own row; copies of one vector are linked, whatever else is
    known = points.select("rep", "weight", "digest").join(counts.hint("merge"), "rep", "left").join(labels.hint("merge"), "rep", "left")
    known = known.select("digest", "weight", (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    known = stage(known.where("n_links > 0"), "known")
    # a vector with very many copies is dealt over several keys
    out = dealt_join(rows.select("vec_id", "digest"), known, ["digest"], "vec_id", "weight", "left")
    own = F.col("vec_id").isNotNull()
    component = F.when(own, F.coalesce("component_id", "vec_id"))
    return out.select("vec_id", F.when(own, F.coalesce("n_links", F.lit(0))).otherwise(0).alias("n_links"), component.alias("component_id")).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
