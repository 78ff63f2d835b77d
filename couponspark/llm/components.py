"""Connected components of a table of links, by rounds of contraction.

Each partition first replaces its links by a spanning forest, as a chain through each tree, so that no label has more than
two links a partition. While more than ``bound`` links are left, a round hooks every label to its smallest neighbour, follows
the hooks to their ends, and rewrites the links between the labels that are left; joins on ends, which many labels share, are
salted. At most ``bound`` links (a fixed number, not a share of the input) are finished in one task. Labels are smallest ids.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import mark, salted_join, stage, sweep

BOUND = 200_000


class Forest:
    """Union-find over arbitrary ids; the root of a tree is its smallest id."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def root(self, x: int) -> int:
        up, path = self.up, []
        while (y := up.get(x, x)) != x:
            path.append(x)
            x = y
        for p in path:
            up[p] = x
        return x

    def join(self, a: int, b: int) -> bool:
        a, b = self.root(a), self.root(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True

    def links(self) -> Iterable[tuple[int, int]]:
        return ((x, self.root(x)) for x in list(self.up))


def chain(links: Iterable[tuple[int, int]]) -> list[tuple[int, int]]:
    """(id, id before it in its tree) for each (id, root)."""
    last: dict[int, int] = {}
    out = []
    for x, root in sorted(links):
        out.append((x, last.get(root, root)))
        last[root] = x
    return out


def _forest(chained: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forest = Forest()
        for batch in batches:
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                forest.join(a, b)
        links = [(x, root) for x, root in forest.links() if x != root]
        pairs = np.array(chain(links) if chained else links, np.int64).reshape(-1, 2)
        yield pa.record_batch([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])

    return run


def components(links: DataFrame, bound: int = BOUND) -> DataFrame:
    """(id, component) of every id in ``links`` (a long, b long) that is not the smallest of its component."""
    clean = links.select(F.col("a").cast("long"), F.col("b").cast("long")).where("a is not null and b is not null and a <> b")
    spark, since = links.sparkSession, mark()
    edges = stage(clean.mapInArrow(_forest(True), "a long, b long"), "links")
    maps: list[DataFrame] = []
    while edges.count() > bound:
        both = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
        hooks = stage(both.groupBy("a").agg(F.min("b").alias("b")), "hooks")
        while True:  # a hook's end is found by doubling
            far = salted_join(hooks, hooks.toDF("b", "further"), ["b"], "a", "left")
            far = stage(far.select("a", F.coalesce("further", "b").alias("b"), F.col("further").isNotNull().alias("moved")), "hooks")
            moved = far.where("moved").limit(1).count()
            hooks = far.select("a", "b")
            if not moved:
                break
        maps.append(far)
        # a label is the larger end of some of its links and the smaller of others: both ends become their hooks
        ends = salted_join(both, hooks.withColumnRenamed("b", "to"), ["a"], "b", "left").select(F.coalesce("to", "a").alias("a"), "b")
        ends = salted_join(ends, hooks.toDF("b", "to"), ["b"], "a", "left").select("a", F.coalesce("to", "b").alias("b"))
        edges = stage(ends.where("a <> b").mapInArrow(_forest(True), "a long, b long"), "links")
        sweep(spark, since, edges, *maps)
    out = edges.repartition(1).mapInArrow(_forest(False), "a long, b long")
    for i, far in enumerate(reversed(maps)):
        last = stage(out, "labels")
        hooks, to = far.select("a", "b"), last.toDF("b", "to")
        # the innermost labels are ``bound`` at most
        joined = hooks.join(F.broadcast(to), "b", "left") if i == 0 and bound <= BOUND else salted_join(hooks, to, ["b"], "a", "left")
        out = joined.select("a", F.coalesce("to", "b").alias("b")).union(last)
    return out.select(F.col("a").alias("id"), F.col("b").alias("component"))
