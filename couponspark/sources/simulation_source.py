"""A data source of simulated runs: ``spark.read.format("coupon_runs").option("k", 64).load()``."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from couponspark.operators.simulate import ESTIMATORS, along, sequence


class Block(InputPartition):
    def __init__(self, first: int, last: int) -> None:
        self.first, self.last = first, last


class RunsReader(DataSourceReader):
    def __init__(self, options: dict[str, str]) -> None:
        self.k, self.trials = int(options.get("k", 64)), int(options.get("trials", 100))
        self.blocks, self.seed = int(options.get("blocks", 8)), int(options.get("seed", 1))
        self.points = np.array([float(x) for x in options.get("points", str(1 << 20)).split(",")])

    def partitions(self) -> list[Block]:
        edges = np.linspace(0, self.trials, self.blocks + 1).astype(int).tolist()
        return [Block(a, b) for a, b in zip(edges[:-1], edges[1:], strict=True) if b > a]

    def read(self, block: Block) -> Iterator[tuple]:
        for t in range(block.first, block.last):
            est = along(self.k, sequence(self.k, np.random.default_rng([self.seed, self.k, t])), self.points)
            for i, n in enumerate(self.points.tolist()):
                for name in ESTIMATORS:
                    yield self.k, t, n, name, float(est[name][i])


class CouponRuns(DataSource):
    @classmethod
    def name(cls) -> str:
        return "coupon_runs"

    def schema(self) -> str:
        return "k int, trial int, n double, estimator string, estimate double"

    def reader(self, schema) -> RunsReader:
        return RunsReader(dict(self.options))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(CouponRuns)
