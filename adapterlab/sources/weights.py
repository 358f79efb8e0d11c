"""Weights: deterministic integer matrices, as arrays and as a Python data source of blocks."""

from __future__ import annotations

import numpy as np
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

K, N = 64, 32


def base_matrix(k: int = K, n: int = N) -> np.ndarray:
    i, j = np.indices((k, n))
    return ((31 * i + 17 * j + 7) % 21 - 10).astype(np.int64)


def down_matrix(a: int, k: int = K, r: int = 16) -> np.ndarray:
    i, c = np.indices((k, r))
    return ((13 * i + 5 * c + 3 * a + 1) % 11 - 5).astype(np.int64)


def up_matrix(a: int, r: int = 16, n: int = N) -> np.ndarray:
    c, j = np.indices((r, n))
    return ((7 * c + 3 * j + 2 * a + 4) % 9 - 4).astype(np.int64)


class BlockPartition(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class WeightReader(DataSourceReader):
    def __init__(self, options: dict):
        self.kind, self.adapter = options.get("kind", "w"), int(options.get("adapter", 0))
        self.rows, self.cols, self.step = (int(options.get(k, d)) for k, d in (("rows", K), ("cols", N), ("block", 16)))

    def partitions(self):
        return [BlockPartition(i, min(i + self.step, self.rows)) for i in range(0, self.rows, self.step)]

    def read(self, partition):
        make = {"w": lambda: base_matrix(self.rows, self.cols), "a": lambda: down_matrix(self.adapter, self.rows, self.cols), "b": lambda: up_matrix(self.adapter, self.rows, self.cols)}[self.kind]
        m = make()
        for i in range(partition.lo, partition.hi):
            for j in range(self.cols):
                yield (i, j, int(m[i, j]))


class WeightSource(DataSource):
    """spark.dataSource.register(WeightSource); spark.read.format("weight_blocks").option("kind", "w").load()"""

    @classmethod
    def name(cls) -> str:
        return "weight_blocks"

    def schema(self) -> str:
        return "i int, j int, v bigint"

    def reader(self, schema) -> WeightReader:
        return WeightReader(dict(self.options))
