"""Adapters of a mixed batch: weights, ranks, scales, dropout; and activation rows taken from `embeddings`."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from adapterlab.sources.tables import load
from adapterlab.sources.weights import K, N, down_matrix, up_matrix


@dataclass(frozen=True)
class AdapterWeights:
    down: np.ndarray  # k x r
    up: np.ndarray  # r x n
    alpha: float
    dropout: float
    seed: int


def default_bank(k: int = K, n: int = N) -> dict[str, AdapterWeights]:
    """Four adapters of different rank, scale and dropout; whole numbers, so that results are exact."""
    shape = [(16, 16, 0.0), (16, 32, 0.5), (32, 16, 0.0), (8, 8, 0.5)]
    return {f"a{a}": AdapterWeights(down_matrix(a, k, r), up_matrix(a, r, n), alpha, p, a + 1) for a, (r, alpha, p) in enumerate(shape)}


def keep_mask(rows: np.ndarray, cols: int, seed: int, dropout: float) -> np.ndarray:
    """What dropout keeps; made again from row and column whenever it is needed."""
    return (rows.astype(np.int64)[:, None] * 7919 + np.arange(cols) * 104_729 + seed * 31) % 1000 >= 1000 * dropout


def dropout_mask(row: Column, col: Column, seed: Column | int, dropout: Column | float) -> Column:
    s = F.lit(seed) if isinstance(seed, int) else seed
    p = F.lit(dropout) if isinstance(dropout, float) else dropout
    return (row * 7919 + col * 104_729 + s * 31) % 1000 >= 1000 * p


def x_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(row_id, adapter_id, x): fixed-point activations floor(1024 x), the adapter by the label."""
    fixed = F.transform("embedding", lambda v: F.floor(v.cast("double") * 1024).cast("bigint"))
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), F.concat(F.lit("a"), (F.col("label") % 4).cast("string")).alias("adapter_id"), fixed.alias("x"))


def upstream_gradient(rows: np.ndarray, n: int = N) -> np.ndarray:
    """A fixed dY, made from row and column."""
    return (rows.astype(np.int64)[:, None] * 3 + np.arange(n) * 7) % 5 - 2


def with_gradient(x: DataFrame, n: int = N) -> DataFrame:
    j = F.sequence(F.lit(0), F.lit(n - 1))
    return x.withColumn("dy", F.transform(j, lambda c: ((F.col("row_id") * 3 + c * 7) % 5 - 2).cast("bigint")))


def scaled_mask(rows: np.ndarray, cols: int, w: AdapterWeights) -> np.ndarray:
    """The mask over its keep probability: whole for dropout 0 and 0.5."""
    keep = keep_mask(rows, cols, w.seed, w.dropout)
    scale = 1 / (1 - w.dropout)
    return keep * (int(scale) if scale == int(scale) else scale)
