"""Variants that reuse the fused passes: magnitude-normalised, shared random matrices, 4-bit base weights."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from adapterlab.algebra.bank import AdapterWeights, scaled_mask
from adapterlab.algebra.layers import ARRAY_SQL, Bank, _lists, _matrix, _rows, map_blocks, tiles_of


def magnitude_scales(w: np.ndarray, a: AdapterWeights, magnitude: np.ndarray | None = None) -> np.ndarray:
    """Per column: the learned magnitude over the norm of W + alpha A B; the magnitude starts as the norm of W."""
    m = np.linalg.norm(w, axis=0) if magnitude is None else magnitude
    return m / np.linalg.norm(w + a.alpha * (a.down @ a.up), axis=0)


def magnitude_forward(x: DataFrame, w: np.ndarray, bank: Bank) -> DataFrame:
    """Column-normalised variant: norms are taken once, the scale is an epilogue of the second pass."""
    scales = {k: magnitude_scales(w, a) for k, a in bank.items()}

    def make(b: pa.RecordBatch):
        m, rows = _matrix(b.column("x")).astype(np.float64), _rows(b)
        y = m @ w
        for k, at in tiles_of(b.column("adapter_id")):
            a = bank[k]
            y[at] = (y[at] + a.alpha * ((m[at] * scaled_mask(rows[at], m.shape[1], a)) @ a.down @ a.up)) * scales[k]
        return {"y": _lists(y)}

    return map_blocks(x, make, {"y": ARRAY_SQL["f8"]}, ["row_id", "adapter_id"])


def shared_random_forward(x: DataFrame, w: np.ndarray, down: np.ndarray, up: np.ndarray, vectors: dict[str, tuple[np.ndarray, np.ndarray]]) -> DataFrame:
    """All adapters share frozen A and B; each trains two scaling vectors (over rank, over outputs)."""

    def make(b: pa.RecordBatch):
        m = _matrix(b.column("x")).astype(np.float64)
        y, s = m @ w, m @ down
        for k, at in tiles_of(b.column("adapter_id")):
            d, e = vectors[k]
            y[at] += ((s[at] * d) @ up) * e
        return {"y": _lists(y)}

    return map_blocks(x, make, {"y": ARRAY_SQL["f8"]}, ["row_id", "adapter_id"])


def quantize4(spark: SparkSession, w: DataFrame, block: int = 16) -> DataFrame:
    """(j, block, scale, i, code): codes from -7 to 7 by the largest absolute value of each block of a column.

    w: (i, j, v) cells of whole numbers.
    """
    b = F.floor(F.col("i") / block).cast("int")
    cells = w.select("i", "j", F.col("v").cast("bigint").alias("v"), b.alias("block"))
    scales = cells.groupBy("j", "block").agg(F.greatest(F.max(F.abs("v")), F.lit(1)).alias("scale"))
    code = F.floor((2 * 7 * F.col("v") + F.col("scale")) / (2 * F.col("scale"))).cast("int")
    return cells.join(scales, ["j", "block"]).select("j", "block", "scale", "i", code.alias("code"))


def dequantize4(codes: DataFrame, k: int, n: int) -> np.ndarray:
    """The base matrix as the passes take it; one layer's weights, read once."""
    out = np.zeros((k, n))
    for r in codes.toLocalIterator():
        out[r["i"], r["j"]] = r["code"] * r["scale"] / 7
    return out
