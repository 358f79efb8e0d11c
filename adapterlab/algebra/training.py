"""Toy training that applies each adapter's gradient at its batch boundary, for the proof that order does not matter."""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from adapterlab.algebra.bank import AdapterWeights, scaled_mask
from adapterlab.algebra.layers import _matrix, _rows


def batch_gradient(rows: DataFrame, w: np.ndarray, a: AdapterWeights, target: float = 1.0) -> tuple[np.ndarray, np.ndarray]:
    """Sums of dA and dB of the squared error to `target`; tasks send one pair of small matrices each."""

    def run(batches):
        da, db = np.zeros_like(a.down, dtype=np.float64), np.zeros_like(a.up, dtype=np.float64)
        for b in batches:
            if not b.num_rows:
                continue
            x = _matrix(b.column("x")).astype(np.float64) / 1024
            xhat = x * scaled_mask(_rows(b), x.shape[1], a)
            s = xhat @ a.down
            dy = x @ w + a.alpha * (s @ a.up) - target
            ds = a.alpha * (dy @ a.up.T)
            da += xhat.T @ ds
            db += a.alpha * (s.T @ dy)
        yield pa.RecordBatch.from_arrays([pa.array([da.tobytes()]), pa.array([db.tobytes()])], names=["da", "db"])

    parts = rows.mapInArrow(run, "da binary, db binary").collect()  # one row a task
    total = [np.sum([np.frombuffer(p[k]) for p in parts], axis=0) for k in ("da", "db")]
    return total[0].reshape(a.down.shape), total[1].reshape(a.up.shape)


def train_adapters(rows: DataFrame, order: list[list[tuple[str, int]]], w: np.ndarray, bank: dict[str, AdapterWeights], rate: float = 1e-4) -> dict[str, AdapterWeights]:
    """rows: (row_id, adapter_id, batch, x). order: microbatches as lists of (adapter, batch), as scheduled.

    A batch's gradient is the sum over its microbatches' rows; the step runs when its last microbatch is through.
    """
    last = {}
    for pos, keys in enumerate(order):
        for k in keys:
            last[k] = pos
    ends = defaultdict(list)
    for k, pos in last.items():
        ends[pos].append(k)
    now = dict(bank)
    for pos in range(len(order)):
        for name, batch in sorted(ends[pos]):
            a = now[name]
            da, db = batch_gradient(rows.where((rows.adapter_id == name) & (rows.batch == batch)), w, a)
            now[name] = AdapterWeights(a.down - rate * da, a.up - rate * db, a.alpha, a.dropout, a.seed)
    return now
