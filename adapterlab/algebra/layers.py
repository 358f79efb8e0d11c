"""The adapter layer Y = XW + alpha (drop(X) A) B and its gradients, in all evaluation orders.

Every pass maps Arrow batches to numpy blocks; a batch may mix adapters, whose rows are then sliced out tile by
tile. Gradients of A and B are summed inside each task and then over tasks, one small matrix per adapter.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from adapterlab.algebra.bank import AdapterWeights, scaled_mask
from adapterlab.session import checkpointed

Bank = dict[str, AdapterWeights]
ARRAY_SQL = {"i8": "array<bigint>", "f8": "array<double>"}


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


def _lists(m: np.ndarray) -> pa.Array:
    m = np.ascontiguousarray(m)
    offsets = np.arange(0, m.size + 1, m.shape[1], dtype=np.int32) if m.size else np.zeros(len(m) + 1, np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(m.ravel()))


def _ragged(parts: list[tuple[np.ndarray, np.ndarray]], n: int, kind) -> pa.Array:
    """Rows of different widths: (positions, block) for each adapter."""
    rows: list = [None] * n
    for at, block in parts:
        for i, r in zip(at.tolist(), block.tolist()):
            rows[i] = r
    return pa.array(rows, pa.list_(kind))


def map_blocks(df: DataFrame, make: Callable[[pa.RecordBatch], dict[str, pa.Array]], added: dict[str, str], keep: list[str]) -> DataFrame:
    """Adds array columns made from each batch; only `keep` of the old columns are read and go on."""
    schema = T.StructType([f for f in df.select(*keep).schema.fields] + T.StructType.fromDDL(", ".join(f"{k} {v}" for k, v in added.items())).fields)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            new = make(b)
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keep), *(new[k] for k in added)], names=[*keep, *added])

    return df.select(*keep, *[c for c in df.columns if c not in keep]).mapInArrow(run, schema)


def tiles_of(adapters: pa.Array) -> list[tuple[str, np.ndarray]]:
    """Rows of each adapter in a batch, in order of the adapter."""
    names = np.array(adapters.to_pylist(), dtype=object)
    return [(a, np.flatnonzero(names == a)) for a in sorted(set(names.tolist()))]


def frozen_forward(x: DataFrame, w: np.ndarray) -> DataFrame:
    return map_blocks(x, lambda b: {"y": _lists(_matrix(b.column("x")) @ w)}, {"y": ARRAY_SQL["i8"]}, ["row_id", "adapter_id"])


def frozen_backward(dy: DataFrame, w: np.ndarray) -> DataFrame:
    return map_blocks(dy, lambda b: {"dx": _lists(_matrix(b.column("dy")) @ w.T)}, {"dx": ARRAY_SQL["i8"]}, ["row_id", "adapter_id"])


def _by_adapter(b: pa.RecordBatch, bank: Bank, make: Callable[[np.ndarray, AdapterWeights], np.ndarray], kind=None) -> pa.Array:
    parts = [(at, make(at, bank[a])) for a, at in tiles_of(b.column("adapter_id"))]
    return _ragged(parts, b.num_rows, kind or pa.int64())


def _rows(b: pa.RecordBatch) -> np.ndarray:
    return b.column("row_id").to_numpy()


def step_drop(df: DataFrame, bank: Bank) -> DataFrame:
    def make(b):
        x, rows = _matrix(b.column("x")), _rows(b)
        return {"xhat": _by_adapter(b, bank, lambda at, w: x[at] * scaled_mask(rows[at], x.shape[1], w))}

    return map_blocks(df, make, {"xhat": ARRAY_SQL["i8"]}, df.columns)


def step_down(df: DataFrame, bank: Bank) -> DataFrame:
    def make(b):
        x = _matrix(b.column("xhat"))
        return {"s": _by_adapter(b, bank, lambda at, w: x[at] @ w.down)}

    return map_blocks(df, make, {"s": ARRAY_SQL["i8"]}, df.columns)


def step_base(df: DataFrame, w: np.ndarray) -> DataFrame:
    return map_blocks(df, lambda b: {"y1": _lists(_matrix(b.column("x")) @ w)}, {"y1": ARRAY_SQL["i8"]}, df.columns)


def step_up(df: DataFrame, bank: Bank) -> DataFrame:
    def make(b):
        s = b.column("s")
        return {"y2": _by_adapter(b, bank, lambda at, w: _matrix(s.take(pa.array(at))) @ w.up)}

    return map_blocks(df, make, {"y2": ARRAY_SQL["i8"]}, df.columns)


def alpha_of(bank: Bank) -> Column:
    pairs = [x for a, w in sorted(bank.items()) for x in (F.lit(a), F.lit(int(w.alpha)))]
    return F.element_at(F.create_map(*pairs), F.col("adapter_id")).cast("bigint")


def naive_forward(x: DataFrame, w: np.ndarray, bank: Bank) -> DataFrame:
    """Each operator by itself, each result written before the next reads it; that is the point of this baseline."""
    at = checkpointed(step_drop(x, bank))
    at = checkpointed(step_down(at, bank))
    at = checkpointed(step_base(at, w))
    at = checkpointed(step_up(at, bank))
    at = checkpointed(at.withColumn("y2", F.transform("y2", lambda v: v * alpha_of(bank))))
    return at.select("row_id", "adapter_id", F.zip_with("y1", "y2", lambda a, b: a + b).alias("y"))


def compiled_forward(x: DataFrame, w: np.ndarray, bank: Bank) -> DataFrame:
    """Only chains of element-wise operators are fused (scale and add in one expression); products stay apart."""
    at = step_up(step_base(step_down(step_drop(x, bank), bank), w), bank)
    return at.select("row_id", "adapter_id", F.zip_with("y1", "y2", lambda a, b: a + b * alpha_of(bank)).alias("y"))


def pass_drop_down(x: DataFrame, bank: Bank) -> DataFrame:
    """First fused pass: dropout and down projection in one read of X. Only the narrow S is kept; masks are made again."""

    def make(b):
        m, rows = _matrix(b.column("x")), _rows(b)
        return {"s": _by_adapter(b, bank, lambda at, w: (m[at] * scaled_mask(rows[at], m.shape[1], w)) @ w.down)}

    return map_blocks(x, make, {"s": ARRAY_SQL["i8"]}, x.columns)


def pass_base_up(xs: DataFrame, w: np.ndarray, bank: Bank) -> DataFrame:
    """Second fused pass: the frozen product and alpha S B added into the same output."""

    def make(b):
        y, s = _matrix(b.column("x")) @ w, b.column("s")
        for a, at in tiles_of(b.column("adapter_id")):
            y[at] += int(bank[a].alpha) * (_matrix(s.take(pa.array(at))) @ bank[a].up)
        return {"y": _lists(y)}

    return map_blocks(xs, make, {"y": ARRAY_SQL["i8"]}, ["row_id", "adapter_id"])


def split_forward(x: DataFrame, w: np.ndarray, bank: Bank) -> DataFrame:
    """Cut at S only; both sides fused."""
    return pass_base_up(pass_drop_down(x, bank), w, bank)


def routed_forward(x: DataFrame, w: np.ndarray, bank: Bank) -> DataFrame:
    """Mixed batches: rows sorted by adapter inside each task, so that tiles are runs; the frozen pass is shared."""
    return split_forward(x.sortWithinPartitions("adapter_id", "row_id"), w, bank)


def looped_forward(x: DataFrame, w: np.ndarray, bank: Bank) -> DataFrame:
    """A launch for each adapter; the frozen pass is repeated."""
    out = None
    for a in sorted(bank):
        part = split_forward(x.where(F.col("adapter_id") == a), w, {a: bank[a]})
        out = part if out is None else out.unionByName(part)
    return out


def auto_forward(x: DataFrame, w: np.ndarray, bank: Bank, adapters: list[str]) -> tuple[str, DataFrame]:
    """Single where the batch holds one adapter (known from its tiles), else routed."""
    if len(adapters) == 1:
        return "single", split_forward(x, w, {adapters[0]: bank[adapters[0]]})
    return "routed", routed_forward(x, w, bank)


def fullfuse_recompute(x: DataFrame, w: np.ndarray, bank: Bank, n_tile: int = 8) -> DataFrame:
    """No cut: S is computed again in each output tile."""
    tiles = w.shape[1] // n_tile
    spread = x.withColumn("tile", F.explode(F.sequence(F.lit(0), F.lit(tiles - 1))))

    def make(b):
        m, rows, tile = _matrix(b.column("x")), _rows(b), b.column("tile").to_numpy()
        y = np.zeros((b.num_rows, n_tile), np.int64)
        for t in np.unique(tile).tolist():
            cols = slice(t * n_tile, (t + 1) * n_tile)
            for a, at in tiles_of(b.column("adapter_id")):
                at = at[tile[at] == t]
                s = (m[at] * scaled_mask(rows[at], m.shape[1], bank[a])) @ bank[a].down
                y[at] = m[at] @ w[:, cols] + int(bank[a].alpha) * (s @ bank[a].up[:, cols])
        return {"part": _lists(y)}

    parts = map_blocks(spread, make, {"part": ARRAY_SQL["i8"]}, ["row_id", "adapter_id", "tile"])
    whole = parts.groupBy("row_id", "adapter_id").agg(F.array_sort(F.collect_list(F.struct("tile", "part"))).alias("p"))
    return whole.select("row_id", "adapter_id", F.flatten(F.transform("p", lambda q: q["part"])).alias("y"))


def fullfuse_sync(x: DataFrame, w: np.ndarray, bank: Bank, n_tile: int = 8) -> DataFrame:
    """No cut: one owner computes S for a row block, the output tiles wait for it at an exchange."""
    owner = pass_drop_down(x, bank).select(F.col("row_id").alias("s_row"), "s")
    tiles = w.shape[1] // n_tile
    waiting = x.withColumn("tile", F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)))).join(owner, F.col("row_id") == F.col("s_row"))

    def make(b):
        m, tile, s = _matrix(b.column("x")), b.column("tile").to_numpy(), b.column("s")
        y = np.zeros((b.num_rows, n_tile), np.int64)
        for t in np.unique(tile).tolist():
            cols = slice(t * n_tile, (t + 1) * n_tile)
            for a, at in tiles_of(b.column("adapter_id")):
                at = at[tile[at] == t]
                if len(at):
                    y[at] = m[at] @ w[:, cols] + int(bank[a].alpha) * (_matrix(s.take(pa.array(at))) @ bank[a].up[:, cols])
        return {"part": _lists(y)}

    parts = map_blocks(waiting, make, {"part": ARRAY_SQL["i8"]}, ["row_id", "adapter_id", "tile"])
    whole = parts.groupBy("row_id", "adapter_id").agg(F.array_sort(F.collect_list(F.struct("tile", "part"))).alias("p"))
    return whole.select("row_id", "adapter_id", F.flatten(F.transform("p", lambda q: q["part"])).alias("y"))


PARTIAL = "kind string, row_id bigint, adapter_id string, i int, v array<bigint>"


def _partials(totals: dict[str, np.ndarray], kind: str) -> pa.RecordBatch:
    rows = [(kind, None, a, i, r.tolist()) for a, m in sorted(totals.items()) for i, r in enumerate(m)]
    cols = list(zip(*rows)) if rows else [[]] * 5
    kinds = [pa.string(), pa.int64(), pa.string(), pa.int32(), pa.list_(pa.int64())]
    return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, kinds)], names=["kind", "row_id", "adapter_id", "i", "v"])


def pass_ds_db(dy_s: DataFrame, bank: Bank) -> DataFrame:
    """Third fused pass: dS and dB from one read of dY; rows of kind ds, and sums of a task of kind db."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict[str, np.ndarray] = {}
        for b in batches:
            dy, s = _matrix(b.column("dy")), b.column("s")
            parts = []
            for a, at in tiles_of(b.column("adapter_id")):
                w = bank[a]
                parts.append((at, int(w.alpha) * (dy[at] @ w.up.T)))
                totals[a] = totals.get(a, 0) + int(w.alpha) * (_matrix(s.take(pa.array(at))).T @ dy[at])
            n = b.num_rows
            yield pa.RecordBatch.from_arrays(
                [pa.array(["ds"] * n), b.column("row_id"), b.column("adapter_id"), pa.array([None] * n, pa.int32()), _ragged(parts, n, pa.int64())], names=["kind", "row_id", "adapter_id", "i", "v"]
            )
        yield _partials(totals, "db")

    return dy_s.select("row_id", "adapter_id", "dy", "s").mapInArrow(run, PARTIAL)


def pass_da(x_ds: DataFrame, bank: Bank) -> DataFrame:
    """Fourth pass: dA from the dropped X and dS; sums of each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict[str, np.ndarray] = {}
        for b in batches:
            m, rows, ds = _matrix(b.column("x")), _rows(b), b.column("ds")
            for a, at in tiles_of(b.column("adapter_id")):
                xhat = m[at] * scaled_mask(rows[at], m.shape[1], bank[a])
                totals[a] = totals.get(a, 0) + xhat.T @ _matrix(ds.take(pa.array(at)))
        yield _partials(totals, "da")

    return x_ds.select("row_id", "adapter_id", "x", "ds").mapInArrow(run, PARTIAL)


def pass_dx(dy_ds: DataFrame, w: np.ndarray, bank: Bank) -> DataFrame:
    """Fifth fused pass: both paths of dX in one output; the mask is made again."""

    def make(b):
        dx, rows, ds = _matrix(b.column("dy")) @ w.T, _rows(b), b.column("ds")
        for a, at in tiles_of(b.column("adapter_id")):
            dx[at] += scaled_mask(rows[at], dx.shape[1], bank[a]) * (_matrix(ds.take(pa.array(at))) @ bank[a].down.T)
        return {"dx": _lists(dx)}

    return map_blocks(dy_ds, make, {"dx": ARRAY_SQL["i8"]}, ["row_id", "adapter_id"])


def sum_partials(parts: DataFrame, kind: str) -> DataFrame:
    """(adapter_id, i, j, g): sums over tasks."""
    cells = parts.where(F.col("kind") == kind).select("adapter_id", "i", F.posexplode("v").alias("j", "v"))
    return cells.groupBy("adapter_id", "i", "j").agg(F.sum("v").alias("g"))


def routed_backward(x_dy: DataFrame, w: np.ndarray, bank: Bank) -> dict[str, DataFrame]:
    """Gradients da, db (adapter_id, i, j, g) and dx (row_id, adapter_id, dx), each adapter's apart from the others'."""
    with_s = pass_drop_down(x_dy.sortWithinPartitions("adapter_id", "row_id"), bank)
    third = checkpointed(pass_ds_db(with_s, bank))
    ds = third.where("kind = 'ds'").select(F.col("row_id").alias("d_row"), F.col("v").alias("ds"))
    both = x_dy.join(ds, F.col("row_id") == F.col("d_row"))
    return {"db": sum_partials(third, "db"), "da": sum_partials(pass_da(both, bank), "da"), "dx": pass_dx(both, w, bank)}


def split_backward(x_dy: DataFrame, w: np.ndarray, adapter: str, weights: AdapterWeights) -> dict[str, DataFrame]:
    """One adapter in the batch."""
    return routed_backward(x_dy, w, {adapter: weights})


def naive_backward(x_dy: DataFrame, w: np.ndarray, bank: Bank) -> dict[str, DataFrame]:
    """Each operator by itself: dY is scaled and read again for dS and dB, the parts of dX are written and added."""
    at = checkpointed(step_down(step_drop(x_dy, bank), bank))
    at = checkpointed(at.withColumn("sdy", F.transform("dy", lambda v: v * alpha_of(bank))))

    def ds(b):
        dy = _matrix(b.column("sdy"))
        return {"ds": _by_adapter(b, bank, lambda i, a: dy[i] @ a.up.T)}

    at = checkpointed(map_blocks(at, ds, {"ds": ARRAY_SQL["i8"]}, at.columns))

    def outer(left: str, right: str, kind: str):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            totals: dict[str, np.ndarray] = {}
            for b in batches:
                for a, i in tiles_of(b.column("adapter_id")):
                    take = pa.array(i)
                    totals[a] = totals.get(a, 0) + _matrix(b.column(left).take(take)).T @ _matrix(b.column(right).take(take))
            yield _partials(totals, kind)

        return at.mapInArrow(run, PARTIAL)

    def low(b):
        d = b.column("ds")
        return {"dlow": _by_adapter(b, bank, lambda i, a: _matrix(d.take(pa.array(i))) @ a.down.T)}

    def mask(b):
        d, rows = _matrix(b.column("dlow")), _rows(b)
        return {"dmasked": _by_adapter(b, bank, lambda i, a: d[i] * scaled_mask(rows[i], d.shape[1], a))}

    dx = checkpointed(map_blocks(at, low, {"dlow": ARRAY_SQL["i8"]}, at.columns))
    dx = checkpointed(map_blocks(dx, mask, {"dmasked": ARRAY_SQL["i8"]}, dx.columns))
    dx = checkpointed(map_blocks(dx, lambda b: {"dbase": _lists(_matrix(b.column("dy")) @ w.T)}, {"dbase": ARRAY_SQL["i8"]}, dx.columns))
    dx = dx.select("row_id", "adapter_id", F.zip_with("dbase", "dmasked", lambda a, b: a + b).alias("dx"))
    return {"db": sum_partials(outer("s", "sdy", "db"), "db"), "da": sum_partials(outer("xhat", "ds", "da"), "da"), "dx": dx}


def cells(df: DataFrame, column: str) -> DataFrame:
    """(row_id, j, v), for comparison."""
    return df.select("row_id", F.posexplode(column).alias("j", "v"))


def agreement(a: DataFrame, b: DataFrame, column: str = "y") -> DataFrame:
    """(cells, unequal, largest): how far two results of one layer are apart."""
    left, right = cells(a, column), cells(b, column).withColumnsRenamed({"v": "u"})
    both = left.join(right, ["row_id", "j"], "full")
    gap = F.abs(F.col("v") - F.col("u"))
    return both.agg(F.count(F.lit(1)).alias("cells"), F.count_if(~F.col("v").eqNullSafe(F.col("u"))).alias("unequal"), F.coalesce(F.max(gap), F.lit(0)).alias("largest"))
