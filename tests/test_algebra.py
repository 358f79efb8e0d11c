"""Layer algebra: finite differences, implementations against each other, variants, toy training, ledger."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from adapterlab.algebra import layers as L
from adapterlab.algebra.bank import AdapterWeights, default_bank, keep_mask, scaled_mask, with_gradient, x_rows
from adapterlab.algebra.training import train_adapters
from adapterlab.algebra.variants import dequantize4, magnitude_forward, quantize4, shared_random_forward
from adapterlab.cost.ledger import kernel_speedup, layer_sweep, shapes_frame, traffic_ledger, traffic_ratio
from adapterlab.cost.measures import arithmetic_intensity, intensity, param_ratio, plan_text, state_memory
from adapterlab.sources.weights import base_matrix, down_matrix, up_matrix


def forward(x, rows, w, a):
    return x @ w + a.alpha * ((x * scaled_mask(rows, x.shape[1], a)) @ a.down @ a.up)


def rows_of(spark, sf_dir):
    df = x_rows(spark, sf_dir)
    got = df.orderBy("row_id").collect()
    return df, np.array([r.row_id for r in got]), np.array([r.x for r in got]), [r.adapter_id for r in got]


def dense(df, column):
    return np.array([r[column] for r in df.orderBy("row_id").collect()])


@pytest.mark.parametrize("make", [L.naive_forward, L.compiled_forward, L.split_forward, L.routed_forward, L.looped_forward, L.fullfuse_recompute, L.fullfuse_sync])
def test_forward_implementations_agree(spark, sf_dir, make):
    df, ids, x, names = rows_of(spark, sf_dir)
    w, bank = base_matrix(), default_bank()
    want = np.array([forward(x[i : i + 1], ids[i : i + 1], w, bank[n])[0] for i, n in enumerate(names)])
    assert (dense(make(df, w, bank), "y") == want).all()


def test_gradients_meet_finite_differences(spark):
    r = np.random.default_rng(0)
    a = AdapterWeights(r.integers(-3, 4, (6, 2)), r.integers(-3, 4, (2, 5)), 2.0, 0.5, 3)
    w, ids, x = r.integers(-3, 4, (6, 5)), np.arange(7), r.integers(-9, 10, (7, 6))
    dy = (ids[:, None] * 3 + np.arange(5) * 7) % 5 - 2
    loss = lambda x, a: (forward(x, ids, w, a) * dy).sum()
    df = spark.createDataFrame([(int(i), "a", [int(v) for v in row]) for i, row in zip(ids, x)], "row_id bigint, adapter_id string, x array<bigint>")
    got = L.routed_backward(with_gradient(df, 5), w, {"a": a})
    matrix = lambda name, shape: _cells(got[name].collect(), shape)
    da, db, dx = matrix("da", (6, 2)), matrix("db", (2, 5)), dense(got["dx"], "dx")
    h = 1e-4
    for i, j in np.ndindex(6, 2):
        e = np.zeros((6, 2))
        e[i, j] = h
        assert abs((loss(x, AdapterWeights(a.down + e, a.up, 2.0, 0.5, 3)) - loss(x, AdapterWeights(a.down - e, a.up, 2.0, 0.5, 3))) / (2 * h) - da[i, j]) < 1e-4
    for i, j in np.ndindex(2, 5):
        e = np.zeros((2, 5))
        e[i, j] = h
        assert abs((loss(x, AdapterWeights(a.down, a.up + e, 2.0, 0.5, 3)) - loss(x, AdapterWeights(a.down, a.up - e, 2.0, 0.5, 3))) / (2 * h) - db[i, j]) < 1e-4
    for i, j in np.ndindex(7, 6):
        e = np.zeros((7, 6))
        e[i, j] = h
        assert abs((loss(x + e, a) - loss(x - e, a)) / (2 * h) - dx[i, j]) < 1e-4
    naive = L.naive_backward(with_gradient(df, 5), w, {"a": a})
    assert (_cells(naive["da"].collect(), (6, 2)) == da).all() and (dense(naive["dx"], "dx") == dx).all()


def _cells(rows, shape):
    out = np.zeros(shape)
    for r in rows:
        out[r.i, r.j] = r.g
    return out


def test_gradients_do_not_leak_between_adapters(spark, sf_dir):
    df, w, bank = x_rows(spark, sf_dir), base_matrix(), default_bank()
    both = with_gradient(df)
    muted = both.withColumn("dy", F.when(F.col("adapter_id") == "a1", F.transform("dy", lambda v: v * 0)).otherwise(F.col("dy")))
    for k in ("da", "db"):
        one = {(r.adapter_id, r.i, r.j): r.g for r in L.routed_backward(both, w, bank)[k].collect()}
        two = {(r.adapter_id, r.i, r.j): r.g for r in L.routed_backward(muted, w, bank)[k].collect()}
        assert all(one[c] == two[c] for c in one if c[0] != "a1") and all(g == 0 for c, g in two.items() if c[0] == "a1")


def test_dispatch(spark, sf_dir):
    df, w, bank = x_rows(spark, sf_dir), base_matrix(), default_bank()
    kind, y = L.auto_forward(df.where("adapter_id = 'a2'"), w, bank, ["a2"])
    assert kind == "single" and L.agreement(y, L.routed_forward(df.where("adapter_id = 'a2'"), w, bank)).first().unequal == 0
    assert L.auto_forward(df, w, bank, ["a0", "a1"])[0] == "routed"


def test_mask_is_about_right():
    keep = keep_mask(np.arange(1000), 64, 2, 0.5)
    assert 0.45 < keep.mean() < 0.55 and keep_mask(np.arange(10), 64, 2, 0.0).all()


def test_variants(spark, sf_dir):
    df, ids, x, names = rows_of(spark, sf_dir)
    w, bank = base_matrix(), default_bank()
    y = dense(magnitude_forward(df, w, bank), "y")
    for i in (0, 3, 11):
        a = bank[names[i]]
        full = w + a.alpha * (a.down @ a.up)
        want = forward(x[i : i + 1], ids[i : i + 1], w, a)[0] * np.linalg.norm(w, axis=0) / np.linalg.norm(full, axis=0)
        assert np.allclose(y[i], want, rtol=1e-9)
    vectors = {f"a{k}": (np.arange(16.0) + k, np.arange(32.0) - k) for k in range(4)}
    y = dense(shared_random_forward(df, w, down_matrix(0), up_matrix(0), vectors), "y")
    d, e = vectors[names[5]]
    assert np.allclose(y[5], x[5] @ w + ((x[5] @ down_matrix(0) * d) @ up_matrix(0)) * e)
    cells = spark.createDataFrame([(i, j, int(w[i, j])) for i in range(64) for j in range(32)], "i int, j int, v bigint")
    codes = quantize4(spark, cells)
    scale = {(r.i, r.j): r.scale for r in codes.collect()}
    back = dequantize4(codes, 64, 32)
    assert all(abs(back[k] - w[k]) <= s / 14 + 1e-9 for k, s in scale.items())


def test_training_does_not_depend_on_the_order_of_jobs(spark):
    r = np.random.default_rng(1)
    bank = {n: AdapterWeights(r.normal(size=(64, 2)), r.normal(size=(2, 4)), 1.0, 0.0, 1) for n in "ab"}
    w = r.normal(size=(64, 4))
    rows = [(i, "ab"[i % 2], i // 8, [int(v) for v in r.integers(-500, 500, 64)]) for i in range(24)]
    df = spark.createDataFrame(rows, "row_id bigint, adapter_id string, batch int, x array<bigint>").cache()
    sequential = [[("a", j)] for j in range(3)] + [[("b", j)] for j in range(3)]
    together = [[("a", 0)], [("b", 0), ("a", 0)], [("a", 1)], [("b", 1)], [("b", 2), ("a", 2)]]
    one, two = train_adapters(df, sequential, w, bank), train_adapters(df, together, w, bank)
    for n in "ab":
        assert np.allclose(one[n].down, two[n].down, atol=1e-9) and np.allclose(one[n].up, two[n].up, atol=1e-9)
        assert not np.allclose(one[n].down, bank[n].down)


def test_costs_move_as_reported(spark):
    shapes = shapes_frame(spark, [(8192, 4096, 4096, 16)])
    ratio = traffic_ratio(traffic_ledger(shapes)).first()
    assert 5100 < ratio.naive_to_frozen < 5300 and 370 < ratio.split_to_naive < 400
    real = traffic_ratio(traffic_ledger(shapes, gemm_reread=7.8)).first()
    assert abs(real.naive_to_frozen - 2640) < 30 and abs(real.split_to_naive - 530) < 15
    speed = {(r.impl, r.direction): r.speed_per_mille for r in layer_sweep(traffic_ledger(shapes)).collect()}
    for d in ("forward", "backward"):
        assert speed[("frozen", d)] == 1000 > speed[("split", d)] > speed[("naive", d)]
        assert speed[("naive", d)] <= speed[("compiled", d)] < speed[("split", d)]
        assert speed[("split", d)] >= speed[("routed", d)] > speed[("naive", d)]
    gain = {(r.impl, r.direction): r.speedup_per_mille for r in kernel_speedup(traffic_ledger(shapes)).collect()}
    assert gain[("split", "forward")] > 1100
    m = state_memory(shapes, 16).first()
    assert 7500 < m.reduction_per_mille < 7600 and 7100 < state_memory(shapes, 32).first().reduction_per_mille < 7200
    p = param_ratio(shapes).first()
    assert (p.both_ppm, p.one_ppm) == (7812, 3906)
    i = intensity(shapes).first()
    assert i.down_memory_bound and i.up_memory_bound and not i.base_memory_bound
    assert abs(arithmetic_intensity(8192, 4096, 16) - 15.91) < 0.01
    assert "Exchange" in plan_text(shapes.groupBy("m").count())
