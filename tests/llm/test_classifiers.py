"""Growing of trees and fitting of the n-gram classifier against plain, slow versions."""

import math
import random
import zlib
from collections import Counter

import numpy as np

from adapterlab.llm import quality, toxicity


def plain_stump(x, y, params):
    """The best split of one level by trying every cut of every column on the rows themselves."""
    p = (y.sum() + 1) / (len(y) - y.sum() + 1)
    p = p / (1 + p)
    g, h = p - y, np.full(len(y), p * (1 - p))
    best = None
    for j in range(x.shape[1]):
        for cut in np.unique(np.quantile(x[:, j], np.linspace(0, 1, params.bins + 1)[1:-1])):
            left = x[:, j] <= cut
            if min(h[left].sum(), h[~left].sum()) < params.min_hessian:
                continue
            gain = sum(g[s].sum() ** 2 / (h[s].sum() + params.l2) for s in (left, ~left)) - g.sum() ** 2 / (h.sum() + params.l2)
            if best is None or gain > best[0] + 1e-12:
                best = (gain, j, cut, *(-params.rate * g[s].sum() / (h[s].sum() + params.l2) for s in (left, ~left)))
    return best


def test_first_split_is_the_best_of_all():
    for seed in range(5):
        r = np.random.default_rng(seed)
        x = r.normal(size=(300, 5)).round(2)
        y = (x[:, seed % 5] + 0.5 * r.normal(size=300) > 0.3).astype(int)
        params = quality.QualityParams(trees=1, depth=1, bins=16)
        f = quality.grow_forest(x, y, params)
        _, j, cut, left, right = plain_stump(x, y, params)
        assert (f.feature[0], f.cut[0]) == (j, cut)
        assert np.allclose([f.value[f.left[0]], f.value[f.right[0]]], [left, right])


def test_each_level_lowers_the_loss():
    r = np.random.default_rng(7)
    x = r.normal(size=(600, 4))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0.2)).astype(int)
    loss = lambda f: np.logaddexp(0, -(2 * y - 1) * f.raw(x)).mean()
    losses = [loss(quality.grow_forest(x, y, quality.QualityParams(trees=t, depth=2))) for t in (1, 5, 20, 60)]
    assert losses == sorted(losses, reverse=True) and losses[-1] < 0.2


def plain_grams(text, params):
    raw = "".join(chr(b + 32) if 65 <= b < 91 else chr(b) for b in text.encode())
    return {raw[i : i + n] for n in params.orders for i in range(len(raw) - n + 1)}


def test_log_count_ratios_equal_plain_counts(spark):
    r = random.Random(4)
    word = lambda: "".join(r.choice("abcdefghij") for _ in range(5))
    bad, good = [word() for _ in range(8)], [word() for _ in range(8)]
    rows = [(i, " ".join(r.choice(bad if i % 2 else good) if r.random() < 0.4 else word() for _ in range(12)), i % 2) for i in range(400)]
    docs = spark.createDataFrame([x[:2] for x in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(x[0], x[2]) for x in rows], "doc_id long, toxic int")
    params = toxicity.ToxicityParams(bits=22)
    model = toxicity.fit_toxicity(docs, labels, params)
    train = [x for x in rows if zlib.crc32(str(x[0]).encode()) % 5]
    counts = [Counter(), Counter()]
    single = {n: toxicity.Grams(toxicity.ToxicityParams(orders=(n,), bits=22)) for n in params.orders}
    for _, t, y in train:
        counts[y].update(plain_grams(t, params))
    assert len(toxicity.Grams(params)(rows[0][1])) == len(plain_grams(rows[0][1], params))
    n = [sum(1 for x in train if x[2] == y) for y in (0, 1)]
    kept = set()
    for gram in set(counts[0]) | set(counts[1]):
        a, b = counts[1][gram], counts[0][gram]
        share = (a + b + 1) / (sum(n) + 2)
        if abs((a / n[1] - b / n[0]) / math.sqrt(share * (1 - share) * (1 / n[0] + 1 / n[1]))) >= params.min_z:
            kept.add(int(single[len(gram)](gram)[0]))
    assert set(model.buckets.tolist()) == kept and len(kept) > 20


def test_sparse_fit_finds_the_optimum_of_the_dense_one():
    r = np.random.default_rng(3)
    x = (r.random((300, 30)) < 0.2).astype(float)
    y = (x @ r.normal(size=30) + 0.3 * r.normal(size=300) > 0).astype(float)
    scale = r.normal(size=30)
    rows, cols = np.nonzero(x)
    w, b = toxicity._logistic(rows, cols, scale, y, 1e-2, 4000)
    dense, v, c = x * scale, np.zeros(30), 0.0
    for _ in range(200):  # Newton steps
        p = 1 / (1 + np.exp(-(dense @ v + c)))
        full = np.hstack([dense, np.ones((300, 1))])
        ridge = np.diag([1e-2] * 30 + [0.0])
        grad = full.T @ (p - y) / 300 + ridge @ np.append(v, c)
        step = np.linalg.solve(full.T @ (full * (p * (1 - p))[:, None]) / 300 + ridge, grad)
        v, c = v - step[:30], c - step[30]
    assert np.allclose(w, v, atol=1e-3) and abs(b - c) < 1e-3
