"""Top-k with finite components of any size that scores in a long allow."""

import numpy as np

from adapterlab.llm import topk


def test_large_components_take_part(spark):
    r = np.random.default_rng(5)
    v = r.normal(size=(120, 6)).astype(np.float32)
    v[50], v[7], v[11], v[100, 2] = 3e6 * v[50], 2e6 * v[7], 1e5 * v[11], 2.0**19
    rows = [(i, [float(c) for c in x]) for i, x in enumerate(v)]
    df = spark.createDataFrame([*rows, (150, [float("inf")] * 6), (13, None)], "vec_id long, embedding array<float>")
    got = [tuple(x) for x in topk.top_k(df).orderBy("query_id", "rank").collect()]
    w = [[int(c) for c in np.floor(256 * x.astype(np.float64))] for x in v]
    want = []
    for q in (0, 50, 100):
        order = sorted((-sum(a * b for a, b in zip(w[q], w[x])), x) for x in range(len(v)) if x != q)[:5]
        want += [(q, k + 1, x, -s) for k, (s, x) in enumerate(order)]
    assert got == want and {7, 11} & {x[2] for x in got}
