"""DuckDB texts for the registered queries; each starts from the base tables."""

from __future__ import annotations

G, C, P, GAP = 16, 2048, 64, 3

SAMPLES = """
short AS (SELECT conv_id * 65536 + turn AS sample_id, (length(text) + 3) // 4 AS tok_len FROM conversations),
medium AS (SELECT doc_id AS sample_id, (length(text) + 3) // 4 AS tok_len FROM documents),
long AS (SELECT page_id AS sample_id, (length(html) + 3) // 4 AS tok_len FROM pages),
mixed AS (SELECT sample_id * 3 AS sample_id, tok_len FROM short UNION ALL SELECT sample_id * 3 + 1, tok_len FROM medium UNION ALL SELECT sample_id * 3 + 2, tok_len FROM long),
samples AS (
  SELECT 'a0' AS adapter_id, sample_id, 'short' AS dataset, tok_len, md5('11-short-' || sample_id::VARCHAR) AS order_key FROM short WHERE tok_len > 0
  UNION ALL SELECT 'a1', sample_id, 'medium', tok_len, md5('12-medium-' || sample_id::VARCHAR) FROM medium WHERE tok_len > 0
  UNION ALL SELECT 'a2', sample_id, 'long', tok_len, md5('13-long-' || sample_id::VARCHAR) FROM long WHERE tok_len > 0
  UNION ALL SELECT 'a3', sample_id, 'mixed', tok_len, md5('14-mixed-' || sample_id::VARCHAR) FROM mixed WHERE tok_len > 0
)"""
NUMBERED = SAMPLES + """,
numbered AS (SELECT *, row_number() OVER (PARTITION BY adapter_id ORDER BY order_key, sample_id) - 1 AS rn FROM samples)"""
GROUPS = NUMBERED + """,
stats AS (SELECT adapter_id, count(*) AS n_samples, CAST(sum(tok_len) AS BIGINT) AS tokens, round(avg(tok_len), 6) AS mean_len FROM samples GROUP BY 1),
ranked AS (SELECT *, row_number() OVER (ORDER BY mean_len, adapter_id) AS len_rank, count(*) OVER () AS n FROM stats),
groups AS (SELECT adapter_id, mean_len, len_rank, CAST(least(len_rank, n + 1 - len_rank) - 1 AS INT) AS group_id FROM ranked)"""
BATCHES = GROUPS + f""",
batches AS (
  SELECT group_id, gb, adapter_id, sample_id, CAST(least(tok_len - {C} * k, {C}) AS BIGINT) AS tok_len, rn, dense_rank() OVER (PARTITION BY group_id ORDER BY adapter_id) AS slot
  FROM (SELECT g.group_id, CAST(n.rn // {G} AS BIGINT) AS gb, n.adapter_id, n.sample_id, n.tok_len, n.rn, unnest(generate_series(0, (n.tok_len - 1) // {C})) AS k
    FROM numbered n JOIN groups g USING (adapter_id))
)"""


def pad(e: str, multiple: int = P) -> str:
    return f"((({e}) + {multiple - 1}) // {multiple} * {multiple})"


def greedy(rule: str, capacity: int = C) -> str:
    """First items in order, one at a time; the state is each bin's tokens of both adapters of the group."""
    order = "tok_len DESC, adapter_id, sample_id" if rule in ("ffd", "bfd") else "adapter_id, rn, sample_id, tok_len"
    loads = f"list_transform(r.l1, lambda x, i: {pad('x + CASE WHEN t.slot = 1 THEN t.tok_len ELSE 0 END')} + {pad('r.l2[i] + CASE WHEN t.slot = 2 THEN t.tok_len ELSE 0 END')})"
    fits = f"list_transform(loads, lambda v: CASE WHEN v <= {capacity} THEN v ELSE -1 END)"
    pick = {
        "next_fit": f"CASE WHEN len(loads) > 0 AND loads[len(loads)] <= {capacity} THEN len(loads) ELSE len(loads) + 1 END",
        "first_fit": f"coalesce(nullif(list_position(list_transform(loads, lambda v: v <= {capacity}), true), 0), len(loads) + 1)",
        "bfd": f"CASE WHEN len(loads) > 0 AND list_max({fits}) >= 0 THEN list_position({fits}, list_max({fits})) ELSE len(loads) + 1 END",
    }
    pick["ffd"] = pick["first_fit"]
    return f"""WITH RECURSIVE {BATCHES},
items AS (SELECT *, row_number() OVER (PARTITION BY group_id, gb ORDER BY {order}) AS k FROM batches),
walk(group_id, gb, k, l1, l2, b, adapter_id, sample_id, tok_len) AS (
  SELECT DISTINCT group_id, gb, CAST(0 AS BIGINT), CAST([] AS BIGINT[]), CAST([] AS BIGINT[]), CAST(0 AS BIGINT), CAST(NULL AS VARCHAR), CAST(NULL AS BIGINT), CAST(NULL AS BIGINT) FROM items
  UNION ALL
  SELECT group_id, gb, k,
    CASE WHEN b > len(l1) THEN list_append(l1, CASE WHEN slot = 1 THEN tok_len ELSE 0 END) ELSE list_transform(l1, lambda x, i: CASE WHEN i = b AND slot = 1 THEN x + tok_len ELSE x END) END,
    CASE WHEN b > len(l2) THEN list_append(l2, CASE WHEN slot = 2 THEN tok_len ELSE 0 END) ELSE list_transform(l2, lambda x, i: CASE WHEN i = b AND slot = 2 THEN x + tok_len ELSE x END) END,
    b, adapter_id, sample_id, tok_len
  FROM (
    SELECT *, CAST({pick[rule]} AS BIGINT) AS b FROM (
      SELECT t.group_id, t.gb, t.k, r.l1, r.l2, t.slot, t.adapter_id, t.sample_id, t.tok_len, {loads} AS loads
      FROM walk r JOIN items t ON t.group_id = r.group_id AND t.gb = r.gb AND t.k = r.k + 1
    )
  )
),
packed AS (SELECT group_id, gb, CAST(b - 1 AS INT) AS bin, adapter_id, sample_id, tok_len FROM walk WHERE k > 0)
"""


FX = """
x AS (SELECT vec_id AS row_id, 'a' || (label % 4)::VARCHAR AS adapter_id, CAST(label % 4 AS BIGINT) AS a,
  unnest(generate_series(0, 63)) AS i, CAST(floor(unnest(embedding)::DOUBLE * 1024) AS BIGINT) AS v FROM embeddings),
w AS (SELECT i, j, (31 * i + 17 * j + 7) % 21 - 10 AS v FROM generate_series(0, 63) t(i), generate_series(0, 31) u(j)),
bank(a, r, alpha, p) AS (VALUES (0, 16, 16, 0), (1, 16, 32, 500), (2, 32, 16, 0), (3, 8, 8, 500)),
down AS (SELECT a, i, c, (13 * i + 5 * c + 3 * a + 1) % 11 - 5 AS v FROM bank, generate_series(0, 63) t(i), generate_series(0, 31) u(c) WHERE c < r),
up AS (SELECT a, c, j, (7 * c + 3 * j + 2 * a + 4) % 9 - 4 AS v FROM bank, generate_series(0, 31) t(c), generate_series(0, 31) u(j) WHERE c < r),
keep AS (SELECT x.row_id, x.adapter_id, x.a, x.i,
  CASE WHEN (x.row_id * 7919 + x.i * 104729 + (x.a + 1) * 31) % 1000 >= b.p THEN CASE WHEN b.p = 500 THEN 2 ELSE 1 END ELSE 0 END AS m
  FROM x JOIN bank b USING (a)),
xhat AS (SELECT x.row_id, x.adapter_id, x.a, x.i, x.v * k.m AS v FROM x JOIN keep k USING (row_id, i)),
s AS (SELECT h.row_id, h.adapter_id, h.a, d.c, sum(h.v * d.v) AS v FROM xhat h JOIN down d ON d.a = h.a AND d.i = h.i GROUP BY 1, 2, 3, 4),
dy AS (SELECT DISTINCT x.row_id, x.adapter_id, x.a, j, (x.row_id * 3 + j * 7) % 5 - 2 AS v FROM x, generate_series(0, 31) u(j)),
ds AS (SELECT y.row_id, y.adapter_id, y.a, u.c, sum(b.alpha * y.v * u.v) AS v FROM dy y JOIN up u ON u.a = y.a AND u.j = y.j JOIN bank b ON b.a = y.a GROUP BY 1, 2, 3, 4)"""

FROZEN_FORWARD = f"WITH {FX} SELECT x.row_id, CAST(w.j AS INT) AS j, CAST(sum(x.v * w.v) AS BIGINT) AS v FROM x JOIN w USING (i) GROUP BY 1, 2"
FROZEN_BACKWARD = f"WITH {FX} SELECT y.row_id, CAST(w.i AS INT) AS j, CAST(sum(y.v * w.v) AS BIGINT) AS v FROM dy y JOIN w USING (j) GROUP BY 1, 2"
FORWARD = f"""WITH {FX},
base AS (SELECT x.row_id, w.j, sum(x.v * w.v) AS v FROM x JOIN w USING (i) GROUP BY 1, 2),
low AS (SELECT s.row_id, u.j, sum(b.alpha * s.v * u.v) AS v FROM s JOIN up u ON u.a = s.a AND u.c = s.c JOIN bank b ON b.a = s.a GROUP BY 1, 2)
SELECT row_id, CAST(j AS INT) AS j, CAST(base.v + low.v AS BIGINT) AS v FROM base JOIN low USING (row_id, j)"""
GRAD_A = f"""WITH {FX} SELECT h.adapter_id, CAST(h.i AS INT) AS i, CAST(ds.c AS INT) AS j, CAST(sum(h.v * ds.v) AS BIGINT) AS g
FROM xhat h JOIN ds USING (row_id) GROUP BY 1, 2, 3"""
GRAD_B = f"""WITH {FX} SELECT s.adapter_id, CAST(s.c AS INT) AS i, CAST(y.j AS INT) AS j, CAST(sum(b.alpha * s.v * y.v) AS BIGINT) AS g
FROM s JOIN dy y USING (row_id) JOIN bank b ON b.a = s.a GROUP BY 1, 2, 3"""
GRAD_X = f"""WITH {FX},
base AS (SELECT y.row_id, w.i, sum(y.v * w.v) AS v FROM dy y JOIN w USING (j) GROUP BY 1, 2),
low AS (SELECT ds.row_id, d.i, sum(ds.v * d.v) AS v FROM ds JOIN down d ON d.a = ds.a AND d.c = ds.c GROUP BY 1, 2)
SELECT base.row_id, CAST(base.i AS INT) AS j, CAST(base.v + low.v * k.m AS BIGINT) AS v FROM base JOIN low USING (row_id, i) JOIN keep k USING (row_id, i)"""
MASK = f"WITH {FX} SELECT row_id, CAST(i AS INT) AS j, m > 0 AS kept FROM keep"

SHAPES = [(8192, 4096, 4096, 16), (8192, 4096, 14336, 16), (8192, 14336, 4096, 16), (8192, 5120, 5120, 16), (8192, 8192, 8192, 16), (8192, 8192, 28672, 16)]
SHAPES_SQL = "shapes(m, k, n, r) AS (VALUES " + ", ".join(f"(CAST({m} AS BIGINT), CAST({k} AS BIGINT), CAST({n} AS BIGINT), CAST({r} AS BIGINT))" for m, k, n, r in SHAPES) + ")"
# Microbatches of 16 consecutive order keys, their padded lengths as rows of a layer, and lines of an order.
ORDER_BATCHES = "mbs AS (SELECT * FROM (SELECT l_orderkey // {n} AS mb, CAST(floor(sum(l_quantity)) AS BIGINT) AS tokens FROM lineitem WHERE l_orderkey IS NOT NULL GROUP BY 1) WHERE tokens > 0)"
LAYERS_SQL = f"{ORDER_BATCHES.format(n=16)}, shapes AS (SELECT DISTINCT {pad('tokens')} AS m, k, n, r FROM mbs, (VALUES " + ", ".join(f"({k}::BIGINT, {n}::BIGINT, {r}::BIGINT)" for _, k, n, r in SHAPES) + ") l(k, n, r))"
RUNS_SQL = "runs AS (SELECT m, count(*) AS orders FROM (SELECT count(*) AS m FROM lineitem WHERE l_orderkey IS NOT NULL GROUP BY l_orderkey) GROUP BY 1)"
# Hand-made totals of bytes, two bytes an element and one for a mask element.
TOTALS_SQL = f"""{SHAPES_SQL},
totals AS (
  SELECT 'frozen' AS impl, 'forward' AS direction, *, 2 * (m*k + k*n + m*n) AS bytes, 2*m*k*n AS flops FROM shapes
  UNION ALL SELECT 'frozen', 'backward', *, 2 * (m*n + k*n + m*k), 2*m*k*n FROM shapes
  UNION ALL SELECT 'naive', 'forward', *, 2 * (4*m*k + 7*m*n + k*n + 2*m*r + k*r + r*n) + m*k, 2*m*k*n + 2*m*k*r + 2*m*r*n FROM shapes
  UNION ALL SELECT 'naive', 'backward', *, 2 * (8*m*k + 5*m*n + k*n + 4*m*r + 2*k*r + 2*r*n) + m*k, 2*m*k*n + 4*m*k*r + 4*m*r*n FROM shapes
  UNION ALL SELECT 'split', 'forward', *, 2 * (3*m*k + m*n + k*n + 2*m*r + k*r + r*n) + m*k, 2*m*k*n + 2*m*k*r + 2*m*r*n FROM shapes
  UNION ALL SELECT 'split', 'backward', *, 2 * (2*m*k + 2*m*n + k*n + 4*m*r + 2*k*r + 2*r*n) + m*k, 2*m*k*n + 4*m*k*r + 4*m*r*n FROM shapes
)"""
