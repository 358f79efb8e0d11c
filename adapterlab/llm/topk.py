"""Exact top-k inner-product search with a pivot-distance index.

Vectors become integers, and inner products become distances: with M the largest norm, the vector
(x, sqrt(M^2 - |x|^2)) is the nearer to (q, 0) the larger q.x is. Each vector is keyed by its nearest pivot and its
distance from it, and sorted annuli of bounded size are the blocks of the index. Queries are sorted the same way, so
that a block of them looks at one region. It first visits the zone of annuli nearest to it; the scores found there
tighten its bounds, and only what the triangle inequality then leaves open is visited, zone by zone, nearest annulus
first, while the bounds go on to tighten. Scores are integers, so the result is exact.

Pruning needs vectors that cluster: where all distances are nearly equal, every annulus stays open (`search_work`).
"""

from __future__ import annotations

from collections.abc import Iterator
from decimal import Decimal

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from adapterlab.llm.common import checkpointed

SCALE, K, EVERY = 256, 5, 50
PIVOTS, SAMPLE = 32, 4096  # the pivots are fitted on at most SAMPLE vectors
ROWS, ZONE = 512, 16  # vectors of an annulus, annuli of a zone
QUERIES, SHARE = 256, 64  # queries of a block, query blocks that meet a zone in one task
NONE = -(1 << 62)  # no score yet
LIMIT = 1 << 27  # vectors with components beyond this are scored through wide integers, beside the index


def integer_vectors(embeddings: DataFrame, scale: int = SCALE) -> DataFrame:
    """(vec_id, v): floor(scale * x) of each component, of vectors within LIMIT; null and non-finite ones are left out."""
    x = F.col("embedding")
    fine = F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c.cast("double")) < float(LIMIT / scale)))
    rows = embeddings.where(F.col("vec_id").isNotNull() & x.isNotNull() & F.coalesce(fine, F.lit(False)))
    return rows.select(F.col("vec_id").cast("long").alias("vec_id"), F.transform(x, lambda c: F.floor(c.cast("double") * scale)).alias("v"))


def wide_vectors(embeddings: DataFrame, scale: int = SCALE) -> DataFrame:
    """(vec_id, w, large): the same of every finite vector, as doubles, and whether it is beyond LIMIT."""
    x = F.col("embedding")
    finite = F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c.cast("double")) < float("inf")))
    rows = embeddings.where(F.col("vec_id").isNotNull() & x.isNotNull() & F.coalesce(finite, F.lit(False)))
    y = F.transform(x, lambda c: c.cast("double") * scale)
    whole = F.transform(y, lambda c: F.when(F.abs(c) < float(1 << 53), F.floor(F.when(F.abs(c) < float(1 << 53), c)).cast("double")).otherwise(c))
    return rows.select(F.col("vec_id").cast("long").alias("vec_id"), whole.alias("w"), F.exists(y, lambda c: F.abs(c) >= float(LIMIT)).alias("large"))


def _wide_scores(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Exact products through Python's integers; what no long holds stays beyond the longs."""
    top = 10**38 - 1
    for batch in batches:
        q, x = batch.column("q"), batch.column("x")
        s = [sum(int(a) * int(b) for a, b in zip(q[i].as_py(), x[i].as_py())) for i in range(batch.num_rows)]
        scores = pa.array([Decimal(max(-top, min(top, v))) for v in s], pa.decimal128(38, 0))
        yield pa.RecordBatch.from_arrays([batch.column("query_id"), batch.column("vec_id"), scores], names=["query_id", "vec_id", "score"])


def _matrix(column, dim: int) -> np.ndarray:
    out = np.zeros((len(column), dim), np.int64)
    lengths = np.array([len(v) for v in column], np.int64)
    if len(column) and (lengths == dim).all():
        return np.stack(list(column)).astype(np.int64)
    for i, v in enumerate(column):
        out[i, : len(v)] = v
    return out


def _lifted(x: np.ndarray, m2: float) -> np.ndarray:
    f = x.astype(np.float64)
    return np.concatenate([f, np.sqrt(np.maximum(0.0, m2 - (f * f).sum(axis=1)))[:, None]], axis=1)


def _distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(0.0, (a * a).sum(axis=1)[:, None] + (b * b).sum(axis=1)[None, :] - 2 * a @ b.T))


def _scores(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Exact integer products; through floats where they are exact."""
    if x.shape[1] * max(1, np.abs(q).max(initial=0)) * max(1, np.abs(x).max(initial=0)) < 1 << 53:
        return np.rint(q.astype(np.float64) @ x.astype(np.float64).T).astype(np.int64)
    return q @ x.T


def fit_pivots(sample: np.ndarray, pivots: int = PIVOTS, rounds: int = 5) -> np.ndarray:
    """Farthest-first start, then a few rounds of means."""
    chosen = [0]
    near = _distances(sample, sample[:1])[:, 0]
    while len(chosen) < min(pivots, len(sample)) and near.max() > 0:
        chosen.append(int(near.argmax()))
        near = np.minimum(near, _distances(sample, sample[chosen[-1:]])[:, 0])
    p = sample[chosen].copy()
    for _ in range(rounds):
        at = _distances(sample, p).argmin(axis=1)
        for k in range(len(p)):
            if (at == k).any():
                p[k] = sample[at == k].mean(axis=0)
    return p


BLOCKS = "zone long, block long, pivot int, lo double, hi double, n int, ids binary, vectors binary"


def _blocks(dim: int, m2: float):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        made, part = 0, TaskContext.get().partitionId()
        for batch in batches:
            batch = batch.sort_values(["pivot", "distance", "vec_id"], kind="stable")
            for pivot, rows in batch.groupby("pivot", sort=True):
                for i in range(0, len(rows), ROWS):
                    r = rows.iloc[i : i + ROWS]
                    x = _matrix(r["v"], dim).astype("<i4")
                    yield pd.DataFrame({"zone": [(part << 32) + made // ZONE], "block": [(part << 32) + made], "pivot": [pivot], "lo": [r["distance"].min()], "hi": [r["distance"].max()], "n": [len(r)], "ids": [r["vec_id"].to_numpy("<i8").tobytes()], "vectors": [x.tobytes()]})
                    made += 1

    return run


FOUND = "q_block long, query_id long, vec_id long, score long, annuli long, pairs long"


def _visit(k: int, dim: int, m2: float, pivots: np.ndarray):
    """Query blocks against the annuli of one zone, nearest first; emits what can still be among the k best.

    A last row without ids tells how many annuli were scored, and how many pairs.
    """

    def run(queries: pa.Table, annuli: pa.Table) -> pa.Table:
        out: list[tuple[np.ndarray, ...]] = []
        scored = pairs = 0
        bodies = annuli.to_pylist() if queries.num_rows else []
        for row in queries.to_pylist():
            qid, q = np.frombuffer(row["ids"], "<i8"), np.frombuffer(row["vectors"], "<i4").reshape(-1, dim).astype(np.int64)
            bound = np.frombuffer(row["bounds"], "<i8").copy()  # the k-th best score known so far
            lifted = np.concatenate([q.astype(np.float64), np.zeros((len(q), 1))], axis=1)
            d = _distances(lifted, pivots)
            norm = (lifted * lifted).sum(axis=1)
            gap = [np.maximum(0.0, np.maximum(d[:, b["pivot"]] - b["hi"], b["lo"] - d[:, b["pivot"]])) for b in bodies]
            best_s = np.full((len(q), k), NONE)
            for at in sorted(range(len(bodies)), key=lambda i: float(gap[i].mean())):
                b = bodies[at]
                radius2 = np.where(bound == NONE, np.inf, norm + m2 - 2.0 * bound)
                open_ = np.flatnonzero(gap[at] ** 2 <= radius2 + 1e-6 * (norm + m2) + 1e-6)
                if not len(open_):
                    continue
                ids, x = np.frombuffer(b["ids"], "<i8"), np.frombuffer(b["vectors"], "<i4").reshape(-1, dim).astype(np.int64)
                scored, pairs = scored + 1, pairs + len(open_) * len(ids)
                s = _scores(q[open_], x)
                i, j = np.nonzero((s >= bound[open_][:, None]) & (ids[None, :] != qid[open_][:, None]))
                if not len(i):
                    continue
                order = np.lexsort((ids[j], -s[i, j], i))
                i, j = i[order], j[order]
                top = np.arange(len(i)) - np.searchsorted(i, i, side="left") < k
                i, j = i[top], j[top]
                out.append((np.full(len(i), row["q_block"]), qid[open_][i], ids[j], s[i, j]))
                rank = np.arange(len(i)) - np.searchsorted(i, i, side="left")
                now = np.full((len(open_), k), NONE)
                now[i, rank] = s[i, j]
                best_s[open_] = -np.sort(-np.concatenate([best_s[open_], now], axis=1), axis=1)[:, :k]
                bound[open_] = np.maximum(bound[open_], best_s[open_][:, -1])
        cols = [np.concatenate(c) for c in zip(*out)] if out else [np.zeros(0, np.int64)] * 4
        n = len(cols[0])
        named = [pa.array([*c.tolist(), None], pa.int64()) for c in cols] + [pa.array([None] * n + [v], pa.int64()) for v in (scored, pairs)]
        return pa.table(named, names=[x.split()[0] for x in FOUND.split(", ")])

    return run


def _tightened(k: int):
    """A query block with its bounds raised to the k-th best score of what it has found."""

    def run(blocks: pa.Table, found: pa.Table) -> pa.Table:
        if not blocks.num_rows:
            return blocks.select(["q_block", "ids", "vectors", "bounds"])
        row = blocks.to_pylist()[0]
        ids, bound = np.frombuffer(row["ids"], "<i8"), np.frombuffer(row["bounds"], "<i8").copy()
        query, score = found.column("query_id").to_numpy(), found.column("score").to_numpy()
        order = np.lexsort((-score, query))
        query, score = query[order], score[order]
        kth = np.flatnonzero(np.arange(len(query)) - np.searchsorted(query, query, side="left") == k - 1)
        sorted_ids = np.argsort(ids)
        at = sorted_ids[np.searchsorted(ids[sorted_ids], query[kth])]
        bound[at] = np.maximum(bound[at], score[kth])
        return pa.table({"q_block": [row["q_block"]], "ids": pa.array([row["ids"]], pa.binary()), "vectors": pa.array([row["vectors"]], pa.binary()), "bounds": pa.array([bound.astype("<i8").tobytes()], pa.binary())})

    return run


def top_k(embeddings: DataFrame, k: int = K, every: int = EVERY, scale: int = SCALE, pivots: int = PIVOTS) -> DataFrame:
    """(query_id, rank, vec_id, score): the k highest integer inner products of each query, ties to the smaller vec_id.

    Queries are the vectors whose id is divisible by `every`, candidates all vectors with another id. Shorter vectors
    count as padded with zeros. Each row is a candidate, so rows that share an id may each be found; as queries they count
    once, by the smallest vector. Finite components of 2^19 and more are scored exactly too, beside the index; a score among
    the best that no long holds is an error. A table with fewer candidates gives them all; an empty one gives no row. Other
    columns are not read.
    """
    wide = wide_vectors(embeddings, scale)
    large = checkpointed(wide.where("large").select("vec_id").distinct())
    raw = integer_vectors(embeddings, scale)
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    if large.isEmpty():
        return _indexed(raw, k, every, pivots)
    # Pairs with a large vector are scored each; the index holds the others.
    small = _indexed(raw.join(large, "vec_id", "left_anti"), k, every, pivots).select("query_id", "vec_id", F.col("score").cast("decimal(38,0)").alias("score"))
    marked = wide.drop("large").join(large.select("vec_id", F.lit(True).alias("large")), "vec_id", "left").withColumn("large", F.coalesce("large", F.lit(False)))
    firsts = marked.where(F.col("vec_id") % every == 0).groupBy("vec_id", "large").agg(F.min("w").alias("q"))
    q = firsts.select(F.col("vec_id").alias("query_id"), "q", F.col("large").alias("q_large"))
    x = marked.select("vec_id", F.col("w").alias("x"), "large")
    some = q.where("q_large").crossJoin(x).unionByName(q.where("NOT q_large").crossJoin(x.where("large"))).where("query_id <> vec_id")
    scored = some.select("query_id", "vec_id", "q", "x").mapInArrow(_wide_scores, "query_id long, vec_id long, score decimal(38,0)")
    ranked = small.unionByName(scored).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    fits = F.abs("score") < F.lit(1 << 62).cast("decimal(38,0)") * 2
    score = F.when(fits, F.when(fits, F.col("score")).cast("long")).otherwise(F.raise_error(F.lit("a score among the best does not fit a long")).cast("long"))
    return ranked.select("query_id", "rank", "vec_id", score.alias("score"))


def _indexed(raw: DataFrame, k: int, every: int, pivots: int) -> DataFrame:
    """The same for integer vectors within LIMIT."""
    searched = _searched(raw, k, every, pivots)
    if searched is None:
        return raw.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    found = searched[0].where("pairs IS NULL")
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def search_work(embeddings: DataFrame, k: int = K, every: int = EVERY, scale: int = SCALE, pivots: int = PIVOTS) -> DataFrame:
    """(annuli, annuli_scored, pairs, pairs_scored) of a search by the index, one row; annuli are counted once per query block."""
    searched = _searched(integer_vectors(embeddings, scale), k, every, pivots)
    names = "annuli long, annuli_scored long, pairs long, pairs_scored long"
    if searched is None:
        return embeddings.sparkSession.createDataFrame([(0, 0, 0, 0)], names)
    found, index, blocks = searched
    done = found.agg(F.sum("annuli").alias("annuli_scored"), F.sum("pairs").alias("pairs_scored"))
    there = index.agg(F.count(F.lit(1)).alias("a"), F.sum("n").alias("n"))
    asked = blocks.agg(F.count(F.lit(1)).alias("b"), F.sum(F.length("ids") / 8).cast("long").alias("q"))
    return there.crossJoin(asked).crossJoin(done).select((F.col("a") * F.col("b")).alias("annuli"), "annuli_scored", (F.col("n") * F.col("q")).alias("pairs"), "pairs_scored")


def _searched(raw: DataFrame, k: int, every: int, pivots: int) -> tuple[DataFrame, DataFrame, DataFrame] | None:
    """FOUND, the index and the query blocks; None for an empty table."""
    spark = raw.sparkSession
    norm = F.aggregate("v", F.lit(0).cast("double"), lambda a, c: a + c.cast("double") * c.cast("double"))
    facts = raw.agg(F.max(F.size("v")).alias("dim"), F.max(norm).alias("m2"), F.count(F.lit(1)).alias("n")).first()
    if not facts["n"]:
        return None
    dim, m2 = max(1, facts["dim"]), float(facts["m2"])
    sample = raw.orderBy(F.xxhash64("vec_id"), "vec_id", "v").limit(SAMPLE).toPandas()
    s_ids, s_vecs = sample["vec_id"].to_numpy(np.int64), _matrix(sample["v"], dim)
    points = fit_pivots(_lifted(s_vecs, m2), pivots)

    def keyed(vectors: DataFrame, lift: float) -> DataFrame:
        @F.pandas_udf("pivot int, distance double")
        def key(v: pd.Series) -> pd.DataFrame:
            x = _matrix(v, dim)
            d = _distances(_lifted(x, m2) if lift else np.concatenate([x.astype(np.float64), np.zeros((len(x), 1))], axis=1), points)
            at = d.argmin(axis=1)
            return pd.DataFrame({"pivot": at.astype(np.int32), "distance": d[np.arange(len(d)), at]})

        found = vectors.withColumn("key", key("v")).select("vec_id", "v", "key.pivot", "key.distance")
        return found.repartitionByRange("pivot", "distance", "vec_id").sortWithinPartitions("pivot", "distance", "vec_id")

    index = checkpointed(keyed(raw, True).mapInPandas(_blocks(dim, m2), BLOCKS))

    def query_blocks(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        made, part = 0, TaskContext.get().partitionId()
        for batch in batches:
            for _, near in batch.groupby("pivot", sort=True):
                for i in range(0, len(near), QUERIES):
                    rows = near.iloc[i : i + QUERIES]
                    ids, q = rows["vec_id"].to_numpy(np.int64), _matrix(rows["v"], dim)
                    s = _scores(q, s_vecs)
                    s[ids[:, None] == s_ids[None, :]] = NONE
                    # The k-th best in the sample: no annulus needs to be visited for less.
                    bounds = -np.sort(-s, axis=1)[:, k - 1] if s.shape[1] >= k else np.full(len(ids), NONE)
                    yield pd.DataFrame({"q_block": [(part << 32) + made], "ids": [ids.astype("<i8").tobytes()], "vectors": [q.astype("<i4").tobytes()], "bounds": [bounds.astype("<i8").tobytes()]})
                    made += 1

    def with_reach(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        """What each block can still gain from, by pivot: distances that some query leaves open, and their mean."""
        for batch in batches:
            for row in batch.itertuples():
                q, bounds = np.frombuffer(row.vectors, "<i4").reshape(-1, dim).astype(np.float64), np.frombuffer(row.bounds, "<i8")
                d = _distances(np.concatenate([q, np.zeros((len(q), 1))], axis=1), points)
                norm2 = (q * q).sum(axis=1)
                r = np.where(bounds == NONE, np.inf, np.sqrt(np.maximum(0.0, norm2 + m2 - 2.0 * bounds) + 1e-6 * (norm2 + m2) + 1e-6))
                low, high, mean = (d - r[:, None]).min(axis=0), (d + r[:, None]).max(axis=0), d.mean(axis=0)
                yield pd.DataFrame({"q_block": row.q_block, "r_pivot": np.arange(len(points), dtype=np.int32), "low": low, "high": high, "at": mean})

    every_query = raw.where(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.min("v").alias("v"))
    queries = "q_block long, ids binary, vectors binary, bounds binary"
    blocks = checkpointed(keyed(every_query, False).mapInPandas(query_blocks, queries))
    shares = max(1, -(-blocks.count() // SHARE))  # a zone meets at most about SHARE query blocks in one task
    share = F.pmod(F.hash("q_block"), F.lit(shares)).alias("share")
    directory = index.select("zone", F.col("pivot").alias("b_pivot"), "lo", "hi")

    def opened(some: DataFrame) -> DataFrame:
        """(q_block, zone, gap): the zones with an annulus that the bounds leave open, and the mean distance to the nearest of them."""
        reach = some.mapInPandas(with_reach, "q_block long, r_pivot int, low double, high double, at double")
        met = reach.join(directory, (F.col("r_pivot") == F.col("b_pivot")) & (F.col("lo") <= F.col("high")) & (F.col("hi") >= F.col("low")))
        gap = F.greatest(F.lit(0.0), F.col("at") - F.col("hi"), F.col("lo") - F.col("at"))
        return met.groupBy("q_block", "zone").agg(F.min(F.struct(gap.alias("gap"), F.abs(F.col("at") - F.col("lo")).alias("off"))).alias("near"))

    def visited(zones: DataFrame, some: DataFrame) -> DataFrame:
        asked = zones.select("q_block", F.col("zone").alias("a_zone"), share).join(some, "q_block")
        wanted = zones.select("zone", share).distinct()  # annuli travel only to tasks that ask for them
        copies = index.drop("n").join(wanted, "zone")
        return asked.groupBy("a_zone", "share").cogroup(copies.groupBy("zone", "share")).applyInArrow(_visit(k, dim, m2, points), FOUND)

    open_ = opened(blocks)
    nearest = checkpointed(open_.groupBy("q_block").agg(F.min_by("zone", F.struct("near", "zone")).alias("zone")))
    first = checkpointed(visited(nearest, blocks))
    scores = first.where("pairs IS NULL").select(F.col("q_block").alias("f_block"), "query_id", "score")
    tight = checkpointed(blocks.groupBy("q_block").cogroup(scores.groupBy("f_block")).applyInArrow(_tightened(k), queries))
    rest = checkpointed(opened(tight).join(nearest, ["q_block", "zone"], "left_anti").select("q_block", "zone"))
    return first.unionByName(visited(rest, tight)), index, blocks


TOPK_SQL = """
WITH base AS (
  SELECT vec_id, list_transform(embedding, lambda c: CAST(floor(256 * CAST(c AS DOUBLE)) AS BIGINT)) AS v FROM embeddings
  WHERE embedding IS NOT NULL
    AND len(list_filter(embedding, lambda c: c IS NULL OR isnan(c) OR isinf(c))) = 0
), scored AS (
  SELECT q.vec_id AS query_id, x.vec_id, CAST(list_sum(list_transform(generate_series(1, len(q.v)), lambda i: q.v[i] * x.v[i])) AS BIGINT) AS score
  FROM (SELECT vec_id, min(v) AS v FROM base WHERE vec_id % 50 = 0 GROUP BY vec_id) q JOIN base x ON q.vec_id <> x.vec_id
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM scored
)
SELECT query_id, CAST(rank AS INT) AS rank, vec_id, score FROM ranked WHERE rank <= 5
"""
