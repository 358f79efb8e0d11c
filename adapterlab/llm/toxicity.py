"""Toxicity: linear classifier on character n-grams scaled by naive Bayes log-count ratios.

Byte n-grams (ASCII lower-cased, hashed) count once per document. Their log-count ratios between the classes
scale the inputs of an L2-regularised logistic regression. N-grams whose document frequency does not differ
clearly between the classes are left out, so that long clean texts gather no noise.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adapterlab.llm.common import checkpointed, held_out, texts, training_ids, with_small_batches

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


@dataclass(frozen=True)
class ToxicityParams:
    orders: tuple[int, ...] = (3, 4, 5)
    bits: int = 18
    train_per_class: int = 3000  # labelled documents of each class at most
    max_features: int = 2048
    min_z: float = 3.5
    alpha: float = 1.0
    l2: float = 1e-3
    steps: int = 400


@dataclass(frozen=True)
class ToxicityModel:
    params: ToxicityParams
    buckets: np.ndarray  # ascending
    weights: np.ndarray
    bias: float


class Grams:
    """Distinct n-gram buckets of a text; a stamp per bucket keeps it linear in the text."""

    def __init__(self, params: ToxicityParams):
        self.params = params
        self.stamp = np.zeros(1 << params.bits, np.int64)

    def __call__(self, text: str | None) -> np.ndarray:
        raw = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8)
        x = LOWER[raw].astype(np.uint64) + np.uint64(1)
        found = []
        h = x.copy()
        for n in range(2, max(self.params.orders) + 1):
            if len(x) < n:
                break
            h = h[:-1] * np.uint64(0x9E3779B97F4A7C15) + x[n - 1 :]
            if n in self.params.orders:
                mixed = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
                found.append((mixed >> np.uint64(64 - self.params.bits)).astype(np.int64))
        if not found:
            return np.zeros(0, np.int64)
        g = np.concatenate(found)
        at = np.arange(len(g))
        self.stamp[g] = at
        return g[self.stamp[g] == at]


def _counts(params: ToxicityParams):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        grams, totals = Grams(params), np.zeros((2, 1 << params.bits), np.int64)
        for batch in batches:
            for text, y in zip(batch["text"], batch["y"]):
                totals[y, grams(text)] += 1
        seen = np.flatnonzero(totals.sum(axis=0))
        yield pd.DataFrame({"bucket": seen, "neg": totals[0, seen], "pos": totals[1, seen]})

    return run


def _selected(params: ToxicityParams, buckets: np.ndarray):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        grams, column = Grams(params), np.full(1 << params.bits, -1, np.int64)
        column[buckets] = np.arange(len(buckets))
        for batch in batches:
            hits = [column[grams(t)] for t in batch["text"]]
            yield pd.DataFrame({"doc_id": batch["doc_id"], "y": batch["y"], "cols": [np.sort(h[h >= 0]).astype("<i4").tobytes() for h in hits]})

    return run


def _logistic(rows: np.ndarray, cols: np.ndarray, scale: np.ndarray, y: np.ndarray, l2: float, steps: int) -> tuple[np.ndarray, float]:
    """Accelerated gradient descent on the mean log loss; the inputs are scale[c] at each (row, c), zero elsewhere."""
    n, m = len(y), len(scale)
    product = lambda w: np.bincount(rows, (w * scale)[cols], n)
    loss = lambda w, z: float(np.logaddexp(0, -(2 * y - 1) * z).mean() + l2 / 2 * w @ w)
    w, b, z = np.zeros(m), 0.0, np.zeros(n)  # z: margins, linear in w and b, so that mixtures of steps need no product
    step = 1.0 / (0.25 * (float(np.bincount(rows, (scale * scale)[cols], n).max(initial=0.0)) + 1.0) + l2)
    step *= 8.0  # the bound is far from tight; backtracking below keeps it safe
    vw, vb, vz, last = w, b, z, loss(w, z)
    for k in range(steps):
        off = 1 / (1 + np.exp(-np.clip(vz, -30, 30))) - y
        gw, gb = np.bincount(cols, off[rows], m) * scale / n + l2 * vw, float(off.mean())
        if k and np.abs(gw).max(initial=abs(gb)) < 1e-6:
            break
        nw, nb = vw - step * gw, vb - step * gb
        nz = product(nw) + nb
        now = loss(nw, nz)
        if now > last + 1e-9:
            step, vw, vb, vz = step / 2, w, b, z
            continue
        mix = k / (k + 3)
        vw, vb, vz = nw + mix * (nw - w), nb + mix * (nb - b), nz + mix * (nz - z)
        w, b, z, last = nw, nb, nz, now
    return w, b


def fit_toxicity(documents: DataFrame, labels: DataFrame, params: ToxicityParams = ToxicityParams(), label: str = "toxic") -> ToxicityModel:
    """Learns from at most `train_per_class` labelled documents of each class, none of them held out.

    Null texts are empty, rows that repeat an id each count, null ids and null labels are left out (`training_ids`). Without
    documents of both classes the model scores their share alone; other columns are not read.
    """
    ids = training_ids(labels, label, params.train_per_class)
    train = with_small_batches(documents).select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(ids), F.col("doc_id") == F.col("train_id"))
    train = checkpointed(train.select("doc_id", "text", "y"))
    n = {r["y"]: r["count"] for r in train.groupBy("y").count().collect()}
    neg, pos = n.get(0, 0), n.get(1, 0)
    prior = float(np.log((pos + 1) / (neg + 1)))
    empty = ToxicityModel(params, np.zeros(0, np.int64), np.zeros(0), prior)
    if not neg or not pos:
        return empty
    totals = train.mapInPandas(_counts(params), "bucket long, neg long, pos long").groupBy("bucket").agg(F.sum("neg").alias("neg"), F.sum("pos").alias("pos"))
    rows = totals.toPandas()  # one row for each hash bucket at most
    a, b = rows["pos"].to_numpy(np.float64), rows["neg"].to_numpy(np.float64)
    share = (a + b + 1) / (neg + pos + 2)
    z = (a / pos - b / neg) / np.sqrt(share * (1 - share) * (1 / pos + 1 / neg))
    ratio = np.log(((a + params.alpha) / (a.sum() + params.alpha * len(a))) / ((b + params.alpha) / (b.sum() + params.alpha * len(b))))
    buckets = rows["bucket"].to_numpy()
    best = np.lexsort((buckets, -np.abs(z)))[: params.max_features]
    best = best[np.abs(z[best]) >= params.min_z]
    if not len(best):
        return empty
    best = best[np.argsort(buckets[best])]
    buckets, ratio = buckets[best], ratio[best]
    seen = train.mapInPandas(_selected(params, buckets), "doc_id long, y int, cols binary").toPandas().sort_values(["doc_id", "y", "cols"])
    hits = [np.frombuffer(c, "<i4") for c in seen["cols"]]
    rows = np.repeat(np.arange(len(hits)), list(map(len, hits)))
    w, bias = _logistic(rows, np.concatenate(hits), ratio, seen["y"].to_numpy(np.float64), params.l2, params.steps)
    return ToxicityModel(params, buckets, w * ratio, bias)


def score_toxicity(documents: DataFrame, model: ToxicityModel, threshold: float = 0.5) -> DataFrame:
    """(doc_id, held_out, score, predicted) per row of `documents`; null and empty texts score the bias alone.

    A null id is held out. Repeated rows are scored each, an empty table gives no row, other columns are not read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grams, table = Grams(model.params), np.zeros(1 << model.params.bits)
        table[model.buckets] = model.weights
        for batch in batches:
            raw = np.fromiter((table[grams(t)].sum() for t in texts(batch.column("text"))), np.float64, batch.num_rows) + model.bias
            score = pa.array(1 / (1 + np.exp(-np.clip(raw, -50, 50))))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), score], names=["doc_id", "held_out", "score"])

    rows = with_small_batches(documents).select(F.col("doc_id").cast("long"), held_out(F.col("doc_id")).alias("held_out"), "text")
    scored = rows.mapInArrow(run, "doc_id long, held_out boolean, score double")
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
