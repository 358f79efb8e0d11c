"""Quality classifier: histogram gradient-boosted trees over document statistics.

The trees are grown on binned statistics of a bounded labelled sample, then flattened into node arrays that
numpy walks for a whole batch and all trees at once.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from itertools import islice
from operator import eq

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adapterlab.llm.common import held_out, texts, training_ids, with_small_batches

STATISTICS = (
    "log_bytes", "log_words", "log_lines", "word_bytes", "longest_word", "upper", "lower", "digit", "space", "high", "stops", "bangs",
    "symbols", "pipes", "symbols_per_word", "distinct_words", "distinct_pairs", "top_word", "doubled", "distinct_lines", "line_bytes",
    "short_words", "stops_per_word", "letters_per_word",
)
SYMBOLS = np.frombuffer(b"#$%&*@=<>{}[]\\/^~_+", np.uint8)


@dataclass(frozen=True)
class QualityParams:
    train_per_class: int = 6000  # labelled documents of each class at most
    bins: int = 64
    trees: int = 80
    depth: int = 4
    rate: float = 0.15
    l2: float = 1.0
    min_gain: float = 1e-3
    min_hessian: float = 1.0


@dataclass(frozen=True)
class Forest:
    """Flattened trees: node k sends x[feature[k]] <= cut[k] to left[k], else to right[k]; a leaf sends to itself."""

    roots: np.ndarray
    feature: np.ndarray
    cut: np.ndarray
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray
    depth: int
    bias: float

    def raw(self, x: np.ndarray) -> np.ndarray:
        at = np.broadcast_to(self.roots, (len(x), len(self.roots)))
        rows = np.arange(len(x))[:, None]
        for _ in range(self.depth):
            at = np.where(x[rows, self.feature[at]] <= self.cut[at], self.left[at], self.right[at])
        return self.bias + self.value[at].sum(axis=1)

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(x), -50, 50)))


def statistics(text: str | None) -> list[float]:
    """STATISTICS of a whole text; all zero for an empty one."""
    text = text or ""
    raw = text.encode("utf-8", "surrogatepass")
    words = text.split()
    if not words:
        return [0.0] * len(STATISTICS)
    n, w = len(raw), len(words)
    c = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    space, upper, lower, high = int(c[9:14].sum() + c[32]), int(c[65:91].sum()), int(c[97:123].sum()), int(c[128:].sum())
    stops, bangs, symbols, pipes = int(c[46] + c[44] + c[63] + c[58] + c[59]), int(c[33]), int(c[SYMBOLS].sum()), int(c[124])
    lines = [x for x in text.split("\n") if x]
    counts = Counter(words)
    pairs = len(set(zip(words, islice(words, 1, None))))
    sizes = np.fromiter(map(len, words), np.int64, w)
    return [
        np.log1p(n), np.log1p(w), np.log1p(len(lines)), (n - space) / w, float(sizes.max()), upper / n, lower / n, int(c[48:58].sum()) / n,
        space / n, high / n, stops / n, bangs / n, symbols / n, pipes / n, symbols / w, len(counts) / w, pairs / max(1, w - 1),
        max(counts.values()) / w, sum(map(eq, words, islice(words, 1, None))) / w, len(set(lines)) / max(1, len(lines)), n / max(1, len(lines)),
        float((sizes <= 2).mean()), stops / w, (upper + lower + high) / w,
    ]


def matrix(column: Iterable[str | None]) -> np.ndarray:
    return np.array([statistics(t) for t in column], np.float64).reshape(-1, len(STATISTICS))


def grow_forest(x: np.ndarray, y: np.ndarray, params: QualityParams = QualityParams()) -> Forest:
    """Boosts the log loss level by level; every split is found in per-bin sums of gradients and hessians."""
    n, f = x.shape
    y = y.astype(np.float64)
    bias = float(np.log((y.sum() + 1) / (n - y.sum() + 1)))
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, params.bins + 1)[1:-1])) if n else np.zeros(0) for j in range(f)]
    binned = np.stack([np.searchsorted(cuts[j], x[:, j], side="left") for j in range(f)], axis=1) if n else np.zeros((0, f), np.int64)
    width = params.bins
    flat = binned + np.arange(f) * width
    nodes: dict[str, list] = {k: [] for k in ("feature", "cut", "left", "right", "value")}

    def node() -> int:
        k = len(nodes["value"])
        for name, v in (("feature", 0), ("cut", np.inf), ("left", k), ("right", k), ("value", 0.0)):
            nodes[name].append(v)
        return k

    roots, margin = [], np.full(n, bias)
    for _ in range(params.trees if 0 < y.sum() < n else 0):
        p = 1 / (1 + np.exp(-margin))
        g, h = p - y, p * (1 - p)
        roots.append(node())
        open_, where = [(roots[-1], np.arange(n))], np.zeros(n)
        for level in range(params.depth + 1):
            grown = []
            for k, rows in open_:
                gs, hs = g[rows].sum(), h[rows].sum()
                nodes["value"][k] = float(-params.rate * gs / (hs + params.l2))
                where[rows] = nodes["value"][k]
                if level == params.depth or hs < 2 * params.min_hessian:
                    continue
                at = flat[rows].ravel()
                gl = np.bincount(at, np.repeat(g[rows], f), f * width).reshape(f, width).cumsum(axis=1)
                hl = np.bincount(at, np.repeat(h[rows], f), f * width).reshape(f, width).cumsum(axis=1)
                gain = gl**2 / (hl + params.l2) + (gs - gl) ** 2 / (hs - hl + params.l2) - gs**2 / (hs + params.l2)
                gain[(hl < params.min_hessian) | (hs - hl < params.min_hessian)] = -1
                j, b = divmod(int(gain.argmax()), width)
                if gain[j, b] < params.min_gain or b >= len(cuts[j]):
                    continue
                left, right = node(), node()
                nodes["feature"][k], nodes["cut"][k], nodes["left"][k], nodes["right"][k] = j, float(cuts[j][b]), left, right
                goes = binned[rows, j] <= b
                grown += [(left, rows[goes]), (right, rows[~goes])]
            open_ = grown
        margin = margin + where
    if not roots:
        roots = [node()]
    return Forest(np.array(roots), *(np.array(nodes[k]) for k in ("feature", "cut", "left", "right", "value")), params.depth, bias)


def _with_statistics(keep: list[str]):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            x = pd.DataFrame(matrix(batch["text"]), columns=list(STATISTICS))
            yield pd.concat([batch[keep].reset_index(drop=True), x], axis=1)

    return run


def fit_quality(documents: DataFrame, labels: DataFrame, params: QualityParams = QualityParams(), label: str = "quality") -> Forest:
    """Learns from at most `train_per_class` labelled documents of each class, none of them held out.

    Null texts are empty, rows that repeat an id each count, null ids and null labels are left out (`training_ids`). Without
    documents of both classes the forest has no tree and scores their share alone; other columns are not read.
    """
    ids = training_ids(labels, label, params.train_per_class)
    train = with_small_batches(documents).select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(ids), F.col("doc_id") == F.col("train_id"))
    schema = "doc_id long, y int, " + ", ".join(f"{s} double" for s in STATISTICS)
    rows = train.select("doc_id", "text", "y").mapInPandas(_with_statistics(["doc_id", "y"]), schema).toPandas()
    rows = rows.sort_values(["doc_id", "y", *STATISTICS])
    return grow_forest(rows[list(STATISTICS)].to_numpy(np.float64), rows["y"].to_numpy(), params)


def score_quality(documents: DataFrame, forest: Forest, threshold: float = 0.3) -> DataFrame:
    """(doc_id, held_out, score, predicted) per row of `documents`; null and empty texts have statistics of zero.

    A null id is held out. Repeated rows are scored each, an empty table gives no row, other columns are not read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = pa.array(forest.score(matrix(texts(batch.column("text")))))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), score], names=["doc_id", "held_out", "score"])

    rows = with_small_batches(documents).select(F.col("doc_id").cast("long"), held_out(F.col("doc_id")).alias("held_out"), "text")
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double").withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def keep_quality(documents: DataFrame, forest: Forest, threshold: float = 0.3) -> DataFrame:
    """The rows of `documents`, all columns, whose score reaches the threshold; one pass, no join.

    Null texts are scored as empty ones; ids play no part, repeated rows stay or go together, whatever the columns are named.
    """

    @F.pandas_udf("double")
    def score(column: pd.Series) -> pd.Series:
        return pd.Series(forest.score(matrix(column)))

    return with_small_batches(documents).where(score(F.coalesce("text", F.lit(""))) >= threshold)
