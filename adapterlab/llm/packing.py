"""Best-fit packing of tokenised documents with large-item matching.

Lengths are whole numbers up to the capacity, so the whole corpus is planned from its histogram of piece
lengths: pieces above a third of the capacity share a sequence with one other at most and are matched
greedily, smaller pieces go to the tightest gap. The plan says for each length which ranks go where; ranks are
numbered in parallel, and no piece ever meets all others in one task.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from adapterlab.llm.common import checkpointed, texts, tidied, with_small_batches

CAPACITY = 1024
END_ID = 2


class ByteBpe:
    """Token ids of a byte-level BPE file of the tokenizers library.

    Plain text goes through the same vocabulary in tiktoken, several times faster. Texts with a special token's
    string, or with characters whose class may differ between the libraries' Unicode tables, go to tokenizers.
    """

    # Fixed value: the public pattern of this kind of vocabulary (`use_regex` of the byte-level pre-tokenizer).
    PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""

    def __init__(self, path: str):
        import regex
        import tiktoken

        self.path = path
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        specials = [t["content"] for t in spec.get("added_tokens", [])]
        plain = [c for c in range(256) if 33 <= c <= 126 or 161 <= c <= 172 or c >= 174]
        shown = {chr(c): c for c in plain} | {chr(256 + k): c for k, c in enumerate(c for c in range(256) if c not in set(plain))}
        ranks = {bytes(shown[ch] for ch in token): k for token, k in spec["model"]["vocab"].items() if token not in specials}
        self.fast = tiktoken.Encoding("bytes", pat_str=self.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.odd = regex.compile("|".join([r"[^\t\n\r\x20-\x7e¡-ſ‐-‧]", *map(regex.escape, specials)]))

    @cached_property
    def slow(self):
        """Loaded for the first odd text; most tasks have none."""
        from tokenizers import Tokenizer

        return Tokenizer.from_file(self.path)

    def __call__(self, text: str) -> np.ndarray:
        if self.odd.search(text):
            return np.array(self.slow.encode(text, add_special_tokens=False).ids, "<u4")
        return np.asarray(self.fast.encode_to_numpy(text, disallowed_special=()), "<u4")


def tokenize(documents: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, end_id: int = END_ID, keep_ids: bool = False) -> DataFrame:
    """Pieces (doc_id, piece, start, length, ids_crc32[, ids], part, k) of at most `capacity` ids.

    The ids of a document end in `end_id`, so that null and empty texts have one. A longer document is cut so
    that only its first piece is shorter. `k` numbers the pieces of one length within the task `part`.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part, seen = ByteBpe(tokenizer_path), TaskContext.get().partitionId(), np.zeros(capacity + 1, np.int64)
        for batch in batches:
            at, out = [], []
            for i, text in enumerate(texts(batch.column("text"))):
                ids = np.append(encode(text), np.uint32(end_id)).astype("<u4")
                first = (len(ids) - 1) % capacity + 1
                cuts = [0, *range(first, len(ids) + 1, capacity)]
                for j, (a, b) in enumerate(zip(cuts, cuts[1:])):
                    raw = ids[a:b].tobytes()
                    at.append(i)
                    out.append((j, a, b - a, zlib.crc32(raw), part, int(seen[b - a]), raw if keep_ids else None))
                    seen[b - a] += 1
            columns = [list(c) for c in zip(*out)] or [[]] * 7
            kinds = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.binary()]
            names = ["piece", "start", "length", "ids_crc32", "part", "k", "ids"]
            arrays = [batch.column("doc_id").take(pa.array(at, pa.int64())), *(pa.array(c, t) for c, t in zip(columns, kinds))]
            yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", *names])

    rows = with_small_batches(documents).select(F.col("doc_id").cast("long"), "text")
    pieces = rows.mapInArrow(tidied(run), "doc_id long, piece int, start long, length long, ids_crc32 long, part int, k long, ids binary")
    return pieces if keep_ids else pieces.drop("ids")


@dataclass
class Bins:
    """`copies` equal sequences; items: (length, times) in order."""

    copies: int
    free: int
    items: list[tuple[int, int]] = field(default_factory=list)

    def adding(self, copies: int, length: int, times: int) -> Bins:
        return Bins(copies, self.free - length * times, [*self.items, (length, times)])


def plan_bins(counts: dict[int, int], capacity: int = CAPACITY) -> list[Bins]:
    """Packs counts[length] items of each length; equal sequences are planned together."""
    left = {n: c for n, c in counts.items() if c}
    large = sorted((n for n in left if 3 * n > capacity), reverse=True)
    by_free: dict[int, list[Bins]] = {}

    def put(b: Bins) -> None:
        if b.copies:
            by_free.setdefault(b.free, []).append(b)

    for n in large:
        while left[n]:
            mate = next((m for m in large if m <= n and n + m <= capacity and left[m] >= (2 if m == n else 1)), None)
            if mate is None:
                put(Bins(left[n], capacity - n, [(n, 1)]))
                left[n] = 0
                continue
            pairs = left[n] // 2 if mate == n else min(left[n], left[mate])
            put(Bins(pairs, capacity - n - mate, [(n, 2)] if mate == n else [(n, 1), (mate, 1)]))
            left[n] -= pairs
            left[mate] -= pairs
    for n in sorted((n for n in left if 3 * n <= capacity), reverse=True):
        while left[n]:
            gap = min((f for f, bins in by_free.items() if f >= n and bins), default=None)
            b = by_free[gap].pop() if gap is not None else Bins(-(-left[n] // (capacity // n)), capacity)
            times = min(b.free // n, left[n])
            full = min(b.copies, left[n] // times)
            put(b.adding(full, n, times))
            put(Bins(b.copies - full, b.free, b.items))
            left[n] -= full * times
    return [b for bins in by_free.values() for b in bins if b.items]


def plan_rows(bins: list[Bins]) -> list[tuple[int, int, int, int, int, int]]:
    """(length, first rank, end rank, times, first sequence, offset) of each run of equal items."""
    rows, used, sequence = [], {}, 0
    for b in bins:
        offset = 0
        for n, times in b.items:
            first = used.get(n, 0)
            used[n] = first + b.copies * times
            rows.append((n, first, used[n], times, sequence, offset))
            offset += n * times
        sequence += b.copies
    return rows


def pack_documents(documents: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, end_id: int = END_ID, keep_ids: bool = False) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset[, ids]), one row per piece.

    Sequences hold at most `capacity` ids without gaps. Only the histogram of lengths, `capacity` rows at most,
    comes to the driver. Repeated rows and repeated or null ids are packed like any others; an empty table
    gives no row; other columns are not read.
    """
    spark = documents.sparkSession
    pieces = checkpointed(tokenize(documents, tokenizer_path, capacity, end_id, keep_ids))
    counts = {r["length"]: r["count"] for r in pieces.groupBy("length").count().collect()}
    plan = spark.createDataFrame(
        plan_rows(plan_bins(counts, capacity)),
        "p_length long, first long, end long, times long, sequence long, p_offset long",
    )
    per_part = pieces.groupBy(F.col("part").alias("b_part"), F.col("length").alias("b_length")).agg(F.count(F.lit(1)).alias("n"))
    earlier = Window.partitionBy("b_length").orderBy("b_part").rowsBetween(Window.unboundedPreceding, -1)
    base = per_part.select("b_part", "b_length", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("base"))
    ranked = pieces.join(base, (F.col("part") == F.col("b_part")) & (F.col("length") == F.col("b_length"))).withColumn("rank", F.col("k") + F.col("base"))
    # The plan has a few rows for each length, whatever the number of documents.
    placed = ranked.join(F.broadcast(plan), (F.col("length") == F.col("p_length")) & (F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("end")))
    within = F.col("rank") - F.col("first")
    return placed.select(
        "doc_id", "piece", "start", "length", "ids_crc32",
        (F.col("sequence") + F.floor(within / F.col("times"))).cast("long").alias("sequence_id"),
        (F.col("p_offset") + within % F.col("times") * F.col("length")).alias("offset"),
        *(["ids"] if keep_ids else []),
    )
