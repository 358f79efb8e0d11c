"""SimHash near-duplicates by multi-index hashing.

A 64-bit fingerprint is cut into segments. If two fingerprints differ in at most r bits, one of m segments
differs in at most floor(r / m); so the Hamming ball of that radius around each segment is looked up in the
table of segments, and the whole distance decides. Only distinct fingerprints take part; copies share a class
from the start. Classes are the connected components of the links.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from adapterlab.llm.common import checkpointed, texts, with_small_batches

SEED, WORDS, DISTANCE, SEGMENTS = 42, 3, 3, 2


def fingerprint(text: str | None, words: int = WORDS, seed: int = SEED) -> int:
    """64-bit SimHash over word shingles, repeats included; zero for a text without words."""
    parts = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: ASCII white space and letters only
    if not parts:
        return 0
    return majority(shingle_hashes(parts, words, seed))


def shingle_hashes(parts: list[bytes], words: int, seed: int = SEED) -> np.ndarray:
    """Hash of each run of so many words, repeats included; fewer words are one run."""
    joined = b" ".join(parts)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1)
    starts = np.concatenate([[0], ends[:-1]])
    k = min(words, len(parts))
    spans = zip(starts[: len(parts) - k + 1].tolist(), (ends[k - 1 :] - 1).tolist())
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(joined[a:b], seed) for a, b in spans), np.uint64, len(parts) - k + 1)


def majority(h: np.ndarray) -> int:
    """The bits set in over half the hashes."""
    ones = np.zeros(64, np.int64)
    for i in range(0, len(h), 4096):
        block = h[i : i + 4096]
        ones += np.unpackbits(block.view(np.uint8).reshape(len(block), 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(h), bitorder="little").view("<u8")[0])


def fingerprints(documents: DataFrame, words: int = WORDS) -> DataFrame:
    """(doc_id, bits) per row; bits: the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bits = np.fromiter((fingerprint(t, words) for t in texts(batch.column("text"))), np.uint64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(bits.view(np.int64))], names=["doc_id", "bits"])

    return with_small_batches(documents).select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, bits long")


def near_links(classes: DataFrame, distance: int = DISTANCE, segments: int = SEGMENTS) -> DataFrame:
    """Links (a, b), a < b, between the `rep`s of distinct `bits` that differ in at most `distance` bits."""
    if not 1 <= segments <= 64 or 64 % segments:
        raise ValueError("segments must divide 64")
    width, radius = 64 // segments, distance // segments
    mask = F.lit((1 << width) - 1 if width < 64 else -1)
    # Of two keys that differ, the one with the highest of the differing bits set looks the other up: half a ball each.
    flips = [(sum(1 << b for b in chosen), 1 << max(chosen, default=0)) for r in range(radius + 1) for chosen in combinations(range(width), r)]
    signed = lambda x: x - (1 << 64) if x >= 1 << 63 else x
    ball = F.array(*[F.struct(F.lit(signed(f)).cast("long").alias("f"), F.lit(signed(h if f else 0)).cast("long").alias("h")) for f, h in flips])
    keys = F.array(*[F.shiftrightunsigned("bits", width * s).bitwiseAND(mask) for s in range(segments)])
    table = classes.select("rep", "bits", F.posexplode(keys).alias("segment", "key"))
    mine = F.filter(ball, lambda x: (x["h"] == 0) | (F.col("key").bitwiseAND(x["h"]) != 0))
    probes = table.select("rep", "bits", "segment", F.explode(F.transform(mine, lambda x: F.col("key").bitwiseXOR(x["f"]))).alias("key"))
    p, t = probes.alias("p"), table.alias("t")
    met = p.join(
        t,
        (F.col("p.segment") == F.col("t.segment")) & (F.col("p.key") == F.col("t.key")) & (F.col("p.rep") != F.col("t.rep"))
        & (F.bit_count(F.col("p.bits").bitwiseXOR(F.col("t.bits"))) <= distance),
    )
    return met.select(F.least("p.rep", "t.rep").alias("a"), F.greatest("p.rep", "t.rep").alias("b")).distinct()


def components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node of `links` but the roots; root: the smallest node of its component.

    Rounds of star contraction: a node's larger neighbours, then its smaller ones, are tied to the smallest
    node around it, until every component is a star. Each round is written to the checkpoint folder.
    """

    def smallest_around(pairs: DataFrame) -> DataFrame:
        m = pairs.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("c"), F.least("u", "m").alias("m"))
        return pairs.withColumn("hu", F.hash("u")).join(m.withColumn("hc", F.hash("c")), (F.col("hu") == F.col("hc")) & (F.col("u") == F.col("c")))

    def settled(edges: DataFrame) -> tuple[DataFrame, tuple]:
        """The edges, written, and what tells two states apart, gathered while they are written."""
        seen = Observation()
        told = edges.observe(seen, F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h"))
        edges = checkpointed(told)
        return edges, (seen.get["n"], seen.get["h"])

    edges, before = settled(links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct())
    for _ in range(max_rounds):
        both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
        large = smallest_around(both).where("v > u").select(F.col("m").alias("a"), F.col("v").alias("b")).where("a < b").distinct()
        down = large.select(F.col("b").alias("u"), F.col("a").alias("v"))
        near = smallest_around(down)
        tied = near.select(F.col("m").alias("a"), F.col("v").alias("b")).unionByName(near.select(F.col("m").alias("a"), F.col("u").alias("b")))
        edges, now = settled(tied.where("a < b").distinct())
        if now == before:
            return edges.select(F.col("b").alias("node"), F.col("a").alias("root"))
        before = now
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")


def near_duplicates(documents: DataFrame, distance: int = DISTANCE, words: int = WORDS, segments: int = SEGMENTS) -> DataFrame:
    """(doc_id, fingerprint, component_id) per row of `documents`; component_id: the smallest doc_id reachable.

    Null and empty texts have fingerprint zero and are linked like any other. Rows with a null doc_id take no
    part and have a null component_id. Repeated rows stay; other columns are not read.
    """
    marks = checkpointed(fingerprints(documents, words))
    classes = checkpointed(marks.where(F.col("doc_id").isNotNull()).groupBy("bits").agg(F.min("doc_id").alias("rep")))
    # Ids that occur with several fingerprints tie these together as well.
    tied = marks.where(F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.min("bits").alias("lo"), F.max("bits").alias("hi")).where("lo <> hi")
    again = marks.join(tied.select("doc_id"), "doc_id").select("doc_id", "bits").distinct().join(classes, "bits")
    links = near_links(classes, distance, segments).unionByName(again.where("doc_id <> rep").select(F.col("rep").alias("a"), F.col("doc_id").alias("b")))
    roots = components(links)
    named = classes.join(roots, F.col("rep") == F.col("node"), "left").select(
        F.hash("bits").alias("c_hash"), F.col("bits").alias("c_bits"), F.coalesce("root", "rep").alias("component_id")
    )
    with_hash = marks.withColumn("hash", F.hash("bits"))  # exchanges on both sides: large classes are split at run time
    joined = with_hash.join(named, (F.col("hash") == F.col("c_hash")) & (F.col("bits") == F.col("c_bits")), "left")
    return joined.select(
        "doc_id", F.lower(F.lpad(F.hex("bits"), 16, "0")).alias("fingerprint"), F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id")
    )
