"""Near duplicates for a corpus: SimHash candidates, decided and completed by the similarity of word shingles.

Two texts are near copies if their sets of five-word shingles have a Jaccard similarity of 0.8 or more. Candidates come
from fingerprints by multi-index hashing (`simhash.near_links`), and from shingles, since most pairs near 0.8 differ in
more bits than any index of fingerprints can afford:

* Under any fixed order of the shingles, similar sets share one of their first fifths; common shingles, told from a
  fixed share of the texts, come last in it. Texts that share one of their very first shingles meet a few others of that bucket each, which
  ties large groups together before anything is compared pair by pair.
* Then the first fifths are dealt by shingle, and texts of different groups meet there, at first the one
  with fewest edits, then a few, at last all. Groups are told anew after each, so that few pairs tie a large one. Buckets of one
  group are left out, large ones are cut into cells that meet two by two.

Each pair is decided on whole sets; counts of the shingles by ranges of hashes, an upper bound, spare most of the others.
The nodes of the graph are distinct texts, so rows that share a doc_id but not the text are different documents.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adapterlab.llm.common import broadcast_within, checkpointed, let_go, tables, texts, tidied, with_small_batches
from adapterlab.llm.simhash import SEED, components, majority, near_links, shingle_hashes

WORDS = 5
OF, IN = 4, 5  # the similarity as a fraction, so that all bounds are exact
SHARE, COMMON = 8, 200_000  # one text in so many has its shingles counted, shingles that come last; both only steer the order
FIRST, SHIFTS = 4, (1, 2, 4, 8, 16, 32)  # shingles of a text that tie groups, distances of the texts it meets in a bucket
CELL = 4096  # rows of a bucket that meet in one place
BITS = 26  # of a shingle's hash, for the bit set of the shingles that several groups have
DIGEST = "__near_digest"


def shingles(text: str | None, words: int = WORDS) -> np.ndarray:
    """Sorted hashes of the distinct word shingles; a shorter text is one shingle, one without words has none."""
    parts = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes, as in fingerprints
    return np.unique(shingle_hashes(parts, words, SEED)) if parts else np.zeros(0, np.uint64)


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    if not len(a) or not len(b):
        return len(a) == len(b)
    if IN * min(len(a), len(b)) < OF * max(len(a), len(b)):
        return False
    return (OF + IN) * len(np.intersect1d(a, b, assume_unique=True)) >= OF * (len(a) + len(b))


def profile(s: np.ndarray) -> np.ndarray:
    """How many shingles fall in each of 2 ** k ranges of hashes, two to four on average; empty if a byte cannot count them."""
    k = max(4, (len(s) // 2).bit_length() - 1)
    counts = np.bincount((s >> np.uint64(64 - k)).astype(np.int64), minlength=1 << k)
    return counts.astype(np.uint8) if counts.max(initial=0) < 256 else np.zeros(0, np.uint8)


def may_be_similar(a: np.ndarray, b: np.ndarray) -> bool:
    """False only if even all that could be shared range by range is too little."""
    if not len(a) or not len(b):
        return True
    least = min(len(a), len(b))
    a, b = (x.reshape(least, -1).sum(axis=1, dtype=np.int64) for x in (a, b))
    return (OF + IN) * int(np.minimum(a, b).sum()) >= OF * int(a.sum() + b.sum())


def _with_digest(documents: DataFrame) -> DataFrame:
    return documents.withColumn(DIGEST, F.unhex(F.md5(F.coalesce(F.col("text"), F.lit("")))))


def _nodes(documents: DataFrame) -> DataFrame:
    """(node, doc_id, digest, copies): one row per distinct text; its smallest id and how many rows have both."""
    rows = _with_digest(documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text")).where("doc_id IS NOT NULL")
    each = rows.groupBy("doc_id", F.col(DIGEST).alias("digest")).agg(F.count(F.lit(1)).alias("copies"))
    firsts = each.groupBy("digest").agg(F.min(F.struct("doc_id", "copies")).alias("first"))
    return firsts.select(F.monotonically_increasing_id().alias("node"), "first.doc_id", "digest", "first.copies")


def _texts_of(documents: DataFrame, nodes: DataFrame) -> DataFrame:
    """(node, text) of the nodes, by one pass over the documents; rows with the same id and text give one each."""
    rows = _with_digest(documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text"))
    wanted = nodes.select("node", F.col("doc_id").alias("n_id"), F.col("digest").alias("n_digest"))
    joined = rows.join(broadcast_within(wanted), (F.col("doc_id") == F.col("n_id")) & (F.col(DIGEST) == F.col("n_digest")))
    return with_small_batches(joined).select("node", "text")


def _common(sample: DataFrame, words: int) -> np.ndarray:
    """The shingles found most often in the texts, the less common first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for t in texts(batch.column("text")):
                yield pa.RecordBatch.from_arrays([pa.array(shingles(t, words).view(np.int64))], names=["token"])

    counts = sample.select("text").mapInArrow(run, "token long").groupBy("token").count().where("count > 2")
    rows = counts.orderBy(F.col("count").desc(), "token").limit(COMMON).toPandas()
    return rows["token"].to_numpy(np.int64)[::-1].copy().view(np.uint64)


def _marks(found: DataFrame, common: np.ndarray, words: int) -> DataFrame:
    """(node, n, bits, profile, tokens): size, fingerprint, counts by range, and the shingles it may be found by, in order."""
    order = np.argsort(common)
    ordered = common[order]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, bits, profiles, tokens = [], [], [], []
            for t in texts(batch.column("text")):
                parts = (t or "").encode("utf-8", "surrogatepass").lower().split()
                every = shingle_hashes(parts, words, SEED) if parts else np.zeros(0, np.uint64)
                s = np.unique(every)
                rank = np.zeros(len(s), np.int64)
                if len(ordered) and len(s):
                    at = np.minimum(np.searchsorted(ordered, s), len(ordered) - 1)
                    rank = np.where(ordered[at] == s, order[at] + 1, 0)
                first = s[np.argsort(rank, kind="stable")][: len(s) - -(-OF * len(s) // IN) + 1] if len(s) else s
                n.append(len(s))
                bits.append(majority(every))
                profiles.append(profile(s).tobytes())
                tokens.append(first.tobytes())
            arrays = [batch.column("node"), pa.array(n, pa.int32()), pa.array(np.array(bits, np.uint64).view(np.int64)), pa.array(profiles, pa.binary()), pa.array(tokens, pa.binary())]
            yield pa.RecordBatch.from_arrays(arrays, names=["node", "n", "bits", "profile", "tokens"])

    return found.mapInArrow(tidied(run), "node long, n int, bits long, profile binary, tokens binary")


def _bit_set(tokens: DataFrame) -> bytes:
    """One bit for each value of the first BITS bits of a token; 2 ** (BITS - 6) words at most come to the driver."""
    slots = tokens.select(F.shiftrightunsigned("m_token", 64 - BITS).alias("slot"))
    words = slots.groupBy(F.shiftright("slot", 6).alias("word")).agg(F.expr("bit_or(shiftleft(1L, cast(slot & 63 as int)))").alias("bits")).toPandas()
    seen = np.zeros(1 << (BITS - 6), np.int64)
    seen[words["word"].to_numpy(np.int64)] = words["bits"].to_numpy(np.int64)
    return seen.tobytes()


def _entries(marks: DataFrame, most: int | None = None, bits=None) -> DataFrame:
    """(token, node, n, pos, root): a row for each of the first shingles, or `most` of them, whose bit is set if `bits` are given."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = None if bits is None else np.frombuffer(bits.value, "<u8")
        for batch in batches:
            for i in range(0, batch.num_rows, 1024):
                some = batch.slice(i, 1024)
                sets = [np.frombuffer(t, "<i8")[:most] for t in some.column("tokens").to_pylist()]
                m = np.fromiter(map(len, sets), np.int64, len(sets))
                pos = np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m)
                arrays = [np.concatenate(sets), np.repeat(some.column("node").to_numpy(), m), np.repeat(some.column("n").to_numpy(), m), pos.astype(np.int32), np.repeat(some.column("root").to_numpy(), m)]
                if seen is not None:
                    slot = arrays[0].view(np.uint64) >> np.uint64(64 - BITS)
                    keep = (seen[slot >> np.uint64(6)] >> (slot & np.uint64(63)) & np.uint64(1)).astype(bool)
                    arrays = [a[keep] for a in arrays]
                yield pa.RecordBatch.from_arrays([pa.array(a) for a in arrays], names=["token", "node", "n", "pos", "root"])

    return marks.where("n > 0").select("node", "n", "tokens", "root").mapInArrow(run, "token long, node long, n int, pos int, root long")


def _alike_in_size(n: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    return IN * np.minimum(n[i], n[j]) >= OF * np.maximum(n[i], n[j])


def _pairs(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    pairs = np.unique(np.sort(np.stack([a, b], axis=1), axis=1), axis=0)
    return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])


def _hubs(rows: DataFrame) -> DataFrame:
    """Distinct (a, b), a < b: each text with the first of its bucket."""
    return _met(rows, ())


def _first_met(rows: DataFrame) -> DataFrame:
    """Each text with the one first text of its whole bucket, in however many places the bucket lies."""
    first = F.min(F.struct("pos", F.xxhash64("node").alias("h"), "node", "n", "root")).alias("first")
    firsts = rows.groupBy("token").agg(first, F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi")
    firsts = firsts.select(F.col("token").alias("f_token"), *[F.col(f"first.{c}").alias(f"f_{c}") for c in ("node", "n", "root")])
    met = rows.join(broadcast_within(checkpointed(firsts)), F.col("token") == F.col("f_token"))
    met = met.where((F.col("root") != F.col("f_root")) & (IN * F.least("n", "f_n") >= OF * F.greatest("n", "f_n")))
    return met.select(F.least("node", "f_node").alias("a"), F.greatest("node", "f_node").alias("b")).distinct()


def _neighbours(rows: DataFrame) -> DataFrame:
    return _met(rows, SHIFTS)


def _met(rows: DataFrame, shifts: tuple[int, ...]) -> DataFrame:
    """Distinct (a, b), a < b: each text with the first of its bucket and with a few before it, of other groups than its own.

    shifts: which before it. Where a shingle comes early, few of the text's own stand before it: such a text is near the
    middle of its group, so it comes first in the bucket. Buckets of any size stream; what they miss is left to the last step.
    """
    if not shifts:
        return _first_met(rows)
    columns = ["token", "node", "n", "root"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [np.zeros(0, np.int64)] * 4  # rows of the last bucket that the next batch may meet, its first one in front
        for batch in batches:
            fresh = len(held[0])
            token, node, n, root = (np.concatenate([h, batch.column(c).to_numpy().astype(np.int64)]) for h, c in zip(held, columns))
            if not len(token):
                continue
            at = np.arange(fresh, len(token))
            head = np.maximum.accumulate(np.where(np.concatenate([[True], token[1:] != token[:-1]]), np.arange(len(token)), 0))
            i, j = (np.concatenate(x) for x in zip((head[at], at), *((at - k, at) for k in shifts)))
            keep = (i >= 0) & (i < j)
            i, j = i[keep], j[keep]
            keep = (token[i] == token[j]) & (root[i] != root[j]) & _alike_in_size(n, i, j)
            if keep.any():
                yield _pairs(node[i[keep]], node[j[keep]])
            last = np.unique(np.concatenate([[head[-1]], np.arange(max(head[-1], len(token) - max(shifts, default=0)), len(token))]))
            held = [token[last], node[last], n[last], root[last]]

    dealt = rows.select(*columns, "pos", F.xxhash64("node", "token").alias("h")).repartitionByRange("token", "pos", "h").sortWithinPartitions("token", "pos", "h")
    return dealt.select(*columns).mapInArrow(run, "a long, b long").distinct()


def _rooted(rows: DataFrame, roots: DataFrame) -> DataFrame:
    """With the group of each row's node as `root`; few nodes are in a group of several."""
    named = broadcast_within(roots.select(F.col("node").alias("r_node"), F.col("root").alias("r_root")))
    joined = rows.drop("root").join(named, F.col("node") == F.col("r_node"), "left")
    return joined.withColumn("root", F.coalesce("r_root", "node")).drop("r_node", "r_root")


def _shared(rooted: DataFrame) -> DataFrame:
    """(m_token) of the buckets that hold several groups."""
    return rooted.groupBy("token").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi").select(F.col("token").alias("m_token"))


def _within(rooted: DataFrame, tokens: DataFrame) -> DataFrame:
    return rooted.join(broadcast_within(tokens), F.col("token") == F.col("m_token")).drop("m_token")


def _across(mixed: DataFrame) -> DataFrame:
    """Distinct (a, b), a < b: texts of different groups that meet in a bucket, where their sizes and places leave room."""
    size = mixed.groupBy("token").agg(F.ceil(F.count(F.lit(1)) / CELL).cast("int").alias("blocks")).where("blocks > 1").withColumnRenamed("token", "s_token")
    mine = F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")
    rows = mixed.join(broadcast_within(checkpointed(size)), F.col("token") == F.col("s_token"), "left").drop("s_token")
    rows = rows.withColumn("blocks", F.coalesce("blocks", F.lit(1))).withColumn("block", mine).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = rows.withColumn("x", F.least("block", "other")).withColumn("y", F.greatest("block", "other"))
    columns = ["token", "x", "y", "block", "node", "n", "pos", "root"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None  # the last cell may go on in the next batch
        for batch in _with_end(batches):
            if batch is not None:
                now = [batch.column(c).to_numpy().astype(np.int64) for c in columns]
                held = now if held is None else [np.concatenate(p) for p in zip(held, now)]
                if not len(held[0]):
                    continue
            elif held is None:
                return
            keys = np.stack(held[:3])
            new = np.concatenate([[True], (keys[:, 1:] != keys[:, :-1]).any(axis=0)])[: len(held[0])]
            edges = [*np.flatnonzero(new).tolist(), len(held[0])]
            if batch is not None:
                edges.pop()
            found = [[], []]
            for a, b in zip(edges, edges[1:]):
                _, x, y, block, node, n, pos, root = (c[a:b] for c in held)
                i, j = np.nonzero(root[:, None] < root[None, :])
                rest = np.minimum(n[i] - pos[i], n[j] - pos[j])  # what can follow if this is the first shingle that both share
                keep = _alike_in_size(n, i, j) & ((OF + IN) * rest >= OF * (n[i] + n[j]))
                if x[0] != y[0]:  # cells of two blocks: those within a block meet in a cell of their own
                    keep &= block[i] != block[j]
                found[0].append(node[i[keep]])
                found[1].append(node[j[keep]])
            if sum(map(len, found[0])):
                yield _pairs(*map(np.concatenate, found))
            held = [c[edges[-1] :] for c in held] if batch is not None else None

    dealt = rows.select(*columns).repartition("token", "x", "y").sortWithinPartitions("token", "x", "y", "block", "node")
    return dealt.mapInArrow(run, "a long, b long").distinct()


def _with_end(batches: Iterator) -> Iterator:
    yield from batches
    yield None


def _both(pairs: DataFrame, of: DataFrame, column: str) -> DataFrame:
    x = of.select(F.col("node").alias("x_node"), F.col(column).alias("x"))
    y = of.select(F.col("node").alias("y_node"), F.col(column).alias("y"))
    return pairs.join(x, F.col("a") == F.col("x_node")).join(y, F.col("b") == F.col("y_node")).select("a", "b", "x", "y")


def _that(pairs: DataFrame, dtype: str, test) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, y = (batch.column(c) for c in ("x", "y"))
            good = [test(np.frombuffer(x[i].as_py(), dtype), np.frombuffer(y[i].as_py(), dtype)) for i in range(batch.num_rows)]
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], names=["a", "b"]).filter(pa.array(good, pa.bool_()))

    return pairs.mapInArrow(run, "a long, b long")


def _decided(pairs: DataFrame, marks: DataFrame, documents: DataFrame, nodes: DataFrame, words: int, written) -> DataFrame:
    """The pairs whose whole sets are similar."""

    def named(some: DataFrame) -> DataFrame:
        ends = some.select(F.col("a").alias("l_node")).unionByName(some.select(F.col("b").alias("l_node")))
        return broadcast_within(checkpointed(ends.distinct()))

    pairs = written(pairs)
    few = marks.select("node", "profile").join(named(pairs), F.col("node") == F.col("l_node"), "left_semi")
    likely = written(_that(_both(pairs, few, "profile"), "u1", may_be_similar))
    wanted = nodes.join(named(likely), F.col("node") == F.col("l_node"), "left_semi")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingles(t, words).tobytes() for t in texts(batch.column("text"))]
            yield pa.RecordBatch.from_arrays([batch.column("node"), pa.array(sets, pa.binary())], names=["node", "shingles"])

    sets = written(_texts_of(documents, checkpointed(wanted)).mapInArrow(tidied(run), "node long, shingles binary"))
    good = written(_that(_both(likely, sets, "shingles"), "<u8", similar).distinct())
    let_go(documents.sparkSession)
    return good


def similar_texts(documents: DataFrame, words: int = WORDS) -> DataFrame:
    """(doc_id, digest, copies, component): one row per distinct text, under its smallest doc_id; equal components are linked.

    Null and empty texts are one text, and texts without words are alike. Rows with a null doc_id take no part.
    """
    spark = documents.sparkSession
    with tables(spark) as written:
        nodes = written(_nodes(documents))
        sample = nodes.where(F.pmod(F.xxhash64("digest"), F.lit(SHARE)) == 0)
        marks = written(_marks(_texts_of(documents, nodes), _common(_texts_of(documents, sample), words), words))
        marks = marks.dropDuplicates(["node"]) if nodes.where("copies > 1").take(1) else marks
        wordless = marks.where("n = 0").select("node")
        links = wordless.crossJoin(wordless.agg(F.min("node").alias("a"))).select("a", F.col("node").alias("b")).where("a < b")  # one row on the other side
        prints = marks.where("n > 0").groupBy("bits").agg(F.min("node").alias("rep"))
        same = marks.where("n > 0").select(F.col("bits").alias("m_bits"), "node").join(prints, F.col("m_bits") == F.col("bits")).where("node <> rep")
        close = near_links(checkpointed(prints)).unionByName(same.select(F.least("rep", "node").alias("a"), F.greatest("rep", "node").alias("b")))
        decided = lambda pairs: _decided(pairs, marks, documents, nodes, words, written)
        alone = _entries(marks.withColumn("root", F.col("node")), FIRST)
        tied = decided(close.unionByName(_hubs(alone)).distinct()).unionByName(links)
        rooted = _rooted(marks, components(tied))
        shared = written(_shared(_entries(rooted)))
        bits = spark.sparkContext.broadcast(_bit_set(shared))  # most shingles are one text's own and need no exchange
        mixed = written(_within(_entries(rooted, bits=bits), shared))
        for meet in (_hubs, _neighbours):  # the second for what the first left apart
            tied = tied.unionByName(decided(meet(mixed)))
            rooted = _rooted(mixed, components(tied))
            let_go(spark)
            mixed = written(_within(rooted, written(_shared(rooted))))
        roots = components(tied.unionByName(decided(_across(mixed))))
        return checkpointed(
            nodes.join(roots.withColumnRenamed("node", "r_node"), F.col("node") == F.col("r_node"), "left").select(
                "doc_id", "digest", "copies", F.coalesce("root", "node").alias("component")
            )
        )


def keep_one_of_similar(documents: DataFrame, words: int = WORDS) -> DataFrame:
    """One document of each group of similar texts, all columns: the text with the smallest doc_id (then digest).

    Rows without an id stay. Rows that share both id and text are one document, of which the row with the smallest hash of
    all columns stays; rows that share an id but not the text are different documents.
    """
    found = similar_texts(documents, words)
    first = found.groupBy("component").agg(F.min(F.struct("doc_id", "digest", "copies")).alias("k"))
    kept = broadcast_within(checkpointed(first.select(F.col("k.doc_id").alias("__near_id"), F.col("k.digest").alias("__near_kept"), F.col("k.copies").alias("__near_copies"))))
    rows = _with_digest(documents).join(kept, (F.col("doc_id").cast("long") == F.col("__near_id")) & (F.col(DIGEST) == F.col("__near_kept")))
    once = rows.where("__near_copies = 1").select(*documents.columns)
    whole = F.struct(*documents.columns)
    again = rows.where("__near_copies > 1").groupBy("__near_id", "__near_kept").agg(F.min_by(whole, F.xxhash64(*documents.columns)).alias("row")).select("row.*")
    return once.unionByName(again).unionByName(documents.where(F.col("doc_id").isNull()))
