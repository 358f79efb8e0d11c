"""Exact substring dedup by bucket-pointer refinement of suffixes.

A byte goes if it lies in a string of `length` bytes that also starts earlier. Suffixes are put into q-gram
buckets, and buckets are refined by the bucket pointers of later offsets until strings of the full length are
told apart; buckets of one suffix are never touched again.

Spread over a cluster this takes these steps:

1. Documents are dealt into groups of a few MB. Each string has one anchor, the smallest q-gram hash inside it, so
   that equal strings have equal anchors. Consecutive strings with one anchor form a run, and the anchor's q-gram is the
   first bucket. A group sends each distinct (bucket, content) of its runs once.
2. Bucket by bucket: runs with a content seen earlier are repeats as a whole; a bucket with one content is done
   (as a bucket of one suffix is); only runs in buckets of several contents need refinement.
3. These runs are sent with their bytes and refined by bucket pointers, doubling the depth. A bucket with very many
   contents (a common line in ever new surroundings) is cut down to single strings by pointers that need no
   neighbours, the hashes of its 64-byte ends, so that none grows with the corpus.
4. The groups take the verdicts and cut their documents.

Bytes of documents move once; the other exchanges carry hashes, verdicts and the few runs of step 3.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

LENGTH, GRAM = 100, 32
GROUP_BYTES = 4 << 20
BLOCK = 1 << 18
REFINED = 1 << 18  # bytes refined at once, beside the first bucket that crosses it
LOCAL_CONTENTS, BUCKET_CONTENTS = 64, 4096  # beyond these, a bucket is cut down to single strings
GROUP = "__group"  # a column of our own, beside whatever columns the documents have
KEEP, REPEAT, REFINE, SINGLE = 0, 1, 2, 3
U = np.uint64
ENTRY = np.dtype([("h", "<u8"), ("c", "<u8"), ("doc", "<i8"), ("hot", "u1")])
RUN = np.dtype([("h", "<u8"), ("doc", "<i8"), ("at", "<i8"), ("strings", "<i4")])
STRING = np.dtype([("x", "<u8"), ("y", "<u8"), ("doc", "<i8"), ("at", "<i8")])


def _mix(x: np.ndarray) -> np.ndarray:
    x ^= x >> U(32)
    x *= U(0xD6E8FEB86659FD93)
    x ^= x >> U(32)
    return x


def _double(g: np.ndarray, step: int) -> np.ndarray:
    out = g[:-step] * U(0x9E3779B97F4A7C15)
    out += g[step:]
    return _mix(out)


def gram_hashes(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the 32- and 64-byte grams that start at each byte."""
    eight = np.ndarray((len(data) - 7,), "<u8", data, 0, (1,)).astype(U)
    eight *= U(0xC2B2AE3D27D4EB4F)
    g32 = _double(_double(_mix(eight), 8), 16)
    return g32, _double(g32, 32)


@dataclass
class Runs:
    """Runs of strings with one anchor; first and last are positions of strings in the group's bytes."""

    first: np.ndarray
    last: np.ndarray
    h: np.ndarray  # bucket: the anchor's q-gram
    c: np.ndarray  # content


def find_runs(data: np.ndarray, offsets: np.ndarray, length: int = LENGTH) -> Runs:
    window, n = length - GRAM + 1, len(data)
    steps = -(-(length + window - 1 - 64) // 64)  # so that no byte of the longest run is left out
    found: list[tuple[np.ndarray, ...]] = []
    if n >= length:
        valid = np.ones(n, bool)
        for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist()):
            valid[max(a, b - length + 1) : b] = False
        mask = U((1 << 24) - 1)
        for at in range(0, n - length + 1, BLOCK):
            ok = valid[at : at + BLOCK][: n - length + 1 - at]
            m = len(ok)
            if not ok.any():
                continue
            g32, g64 = gram_hashes(data[at : at + m + length - 1])
            key = (g32 & ~mask) | np.arange(len(g32), dtype=U)
            low, span = key, 1
            while 2 * span <= window:
                low = np.minimum(low[:-span], low[span:])
                span *= 2
            low = np.minimum(low[:m], low[window - span : window - span + m])
            anchor = (low & mask).astype(np.int64)
            new = ok.copy()
            new[1:] &= ~ok[:-1] | (anchor[1:] != anchor[:-1])
            end = ok.copy()
            end[:-1] &= ~ok[1:] | (anchor[1:] != anchor[:-1])
            first, last = np.flatnonzero(new), np.flatnonzero(end)
            p, size = anchor[first], last - first + length
            c = g64[first] * U(0x9E3779B97F4A7C15)
            for k in range(1, steps):  # 64-byte grams over the whole run
                c = _mix(c + g64[first + (size - 64) * k // steps]) * U(0xC2B2AE3D27D4EB4F)
            c = _mix(c + g64[first + size - 64]) + size.astype(U) * U(0x165667B19E3779F9) + (p - first).astype(U)
            found.append((first + at, last + at, g32[p], _mix(c)))
    if not found:
        return Runs(*(np.zeros(0, np.int64) for _ in range(2)), *(np.zeros(0, U) for _ in range(2)))
    return Runs(*(np.concatenate(x) for x in zip(*found)))


@dataclass
class Group:
    """Documents of one group in order, and what of their runs others need to know."""

    table: pa.Table
    data: np.ndarray
    offsets: np.ndarray
    ids: np.ndarray
    runs: Runs
    repeats: np.ndarray  # runs whose content was seen earlier in this group
    firsts: np.ndarray  # the others, by (bucket, h, c); those of hot buckets are not among them
    single: np.ndarray  # runs of buckets with many contents in this group alone
    entries: np.ndarray
    cuts: np.ndarray  # entries[cuts[b]:cuts[b + 1]] go to bucket b
    doc: np.ndarray  # id of each run's document


def bytes_of(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    column = pa.concat_arrays(table.column("text").cast(pa.large_string()).fill_null("").chunks or [pa.array([], pa.large_string())])
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, "<i8", len(column) + 1, column.offset * 8) if len(column) else np.zeros(1, np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def ordered(table: pa.Table) -> pa.Table:
    """Rows by id (null first), then text; equal ones are alike."""
    keys = pa.table({"doc_id": table.column("doc_id"), "text": table.column("text")})
    return table.take(pc.sort_indices(keys, [("doc_id", "ascending"), ("text", "ascending")], null_placement="at_start"))


def analyse(table: pa.Table, buckets: int, length: int) -> Group:
    """The same for the same rows in any order, so that it can be made again when the verdicts come."""
    table = ordered(table)
    data, offsets = bytes_of(table)
    ids = table.column("doc_id").fill_null(np.iinfo(np.int64).min).to_numpy()
    runs = find_runs(data, offsets, length)
    order = np.lexsort((runs.first, runs.c, runs.h))
    h, c = runs.h[order], runs.c[order]
    new_h = np.ones(len(h), bool)
    new_h[1:] = h[1:] != h[:-1]
    new = new_h.copy()
    new[1:] |= c[1:] != c[:-1]
    bucket_no = np.cumsum(new_h) - 1
    contents = np.bincount(bucket_no[new]) if len(h) else np.zeros(0, np.int64)
    hot = contents[bucket_no] > LOCAL_CONTENTS if len(h) else np.zeros(0, bool)
    doc = ids[np.searchsorted(offsets, runs.first, side="right") - 1] if len(h) else np.zeros(0, np.int64)

    sent = order[new & (~hot | new_h)]
    is_hot = hot[new & (~hot | new_h)]
    bucket = ((runs.h[sent] * U(0x9E3779B97F4A7C15)) >> U(33)) % U(buckets)
    by_bucket = np.argsort(bucket, kind="stable")
    sent, is_hot, bucket = sent[by_bucket], is_hot[by_bucket], bucket[by_bucket]
    entries = np.zeros(len(sent), ENTRY)
    entries["h"], entries["c"], entries["doc"], entries["hot"] = runs.h[sent], runs.c[sent], doc[sent], is_hot
    cuts = np.searchsorted(bucket, np.arange(buckets + 1, dtype=U))
    return Group(table, data, offsets, ids, runs, order[~new], np.where(is_hot, -1, sent), order[new & hot], entries, cuts, doc)


def refine(data: np.ndarray, ends: np.ndarray, length: int = LENGTH) -> np.ndarray:
    """Bucket pointers at depth `length`; equal pointers mean equal strings. -1 where fewer bytes are left.

    ends[i]: where the piece that holds byte i ends; no string crosses it.
    """
    n = len(data)
    pointer = np.full(n, -1, np.int64)
    at = np.flatnonzero(ends - np.arange(n) >= 8)
    if not len(at):
        return pointer
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    words = np.ndarray((n,), ">u8", padded, 0, (1,))[at].astype(U)
    order = np.argsort(words, kind="stable")
    ranked = words[order]
    new = np.concatenate([[True], ranked[1:] != ranked[:-1]])
    pointer[at[order]] = np.flatnonzero(new)[np.cumsum(new) - 1]
    depth = 8
    while depth < length:
        step = min(depth, length - depth)
        at = at[ends[at] - at >= depth + step]
        size = np.bincount(pointer[at], minlength=n + 1) if len(at) else np.zeros(n + 1, np.int64)
        live = at[size[pointer[at]] > 1]
        mine, later = pointer[live], pointer[live + step]
        order = np.lexsort((later, mine))
        mine, later, live = mine[order], later[order], live[order]
        if len(live):
            head = np.concatenate([[True], mine[1:] != mine[:-1]])
            new = head | np.concatenate([[True], later[1:] != later[:-1]])
            index = np.arange(len(live))
            start = np.maximum.accumulate(np.where(head, index, 0))
            run = np.maximum.accumulate(np.where(new, index, 0))
            moved = mine + (run - start)
        short = np.flatnonzero((pointer >= 0) & (ends - np.arange(n) < depth + step))
        pointer[short] = -1
        if len(live):
            pointer[live] = moved
        depth += step
    return pointer


def string_hashes(g64: np.ndarray, at: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Two hashes of each string that starts at `at`, over all its bytes; the first one that of its first gram."""
    steps = max(1, -(-(length - 64) // 64))
    y = g64[at + length - 64]
    for k in range(1, steps):
        y = _mix(y * U(0x9E3779B97F4A7C15) + g64[at + (length - 64) * k // steps])
    return g64[at], y


def _pack(rows: list[tuple], schema: pa.Schema) -> pa.Table:
    return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), schema.types)] if rows else [pa.array([], t) for t in schema.types], schema=schema)


ASK = pa.schema([("bucket", pa.int64()), ("g", pa.int64()), ("kind", pa.int32()), ("head", pa.binary()), ("body", pa.binary())])
ASK_SQL = "bucket long, g long, kind int, head binary, body binary"


def _announce(buckets: int, length: int):
    def run(table: pa.Table) -> pa.Table:
        group, g = analyse(table, buckets, length), table.column(GROUP)[0].as_py()
        pairs = [(b, group.entries[group.cuts[b] : group.cuts[b + 1]]) for b in np.flatnonzero(np.diff(group.cuts)).tolist()]
        return _pack([(b, g, 0, e.tobytes(), b"") for b, e in pairs], ASK)

    return run


def _judge_contents(table: pa.Table) -> pa.Table:
    bucket, groups = table.column("bucket")[0].as_py(), table.column("g").to_pylist()
    parts = [np.frombuffer(x, ENTRY) for x in table.column("head").to_pylist()]
    e = np.concatenate(parts)
    g = np.repeat(np.array(groups), [len(p) for p in parts])
    order = np.lexsort((g, e["doc"], e["c"], e["h"]))
    s = e[order]
    new_h = np.concatenate([[True], s["h"][1:] != s["h"][:-1]])
    new = new_h | np.concatenate([[True], s["c"][1:] != s["c"][:-1]])
    no = np.cumsum(new_h) - 1
    contents = np.bincount(no[new])[no]
    hot = np.maximum.reduceat(s["hot"], np.flatnonzero(new_h))[no].astype(bool) | (contents > BUCKET_CONTENTS)
    verdict = np.where(~new, REPEAT, np.where(contents > 1, REFINE, KEEP))
    verdict = np.where(hot, SINGLE, verdict).astype(np.uint8)
    back = np.empty(len(e), np.uint8)
    back[order] = verdict
    cuts = np.cumsum([0, *map(len, parts)])
    return _pack([(bucket, k, 0, back[a:b].tobytes(), b"") for k, a, b in zip(groups, cuts, cuts[1:]) if back[a:b].any()], ASK)


def _ask(buckets: int, length: int):
    """Runs to refine and single strings to compare go to their buckets, what is known to be repeated stays (bucket -1 - g)."""

    def run(docs: pa.Table, told: pa.Table) -> pa.Table:
        if not docs.num_rows:
            return _pack([], ASK)
        group, g = analyse(docs, buckets, length), docs.column(GROUP)[0].as_py()
        verdict = np.zeros(len(group.entries), np.uint8)
        for b, v in zip(told.column("bucket").to_pylist(), told.column("head").to_pylist()):
            verdict[group.cuts[b] : group.cuts[b + 1]] = np.frombuffer(v, np.uint8)
        named = group.firsts >= 0
        gone = np.concatenate([group.repeats, group.firsts[(verdict == REPEAT) & named]])
        # Repeats of a hot bucket are repeats all the same: their content came earlier in this very group.
        out = [(-1 - g, g, 0, np.stack([group.runs.first[gone], group.runs.last[gone] + 1], axis=1).astype("<i8").tobytes(), b"")]

        some = group.firsts[(verdict == REFINE) & named]
        where = ((group.runs.h[some] * U(0x9E3779B97F4A7C15)) >> U(33)) % U(buckets)
        order = np.lexsort((some, where))
        some, where = some[order], where[order]
        first, last = group.runs.first[some], group.runs.last[some]
        head = np.zeros(len(some), RUN)
        head["h"], head["doc"], head["at"], head["strings"] = group.runs.h[some], group.doc[some], first, last - first + 1
        cuts = np.flatnonzero(np.concatenate([[True], where[1:] != where[:-1], [True]])) if len(some) else np.zeros(1, np.int64)
        raw = group.data
        for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
            body = b"".join(raw[x : y + length].tobytes() for x, y in zip(first[a:b].tolist(), last[a:b].tolist()))
            out.append((int(where[a]), g, 1, head[a:b].tobytes(), body))

        some = np.concatenate([group.firsts[(verdict == SINGLE) & named], group.single])
        if len(some):
            sizes = group.runs.last[some] - group.runs.first[some] + 1
            at = np.repeat(group.runs.first[some] - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes) + np.arange(sizes.sum())
            at.sort()
            one = np.zeros(len(at), STRING)
            doc = group.ids[np.searchsorted(group.offsets, at, side="right") - 1]
            for i in range(0, len(at), BLOCK):
                pos = at[i : i + BLOCK]
                lo, hi = int(pos[0]), int(pos[-1]) + length
                if hi - lo > 8 * BLOCK:  # scattered: hash each string by itself
                    both = [string_hashes(gram_hashes(raw[x : x + length])[1], np.zeros(1, np.int64), length) for x in pos.tolist()]
                    one["x"][i : i + BLOCK], one["y"][i : i + BLOCK] = (np.concatenate(h) for h in zip(*both))
                else:
                    one["x"][i : i + BLOCK], one["y"][i : i + BLOCK] = string_hashes(gram_hashes(raw[lo:hi])[1], pos - lo, length)
            one["doc"], one["at"] = doc, at
            order = np.lexsort((one["at"], one["y"], one["x"]))
            one = one[order]
            new = np.concatenate([[True], (one["x"][1:] != one["x"][:-1]) | (one["y"][1:] != one["y"][:-1])])
            again = one["at"][~new]
            out.append((-1 - g, g, 0, np.stack([again, again + 1], axis=1).astype("<i8").tobytes(), b""))
            one = one[new]
            where = (one["x"] >> U(33)) % U(buckets)
            order = np.argsort(where, kind="stable")
            one, where = one[order], where[order]
            cuts = np.flatnonzero(np.concatenate([[True], where[1:] != where[:-1], [True]]))
            out += [(int(where[a]), g, 2, one[a:b].tobytes(), b"") for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist())]
        return _pack(out, ASK)

    return run


def _later(group_keys: tuple[np.ndarray, ...], doc: np.ndarray, g: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Indices of all but the earliest of equal keys."""
    order = np.lexsort((at, g, doc, *group_keys))
    same = np.ones(len(order), bool)
    for k in group_keys:
        s = k[order]
        same &= np.concatenate([[False], s[1:] == s[:-1]])
    return order[same]


def _refine_runs(length: int):
    def run(table: pa.Table) -> pa.Table:
        bucket = table.column("bucket")[0].as_py()
        if bucket < 0:
            return table
        rows = list(zip(*(table.column(c).to_pylist() for c in ("g", "kind", "head", "body"))))
        gone: list[tuple[np.ndarray, np.ndarray]] = []
        if runs := [(g, np.frombuffer(head, RUN), body) for g, kind, head, body in rows if kind == 1]:
            head = np.concatenate([h for _, h, _ in runs])
            g = np.repeat(np.array([x for x, _, _ in runs]), [len(h) for _, h, _ in runs])
            data = np.frombuffer(b"".join(body for *_, body in runs), np.uint8)
            sizes = head["strings"].astype(np.int64) + length - 1
            starts = np.cumsum(sizes) - sizes
            # Equal strings have equal anchors: whole first buckets are refined, a few at a time.
            order = np.argsort(head["h"], kind="stable")
            h, done = head["h"][order], np.cumsum(sizes[order])
            edges = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
            lot = (done[edges] - sizes[order][edges]) // REFINED
            cuts = [*edges[np.concatenate([[True], lot[1:] != lot[:-1]])].tolist(), len(h)]
            for a, b in zip(cuts, cuts[1:]):
                some = order[a:b]
                size = sizes[some]
                last = np.cumsum(size)
                piece = data[np.repeat(starts[some] - (last - size), size) + np.arange(last[-1])]
                pointer = refine(piece, np.repeat(last, size), length)
                at = np.flatnonzero(pointer >= 0)
                of = np.searchsorted(last, at, side="right")
                pos = head["at"][some][of] + at - (last - size)[of]
                owner = g[some][of]
                later = _later((pointer[at],), head["doc"][some][of], owner, pos)
                gone.append((owner[later], pos[later]))
        if ones := [(g, np.frombuffer(head, STRING)) for g, kind, head, _ in rows if kind == 2]:
            one = np.concatenate([h for _, h in ones])
            g = np.repeat(np.array([x for x, _ in ones]), [len(h) for _, h in ones])
            later = _later((one["x"], one["y"]), one["doc"], g, one["at"])
            gone.append((g[later], one["at"][later]))
        if not gone:
            return _pack([], ASK)
        g, pos = (np.concatenate(x) for x in zip(*gone))
        order = np.lexsort((pos, g))
        g, pos = g[order], pos[order]
        head = np.flatnonzero(np.concatenate([[True], (g[1:] != g[:-1]) | (pos[1:] != pos[:-1] + 1)])) if len(g) else np.zeros(0, np.int64)
        tail = np.concatenate([head[1:], [len(g)]]) - 1 if len(g) else head
        pairs, owner = np.stack([pos[head], pos[tail] + 1], axis=1).astype("<i8"), g[head]
        return _pack([(bucket, k, 0, pairs[owner == k].tobytes(), b"") for k in np.unique(owner).tolist()], ASK)

    return run


def _cut(length: int, with_text: bool, schema: pa.Schema):
    def run(docs: pa.Table, told: pa.Table) -> pa.Table:
        if not docs.num_rows:
            return schema.empty_table()
        table = ordered(docs)
        data, offsets = bytes_of(table)
        n = len(data)
        change = np.zeros(n + 1, np.int64)
        for x in told.column("head").to_pylist():
            pairs = np.frombuffer(x, "<i8").reshape(-1, 2)
            np.add.at(change, pairs[:, 0], 1)
            np.add.at(change, pairs[:, 1] + length - 1, -1)
        gone = np.cumsum(change[:-1]) > 0
        total = np.concatenate([[0], np.cumsum(gone)])
        removed = total[offsets[1:]] - total[offsets[:-1]]
        spans, digests, kept = [], [], []
        for a, b, k in zip(offsets[:-1].tolist(), offsets[1:].tolist(), removed.tolist()):
            part = data[a:b]
            if k:
                lost = gone[a:b]
                spans.append(int(lost[0]) + int(np.count_nonzero(lost[1:] & ~lost[:-1])))
                part = part[~lost]
            else:
                spans.append(0)
            raw = part.tobytes()
            digests.append(hashlib.sha256(raw).hexdigest())
            kept.append(raw.decode("utf-8", "ignore") if with_text else None)
        made = {"n_bytes": pa.array(np.diff(offsets)), "n_removed": pa.array(removed), "n_spans": pa.array(spans, pa.int64()), "kept_sha256": pa.array(digests)}
        if with_text:
            made |= {"text": pa.array(kept, pa.string())} | ({"n_chars": pa.array(map(len, kept), pa.int64())} if "n_chars" in schema.names else {})
        return pa.Table.from_arrays([(made[f.name] if f.name in made else table.column(f.name)).cast(f.type) for f in schema], schema=schema)

    return run


def _deduplicated(documents: DataFrame, length: int, with_text: bool) -> DataFrame:
    from pyspark.sql.pandas.types import to_arrow_schema

    if length < 64:
        raise ValueError("length must be 64 bytes at least")
    spark = documents.sparkSession
    size = documents.agg(F.sum(F.octet_length("text"))).first()[0] or 0  # one number
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    groups = max(1, -(-size // GROUP_BYTES))
    rows = documents if with_text else documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    # Rows without an id may all have one text: their place spreads them. Rows with an id are dealt by what they hold.
    place = F.when(F.col("doc_id").isNull(), F.monotonically_increasing_id())
    rows = rows.withColumn("doc_id", F.col("doc_id").cast("long")).withColumn(GROUP, F.pmod(F.xxhash64("doc_id", "text", place), F.lit(groups)))
    docs = rows.repartition(parts, GROUP)  # used three times, exchanged once

    asked = docs.groupBy(GROUP).applyInArrow(_announce(groups, length), ASK_SQL)
    told = asked.groupBy("bucket").applyInArrow(_judge_contents, ASK_SQL)
    asked = docs.groupBy(GROUP).cogroup(told.groupBy("g")).applyInArrow(_ask(groups, length), ASK_SQL)
    told = asked.groupBy("bucket").applyInArrow(_refine_runs(length), ASK_SQL)
    fields = [T.StructField("doc_id", T.LongType()), *(T.StructField(n, T.LongType()) for n in ("n_bytes", "n_removed", "n_spans")), T.StructField("kept_sha256", T.StringType())]
    schema = T.StructType([f for f in rows.schema.fields if f.name != GROUP]) if with_text else T.StructType(fields)
    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in schema.fields])
    return docs.groupBy(GROUP).cogroup(told.groupBy("g")).applyInArrow(_cut(length, with_text, to_arrow_schema(schema)), schema)


def repeated_bytes(documents: DataFrame, length: int = LENGTH) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256) per row of `documents`.

    `length` is 64 at least. Texts are UTF-8 bytes, null is empty. Earlier means a smaller doc_id (null first), or the same document and an
    earlier start; rows that share a doc_id have a fixed order among themselves. Other columns are not read.
    """
    return _deduplicated(documents, length, with_text=False)


def remove_repeats(documents: DataFrame, length: int = LENGTH) -> DataFrame:
    """The rows of `documents`, all columns, with repeated bytes cut out of `text`; `n_chars`, if there, follows.

    Bytes of a character that is cut through are left out with it. Documents left empty stay, with an empty text.
    """
    return _deduplicated(documents, length, with_text=True)
