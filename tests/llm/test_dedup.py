"""Suffix dedup, SimHash classes and components against brute force."""

import hashlib
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from adapterlab.llm import shingles, simhash, suffixes

DOCS = "doc_id long, text string, lang string, source string, n_chars long, g long, k int"


def docs_of(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t), 7, 1) for i, t in rows], DOCS)


def brute_repeats(rows, length=100):
    seen, out = set(), {}
    for i, t in sorted(rows):
        raw = (t or "").encode()
        lost = np.zeros(len(raw), bool)
        for s in range(len(raw) - length + 1):
            x = raw[s : s + length]
            if x in seen:
                lost[s : s + length] = True
            seen.add(x)
        spans = int(np.count_nonzero(lost & ~np.concatenate([[False], lost[:-1]]))) if len(raw) else 0
        kept = bytes(b for b, gone in zip(raw, lost) if not gone)
        out[i] = (len(raw), int(lost.sum()), spans, hashlib.sha256(kept).hexdigest())
    return out


def words(r, n):
    return " ".join("".join(r.choice("abcdeé") for _ in range(r.randint(2, 8))) for _ in range(n))


def corpus(seed, n=60):
    r = random.Random(seed)
    line, passage = words(r, 9), words(r, 60)
    rows = []
    for i in range(n):
        kind = r.randrange(7)
        if kind == 0 and rows:
            rows.append((i, r.choice(rows)[1]))
        elif kind == 1:
            rows.append((i, f"{words(r, 5)} {passage} {words(r, 20)}"))
        elif kind == 2:
            rows.append((i, " ".join([line] * r.randint(1, 30))))
        elif kind == 3:
            rows.append((i, "x" * r.randint(0, 400)))
        else:
            rows.append((i, f"{line} {words(r, r.randint(1, 120))} {passage[r.randint(0, 200):]}"))
    return [*rows, (n, None), (n + 1, ""), (n + 2, "é" * 300), (n + 3, "e" + "é" * 300)]


@pytest.mark.parametrize(("group_bytes", "local", "bucket"), [(1 << 22, 64, 4096), (4000, 64, 4096), (3000, 1, 4096), (2500, 64, 1), (5000, 0, 0)])
def test_repeats_equal_brute_force(spark, monkeypatch, group_bytes, local, bucket):
    monkeypatch.setattr(suffixes, "GROUP_BYTES", group_bytes)
    monkeypatch.setattr(suffixes, "LOCAL_CONTENTS", local)
    monkeypatch.setattr(suffixes, "BUCKET_CONTENTS", bucket)
    rows = corpus(group_bytes + local)
    got = {r[0]: tuple(r[1:]) for r in suffixes.repeated_bytes(docs_of(spark, rows)).collect()}
    assert got == brute_repeats(rows)


@pytest.mark.parametrize("length", [64, 113, 128, 200, 333])
def test_repeats_of_other_lengths(spark, monkeypatch, length):
    monkeypatch.setattr(suffixes, "GROUP_BYTES", 6000)
    monkeypatch.setattr(suffixes, "LOCAL_CONTENTS", 2)
    r = random.Random(length)
    whole = [words(r, 140) for _ in range(4)]
    rows = []
    for i in range(50):
        t = list(r.choice(whole))
        for _ in range(r.randint(0, 6)):  # copies that differ in a byte here and there
            t[r.randrange(len(t))] = "#"
        rows.append((i, "".join(t)[r.randint(0, 50) :]))
    got = {x[0]: tuple(x[1:]) for x in suffixes.repeated_bytes(docs_of(spark, rows), length).collect()}
    assert got == brute_repeats(rows, length)


def test_altered_runs_never_have_equal_hashes():
    r = random.Random(9)
    for length in (100, 128, 200, 400):
        raw = bytes(r.randrange(97, 123) for _ in range(2 * length))
        base = suffixes.find_runs(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]), length)
        seen = set(zip(base.h.tolist(), base.c.tolist()))
        for at in range(length - 8, length + 8):
            other = raw[:at] + b"!" + raw[at + 1 :]
            runs = suffixes.find_runs(np.frombuffer(other, np.uint8), np.array([0, len(other)]), length)
            for a, b, h, c in zip(runs.first, runs.last, runs.h.tolist(), runs.c.tolist()):
                if a <= at < b + length:
                    assert (h, c) not in seen


def test_refine_tells_strings_apart():
    r = random.Random(5)
    piece = bytes(r.choice(b"ab") for _ in range(150))
    data = piece + piece[20:140] + bytes(r.choice(b"ab") for _ in range(130))
    ends = np.repeat([150, 270, 400], [150, 120, 130])
    pointer = suffixes.refine(np.frombuffer(data, np.uint8), ends)
    groups = {}
    for i, p in enumerate(pointer.tolist()):
        assert (p >= 0) == (ends[i] - i >= 100)
        if p >= 0:
            groups.setdefault(p, set()).add(data[i : i + 100])
    assert all(len(g) == 1 for g in groups.values())
    assert len(groups) == len({data[i : i + 100] for i in range(400) if ends[i] - i >= 100})


def test_removed_bytes_leave_the_text_and_other_columns(spark):
    r = random.Random(3)
    a = words(r, 40)
    rows = [(1, a), (2, f"{a} tail"), (3, None)]
    got = {r["doc_id"]: r for r in suffixes.remove_repeats(docs_of(spark, rows)).collect()}
    assert got[1]["text"] == a and got[2]["text"] == " tail" and got[2]["n_chars"] == 5 and got[3]["text"] == ""
    assert got[2]["lang"] == "en"
    assert got[2]["g"] == 7 and suffixes.remove_repeats(docs_of(spark, [])).columns == ["doc_id", "text", "lang", "source", "n_chars", "g", "k"]


def test_repeats_of_empty_table_and_repeated_ids(spark):
    assert suffixes.repeated_bytes(docs_of(spark, [])).count() == 0
    t = words(random.Random(1), 60)
    rows = suffixes.repeated_bytes(docs_of(spark, [(1, t), (1, t), (None, t), (None, None)])).collect()
    assert len(rows) == 4 and sum(r["n_removed"] > 0 for r in rows) == 2
    rows = suffixes.repeated_bytes(docs_of(spark, [(None, t)] * 40)).collect()  # spread over groups, whole in one of them
    assert len(rows) == 40 and sum(r["n_removed"] == 0 for r in rows) == 1 and {r["n_removed"] for r in rows} == {0, len(t.encode())}


def brute_classes(rows, distance=3):
    marks = [(i, simhash.fingerprint(t)) for i, t in rows]
    root = {i: i for i, _ in rows}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, a in marks:
        for j, b in marks:
            if (a ^ b).bit_count() <= distance:
                x, y = sorted((find(i), find(j)))
                root[y] = x
    return {i: (f"{m:016x}", find(i)) for i, m in marks}


def slow_fingerprint(text):
    import re

    import xxhash

    parts = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    shingles = [" ".join(parts[i : i + 3]) for i in range(len(parts) - 2)] or ([" ".join(parts)] if parts else [])
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_fingerprint():
    r = random.Random(2)
    for t in [None, "", " \t\n", "One", "one two", "A b\u00a0C d \x0b E", words(r, 200), "É è " * 5000]:
        assert simhash.fingerprint(t) == slow_fingerprint(t)


@pytest.mark.parametrize("segments", [1, 2, 4])
def test_near_duplicate_classes(spark, segments):
    r = random.Random(7)
    base = [words(r, 300) for _ in range(6)]
    rows = []
    for i in range(80):
        t = r.choice(base).split()
        for _ in range(r.randint(0, 3)):
            t[r.randrange(len(t))] = "changed"
        rows.append((i, " ".join(t)))
    rows += [(100, None), (101, ""), (102, "  "), (103, "x"), (104, "X")]
    distance = 3 if segments > 1 else 1
    got = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in simhash.near_duplicates(docs_of(spark, rows), distance, segments=segments).collect()}
    assert got == brute_classes(rows, distance)
    assert got[101][1] == 100 and got[104][1] == 103


def test_links_equal_all_pairs(spark):
    r = random.Random(9)
    bits = {0, (1 << 63) - 1}
    for _ in range(40):
        x = r.getrandbits(64)
        bits.add(x)
        for _ in range(6):
            y = x
            for _ in range(r.randint(1, 4)):
                y ^= 1 << r.randrange(64)
            bits.add(y)
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    rows = [(k, signed(b)) for k, b in enumerate(sorted(bits))]
    got = {(x.a, x.b) for x in simhash.near_links(spark.createDataFrame(rows, "rep long, bits long")).collect()}
    order = sorted(bits)
    assert got == {(i, j) for i in range(len(order)) for j in range(i + 1, len(order)) if (order[i] ^ order[j]).bit_count() <= 3}


def test_components_of_a_long_chain_and_a_star(spark):
    links = [(i, i + 1) for i in range(50)] + [(1000, 1001 + i) for i in range(40)] + [(2005, 2001), (2005, 2009)]
    got = {x.node: x.root for x in simhash.components(spark.createDataFrame(links, "a long, b long")).collect()}
    want = {i: 0 for i in range(1, 51)} | {1001 + i: 1000 for i in range(40)} | {2005: 2001, 2009: 2001}
    assert got == want


def test_representatives(spark):
    rows = [(5, "a b c d"), (3, "A b c d"), (None, "a b c d"), (9, "other words here now"), (9, "other words here now")]
    kept = shingles.keep_one_of_similar(docs_of(spark, rows)).select("doc_id", "lang", F.col("k")).collect()
    assert sorted(r["doc_id"] for r in kept if r["doc_id"] is not None) == [3, 9] and len(kept) == 3
    assert simhash.near_duplicates(docs_of(spark, [])).count() == 0
