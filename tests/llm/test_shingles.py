"""Near duplicates by shingle similarity against all pairs."""

import random

import pytest

from adapterlab.llm import shingles

import corpus_pipeline


def five_words(text):
    w = (text or "").lower().split()
    return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def brute(rows):
    """Component of each (id, text), named by its smallest (id, text)."""
    keys = sorted({(i, t or "") for i, t in rows})
    root = {k: k for k in keys}

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    sets = [(k, five_words(k[1])) for k in keys]
    for i, a in sets:
        for j, b in sets:
            if len(a & b) * 5 >= 4 * len(a | b):
                x, y = sorted((find(i), find(j)))
                root[y] = x
    return {k: find(k) for k in keys}


def rows_of(seed=3):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(4))
    line = " ".join(word() for _ in range(30))
    base = [" ".join(word() for _ in range(r.choice([6, 40, 150]))) for _ in range(8)]
    rows = []
    for i in range(160):
        t = r.choice(base).split()
        for _ in range(r.randint(0, 1 + len(t) // 30)):
            t[r.randrange(len(t))] = word()
        rows.append((i, f"{' '.join(t)} {line if i % 3 == 0 else ''}"))
    return [*rows, (200, None), (201, ""), (202, "one"), (203, "One "), (7, rows[8][1]), (7, "another text of that id"), (204, " \n"), (5, rows[5][1])]


@pytest.mark.parametrize("common,cell,first", [(50_000, 4096, 4), (0, 7, 1)])
def test_lightly_edited_copies_form_groups(spark, monkeypatch, common, cell, first):
    monkeypatch.setattr(shingles, "COMMON", common)
    monkeypatch.setattr(shingles, "CELL", cell)
    monkeypatch.setattr(shingles, "FIRST", first)
    rows = rows_of()
    docs = spark.createDataFrame([*rows, (None, "x"), (None, "x")], "doc_id long, text string")
    want = brute(rows)
    left = corpus_pipeline.near_duplicates(spark, docs, "").collect()
    kept = sorted((x.doc_id, x.text or "") for x in left if x.doc_id is not None)
    assert kept == sorted(set(want.values())) and len(kept) > 12 and len(left) == len(kept) + 2
    if cell == 7:
        return
    by = {}
    for x in shingles.similar_texts(docs).collect():
        by.setdefault(x.component, set()).add(x.doc_id)
    groups = {}
    for (i, t), r in want.items():
        groups.setdefault(r, {}).setdefault(t, i)
    assert len(by) == len(groups) and sorted(map(min, by.values())) == sorted(min(g.values()) for g in groups.values())


def test_groups_do_not_need_neighbours_or_fingerprints(spark, monkeypatch):
    """What is exact is the last step; without candidates from the others the groups are the same."""
    rows = rows_of(5)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    monkeypatch.setattr(shingles, "near_links", lambda classes: classes.select("rep", "rep").toDF("a", "b").where("a < b"))
    monkeypatch.setattr(shingles, "_neighbours", lambda rows: rows.select("node", "node").toDF("a", "b").where("a < b"))
    kept = sorted((x.doc_id, x.text or "") for x in shingles.keep_one_of_similar(docs).collect())
    assert kept == sorted(set(brute(rows).values()))


def test_range_counts_never_reject_similar_sets():
    r = random.Random(2)
    import numpy as np

    for n in (1, 5, 40, 3000):
        a = np.unique(np.array([r.getrandbits(64) for _ in range(n)], np.uint64))
        for lost in range(0, n // 5 + 1, max(1, n // 20)):
            b = a[lost:]
            if shingles.similar(a, b):
                assert shingles.may_be_similar(shingles.profile(a), shingles.profile(b))
    for n, m in ((400, 400), (5000, 4100), (33_000, 32_000)):
        a, b = (np.unique(np.array([r.getrandbits(64) for _ in range(k)], np.uint64)) for k in (n, m))
        assert not shingles.may_be_similar(shingles.profile(a), shingles.profile(b))
    assert not len(shingles.profile(np.arange(300, dtype=np.uint64)))


def test_a_large_group_of_near_copies_is_tied_by_few_pairs(spark, monkeypatch):
    """Copies with up to a quarter of the edits that part them from each other, not from the text they come from."""
    r = random.Random(5)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(5))
    base, rows = [word() for _ in range(150)], []
    for i in range(300):
        t = list(base)
        for at in r.sample(range(150), i % 6):
            t[at] = word()
        rows.append((i, " ".join(t)))
    met = []
    decided = shingles._both
    monkeypatch.setattr(shingles, "_both", lambda pairs, of, column: met.append(pairs.count()) or decided(pairs, of, column))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    left = corpus_pipeline.near_duplicates(spark, docs, "").collect()
    assert sorted((x.doc_id, x.text) for x in left) == sorted(set(brute(rows).values()))
    assert sum(met) < 6000, met


def test_the_last_step_alone_gives_the_same_groups(spark, monkeypatch):
    rows = rows_of(6)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    monkeypatch.setattr(shingles, "_met", lambda rows, shifts: rows.select("node", "node").toDF("a", "b").where("a < b"))
    kept = sorted((x.doc_id, x.text or "") for x in shingles.keep_one_of_similar(docs).collect())
    assert kept == sorted(set(brute(rows).values()))


def test_a_bucket_in_many_partitions_has_one_first_text(spark):
    """Each text meets the same one, however the rows are dealt; a first text for each partition leaves the group in parts."""
    rows = spark.createDataFrame([(1, i, 100, i // 8, i) for i in range(400)], "token long, node long, n int, pos int, root long")
    kept = {k: spark.conf.get(k) for k in ("spark.sql.shuffle.partitions", "spark.sql.adaptive.coalescePartitions.enabled")}
    try:
        for k, v in zip(kept, ("16", "false")):
            spark.conf.set(k, v)
        pairs = [tuple(x) for x in shingles._hubs(rows).collect()]
    finally:
        for k, v in kept.items():
            spark.conf.set(k, v)
    assert len(pairs) == 399 and len(set.intersection(*map(set, pairs))) == 1
