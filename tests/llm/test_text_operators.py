"""Packing, classifiers, decontamination, extraction, URL rules, chat and top-k."""

import json
import random
import zlib

import duckdb
import numpy as np
import pandas as pd
import pytest

from adapterlab.llm import chat, common, decontaminate, html, packing, quality, queries, topk, toxicity, urls


def tokenizer():
    return queries.tokenizer_file()


TEXTS = [None, "", "Hello  world's\n\n  fine 123\t", "é à ß ñ Ülı 你好", "<|endoftext|> x", "a\u00a0b\u2028c\x1cd\x85e", "x" * 5000, "word " * 3000]


def test_fast_tokens_equal_tokenizers():
    from tokenizers import Tokenizer

    slow, fast = Tokenizer.from_file(tokenizer()), packing.ByteBpe(tokenizer())
    for t in TEXTS:
        assert fast(t or "").tolist() == slow.encode(t or "", add_special_tokens=False).ids


def test_packing_round_trip(spark):
    from tokenizers import Tokenizer

    slow, r = Tokenizer.from_file(tokenizer()), random.Random(1)
    rows = [(i, t) for i, t in enumerate(TEXTS)] + [(100 + i, "some words here " * r.randint(1, 400)) for i in range(60)] + [(None, "x"), (100, "again")]
    df = spark.createDataFrame([(i, t, "q", 1) for i, t in rows], "doc_id long, text string, piece string, length int")
    got = packing.pack_documents(df, tokenizer(), keep_ids=True).toPandas()
    whole = {}
    for row in got[got.doc_id.notna() & (got.doc_id != 100)].sort_values(["doc_id", "piece"]).itertuples():
        assert zlib.crc32(row.ids) == row.ids_crc32 and row.length <= 1024 and len(row.ids) == 4 * row.length
        ids = whole.setdefault(int(row.doc_id), [])
        assert row.start == len(ids) and (row.piece == 0 or row.length == 1024)
        ids += np.frombuffer(row.ids, "<u4").tolist()
    assert whole == {i: [*slow.encode(t or "", add_special_tokens=False).ids, 2] for i, t in rows if i is not None and i != 100}
    for _, s in got.sort_values("offset").groupby("sequence_id"):
        assert s.offset.tolist() == [0, *s.length.cumsum().tolist()[:-1]] and s.length.sum() <= 1024
    assert got.sequence_id.nunique() <= -(-got.length.sum() // 1024) + 1
    assert packing.pack_documents(df.where("1 = 0"), tokenizer()).count() == 0


def test_plan_meets_small_optima():
    from itertools import combinations_with_replacement

    def fewest(sizes, cap):
        best, bins = len(sizes), []

        def place(i):
            nonlocal best
            if len(bins) >= best:
                return
            if i == len(sizes):
                best = len(bins)
                return
            for k in {b: k for k, b in enumerate(bins)}.values():
                if bins[k] + sizes[i] <= cap:
                    bins[k] += sizes[i]
                    place(i + 1)
                    bins[k] -= sizes[i]
            bins.append(sizes[i])
            place(i + 1)
            bins.pop()

        place(0)
        return best

    worse = total = 0
    for sizes in combinations_with_replacement([1, 2, 3, 4, 5, 7, 8, 9], 6):
        counts = {n: sizes.count(n) for n in set(sizes)}
        bins = packing.plan_bins(counts, 12)
        assert sum(b.copies * t for b in bins for n, t in b.items if n == 4) == counts.get(4, 0)
        assert all(sum(n * t for n, t in b.items) + b.free == 12 and b.free >= 0 for b in bins)
        assert all(sum(t for n, t in b.items if 3 * n > 12) <= 2 for b in bins)
        used, least = sum(b.copies for b in bins), fewest(sorted(sizes, reverse=True), 12)
        total += 1
        worse += used > least
        assert used <= least + 1
    assert worse <= 0.05 * total


def test_classifiers_learn_without_held_out_rows(spark):
    r = random.Random(4)
    vocabulary = ["".join(r.choice("abcdefghij") for _ in range(5)) for _ in range(200)]
    rows, labels = [], []
    for i in range(600):
        bad, loud = i % 4 == 0, i % 3 == 0
        t = [r.choice(vocabulary) for _ in range(80)]
        if bad:
            t[r.randrange(80)] = "zyxwv"
        text = " ".join(t)
        rows.append((i, text.upper() + "!!" if loud else text, "l", "s"))
        labels.append((i, int(not loud), int(bad)))
    rows += [(1000, None, "l", "s"), (1001, "", "l", "s"), (None, "abc", "l", "s")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, y string, score string")
    marks = spark.createDataFrame([*labels, (None, 1, 1), (5000, None, None)], "doc_id long, quality int, toxic int")
    tox = toxicity.score_toxicity(docs, toxicity.fit_toxicity(docs, marks)).toPandas()
    good = quality.score_quality(docs, quality.fit_quality(docs, marks)).toPandas()
    truth = pd.DataFrame(labels, columns=["doc_id", "quality", "toxic"])
    for got, label in ((tox, "toxic"), (good, "quality")):
        assert len(got) == len(rows) and got.score.between(0, 1).all()
        both = got.merge(truth, on="doc_id")
        assert ((both.predicted == both[label]) | ~both.held_out).mean() > 0.97
        assert (both.held_out == both.doc_id.map(lambda i: zlib.crc32(str(int(i)).encode()) % 5 == 0)).all()
    # Labels of held-out rows change nothing.
    flipped = spark.createDataFrame([(i, q if not common.is_held_out(i) else 1 - q, t if not common.is_held_out(i) else 1 - t) for i, q, t in labels], "doc_id long, quality int, toxic int")
    again = toxicity.fit_toxicity(docs, flipped)
    first = toxicity.fit_toxicity(docs, marks)
    assert np.allclose(again.weights, first.weights) and (again.buckets == first.buckets).all()
    none = toxicity.fit_toxicity(docs, marks.where("1 = 0"))
    assert toxicity.score_toxicity(docs, none).where("score between 0 and 1").count() == len(rows)
    assert quality.score_quality(docs.where("1 = 0"), quality.fit_quality(docs, marks.where("1 = 0"))).count() == 0


def test_forest_walk_equals_recursion():
    r = np.random.default_rng(0)
    x = r.normal(size=(500, 4))
    y = (x[:, 0] * x[:, 1] > 0).astype(int)
    f = quality.grow_forest(x, y, quality.QualityParams(trees=20))

    def walk(k, row):
        while f.left[k] != k:
            k = f.left[k] if row[f.feature[k]] <= f.cut[k] else f.right[k]
        return f.value[k]

    assert np.allclose(f.raw(x), [f.bias + sum(walk(t, row) for t in f.roots) for row in x])
    assert ((f.score(x) > 0.5) == y).mean() > 0.95


QUESTION = "A baker named Alice sells 12 boxes of 30 kg flour to Bob every week. If Alice gives Bob 5 boxes more, how many kg of flour does Bob then hold after 12 weeks of trade?"


def test_leaks_and_reparameterised_questions(spark):
    changed = QUESTION.replace("Alice", "Carol").replace("Bob", "Dan").replace("12", "17").replace("30", "45").replace("5 boxes", "9 boxes")
    mixed = QUESTION.replace("sells 12", "sells 3").replace("after 12", "after 9").replace("named Alice", "named Eve").replace("to Bob", "to Zed").replace("30", "12")
    clean = "The flour of the baker was sold to the town in the week before the war, and nobody kept a box of it."
    docs = [(1, f"Intro here. {QUESTION} More text follows."), (2, f"Other start.\n{changed}\nEnd."), (3, clean), (4, None), (5, ""), (6, mixed), (7, QUESTION.upper()), (8, QUESTION[:60]), (1, QUESTION)]
    d = spark.createDataFrame([(i, t, 1) for i, t in docs], "doc_id long, text string, item_id int")
    b = spark.createDataFrame([(10, QUESTION), (11, None), (12, "too short"), (13, "")], "item_id long, text string")
    got = decontaminate.find_leaks(d, b).toPandas()
    assert sorted(got.doc_id) == [1, 1, 2, 7] and set(got.item_id) == {10}
    assert got[got.doc_id == 2].changed_slots.iloc[0] > 5 and (got[got.doc_id == 1].changed_slots == 0).all()
    kept = decontaminate.drop_leaked(d, b)
    assert sorted(r.doc_id for r in kept.collect()) == [3, 4, 5, 6, 8] and kept.columns == d.columns
    assert decontaminate.find_leaks(d, b.where("1 = 0")).count() == 0 and decontaminate.find_leaks(d.where("1 = 0"), b).count() == 0


def test_leaks_equal_brute_force_on_plain_words(spark, monkeypatch):
    r = random.Random(8)
    voc = ["".join(r.choice("abcdefgh") for _ in range(4)) for _ in range(500)]
    items = [(i, " ".join(r.choice(voc) for _ in range(r.randint(5, 40)))) for i in range(12)]
    docs = []
    for i in range(80):
        t = [r.choice(voc) for _ in range(r.randint(0, 60))]
        if i % 2:
            w = items[i % 12][1].split()
            w = w[: max(1, int(len(w) * r.uniform(0.6, 1)))]
            t[5:5] = w
        docs.append((i, " ".join(t)))
    grams = lambda t: {tuple(t.split()[i : i + 5]) for i in range(len(t.split()) - 4)}
    want = {(d, i) for d, t in docs for i, q in items if grams(q) and len(grams(q) & grams(t)) >= 0.8 * len(grams(q))}
    monkeypatch.setattr(decontaminate, "CHUNK", 300)
    monkeypatch.setattr(decontaminate, "BITS", 4)  # nearly all windows reach the join
    got = decontaminate.find_leaks(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"))
    assert {(x.doc_id, x.item_id) for x in got.collect()} == want and want


PAGE = """<!DOCTYPE html><html><head><title>T, t.</title><style>p{}</style><script>var a="</p>";</script></head><body>
<nav><ul><li><a href="/a">Menu</a></li></ul></nav><div class="ad">Buy, now. Really cheap, yes.</div>
<div id="cookie-notice"><p>We use cookies, as all do. Accept?</p></div>
<article><h1>The head &amp; more</h1><p><b>One sentence, long   enough.<br><p>Second p<i>ar</i>t, with text. It goes on, and on.</p><p>Short</p>
<form><p>Your name, please.</p><input></form><ul><li>item, one</li></ul></article>
<section class="comments"><article class="comment"><p>I think, this is a long comment. Really, very long it is, isn't it?</p></article></section>
<aside><p>Side text, here. More of it, there.</p></aside><footer>&copy; me, now.</footer></body></html>"""


def test_main_text(spark):
    assert html.main_text(PAGE) == "The head & more One sentence, long enough. Second part, with text. It goes on, and on. Short item, one"
    cut = PAGE[: PAGE.index("Short")]
    assert html.main_text(cut).endswith("It goes on, and on.")
    for t in (None, "", "<", "<!--", "<script>x", "<p", "</p></p>", "<a b='"):
        assert html.main_text(t) in ("", "<")
    div = '<body><div class="page"><div class="menu">A, b. C, d.</div><div class="post"><h2>Head</h2><div>Text, that is long. And longer, still.</div><div>More text, as well.</div></div></div></body>'
    assert html.main_text(div) == "Head Text, that is long. And longer, still. More text, as well."
    deep = "<div>" * 3000 + "Words, here." + "</div>" * 3000
    assert html.main_text(deep) == "Words, here."
    rows = [(1, "u", PAGE, 5), (2, None, None, 5), (1, "u", PAGE, 5), (None, "v", "", 5)]
    got = html.extract_main_text(spark.createDataFrame(rows, "page_id long, url string, html string, text int")).collect()
    assert len(got) == 4 and all(r.n_chars == len(r.text) for r in got)
    assert html.extract_main_text(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_url_rules(spark):
    cases = {
        "http://A.Example.com/en/75?x": ("a.example.com", "/en/75", "example.com/en/7", "allow"),
        "https://example.com/en/6": ("example.com", "/en/6", "com/en/", "block"),
        "x://example.net/de/8#a": ("example.net", "/de/8", "example.net/de/8", "block"),
        "x://a.net/de/8": ("a.net", "/de/8", "net/de/", "allow"),
        "x://notexample.net/de/8": ("notexample.net", "/de/8", "net/de/", "allow"),
        "x://a.org/es": ("a.org", "/es", None, "allow"),
        "x://org?/es/": ("org", "", None, "allow"),
        "no-scheme.com/en/": ("", "", None, "allow"),
        "": ("", "", None, "allow"),
        "://com/en/": ("com", "/en/", "com/en/", "block"),
        "a://b://com/en/": ("b:", "//com/en/", None, "allow"),
        "x://.com/en/é": (".com", "/en/é", "com/en/", "block"),
    }
    rows = [(i, u, "h") for i, u in enumerate(cases)] + [(99, None, "h"), (0, next(iter(cases)), "h")]
    df = spark.createDataFrame(rows, "page_id long, url string, host string")
    got = urls.filter_urls(df, urls.task_rules(spark)).collect()
    by = {r.page_id: tuple(r[1:]) for r in got}
    assert len(got) == len(rows) and [by[i] for i in range(len(cases))] == list(cases.values()) and by[99] == ("", "", None, "allow")
    assert urls.filter_urls(df, urls.task_rules(spark).where("1 = 0"), default="block").where("verdict = 'block' and rule is null").count() == len(rows)
    assert urls.filter_urls(df.where("1 = 0"), urls.task_rules(spark)).count() == 0


def brute_chat(rows):
    groups = {}
    for c, t, role, text in rows:
        groups.setdefault(c, []).append((t is not None, t or 0, role or "unknown", text or ""))
    out = {}
    for c, turns in groups.items():
        turns.sort()
        for who in {s for _, _, s, _ in turns} - {"system"}:
            text, spans = "", []
            for _, _, s, t in turns:
                head = "<|start|>assistant\n" if s == who else "<|start|>system\n" if s == "system" else f"<|start|>user name={s}\n"
                body = t.replace("<|", "< |") + "<|end|>\n"
                if s == who:
                    spans.append((len(text) + len(head), len(text) + len(head) + len(body)))
                text += head + body
            out[(c, who)] = (text, spans)
    return out


def test_perspectives(spark):
    r = random.Random(6)
    rows = [(c, t, r.choice(["user", "assistant", "system", "amy", "bob"]), f"text {c} {t} é" * r.randint(0, 4)) for c in range(8) for t in range(r.randint(1, 9))]
    rows += [(50, t, ["user", "amy"][t % 2], f"<|end|> {t}") for t in range(300)]  # one long conversation
    rows += [(60, 0, None, "x"), (60, 0, None, "x"), (60, None, "user", None), (70, 0, "system", "only"), (None, 1, "user", "lost")]
    df = spark.createDataFrame([(*x, 1) for x in rows], "conv_id long, turn long, role string, text string, pid int")
    segments = chat.rotate_perspectives(df)
    got = {(x.conv_id, x.perspective): (x.text, [(s.start, s.end) for s in x.spans]) for x in chat.assemble(segments).collect()}
    assert got == brute_chat(rows)
    assert chat.rotate_perspectives(df.where("1 = 0")).count() == 0


def test_top_k_equals_brute_force(spark, monkeypatch):
    monkeypatch.setattr(topk, "ROWS", 32)
    monkeypatch.setattr(topk, "QUERIES", 4)
    monkeypatch.setattr(topk, "SHARE", 1)
    monkeypatch.setattr(topk, "SAMPLE", 50)
    r = np.random.default_rng(3)
    v = np.concatenate([r.normal(size=(300, 8)), np.repeat(r.normal(size=(1, 8)), 60, axis=0), np.zeros((5, 8))]).astype(np.float32)
    rows = [(i, [float(c) for c in x]) for i, x in enumerate(v)]
    bad = [(400, None), (450, [1.0] * 7 + [None]), (500, [float("nan")] * 8), (550, [float("inf")] * 8), (None, [1.0] * 8)]
    again = [(7, rows[7][1]), (7, rows[9][1]), (100, rows[100][1])]  # candidates like any other; a query counts once
    df = spark.createDataFrame([(*x, 1) for x in rows + bad + again], "vec_id long, embedding array<float>, rank int")
    got = [tuple(x) for x in topk.top_k(df).orderBy("query_id", "rank").collect()]
    w = np.floor(256 * v.astype(np.float64)).astype(np.int64)
    want = []
    for q in range(0, len(v), 50):
        order = sorted((-int(w[q] @ w[y]), x) for x, y in [*((x, x) for x in range(len(v))), (7, 7), (7, 9), (100, 100)] if x != q)[:5]
        want += [(q, k + 1, x, -s) for k, (s, x) in enumerate(order)]
    assert got == want
    few = topk.top_k(df.where("vec_id in (0, 1, 2)")).collect()
    assert len(few) == 2 and topk.top_k(df.where("1 = 0")).count() == 0


def test_bounds_leave_most_of_clustered_vectors_out(spark, monkeypatch):
    for name, value in (("ROWS", 32), ("ZONE", 4), ("QUERIES", 16), ("PIVOTS", 64)):
        monkeypatch.setattr(topk, name, value)
    r = np.random.default_rng(4)
    centres = r.normal(size=(64, 16))
    v = centres[r.integers(0, 64, 8000)] + 0.03 * r.normal(size=(8000, 16))
    v = (v / np.linalg.norm(v, axis=1)[:, None]).astype(np.float32)
    df = spark.createDataFrame([(i, [float(c) for c in x]) for i, x in enumerate(v)], "vec_id long, embedding array<float>")
    w = np.floor(256 * v.astype(np.float64)).astype(np.int64)
    got = [tuple(x) for x in topk.top_k(df, pivots=64).orderBy("query_id", "rank").collect()]
    want = []
    for q in range(0, len(v), 50):
        s = w @ w[q]
        s[q] = -(1 << 60)
        want += [(q, k + 1, int(x), int(s[x])) for k, x in enumerate(np.lexsort((np.arange(len(v)), -s))[:5])]
    assert got == want
    work = topk.search_work(df, pivots=64).first()
    assert work.pairs == 8000 * 160 and work.pairs_scored < 0.1 * work.pairs and work.annuli_scored < 0.1 * work.annuli


@pytest.mark.parametrize("name", sorted(queries.SQL))
def test_sql_twins(spark, sf_dir, name):
    got = queries.QUERIES[name](spark, sf_dir).toPandas()
    con = duckdb.connect()
    for t in ("conversations", "embeddings", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    want = con.execute(queries.SQL[name]).df()
    rows = lambda df: sorted(json.dumps(list(map(str, r))) for r in df[sorted(df.columns)].replace({np.nan: None}).itertuples(index=False))
    assert sorted(got.columns) == sorted(want.columns) and rows(got) == rows(want)
