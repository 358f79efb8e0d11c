"""The pipeline's stages, each against what its operator says about the stage's own input."""

import random

from adapterlab.llm import decontaminate, shingles, suffixes

import corpus_pipeline


def test_stages_on_small_tables(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns = docs.columns
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, sf_dir)
        if k == 4:
            rows = out.toPandas()
            assert set(rows.doc_id) == {r.doc_id for r in docs.select("doc_id").collect()}
            assert rows.groupby("sequence_id").length.sum().max() <= 1024
            break
        assert out.columns == columns, name
        before = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
        after = {r.doc_id: r.text for r in out.select("doc_id", "text").collect()}
        assert set(after) <= set(before)
        if name == "near_duplicates":
            sets = {i: set(shingles.shingles(before[i]).tolist()) for i in before}
            alike = lambda a, b: len(a & b) * 5 >= 4 * len(a | b)
            assert not any(alike(sets[i], sets[j]) for i in after for j in after if i < j)
            assert all(any(alike(sets[i], sets[j]) for j in before if j < i) for i in set(before) - set(after))
        if name == "repeated_passages":
            assert set(after) == set(before)
            told = {r.doc_id: r.n_removed for r in suffixes.repeated_bytes(docs).collect()}
            assert all((before[i] == after[i]) == (told[i] == 0) for i in before)
        if name == "benchmark_leaks":
            leaks = decontaminate.find_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
            assert set(before) - set(after) == {r.doc_id for r in leaks.collect()}
        docs = spark.createDataFrame(out.collect(), docs.schema)


CLASHING = "doc_id long, text string, lang string, source string, n_chars long, g int, kept_id long, y int, score double, __row int, piece int, part int, item_id long, length int"


def test_stages_take_odd_rows(spark, sf_dir):
    """Null ids, null and empty texts, one very long text, repeated rows, and columns named like our own."""
    r = random.Random(1)
    long_text = " ".join("".join(r.choice("abcdefgh") for _ in range(5)) for _ in range(60_000))
    rows = [(1, None), (2, ""), (None, "without an id"), (None, None), (3, "same row here"), (3, "same row here"), (4, long_text), (5, long_text), (6, "\n \t"), (7, "ein Satz. " * 30)]
    docs = spark.createDataFrame([(i, t, None, "s", None, 1, 2, 3, 0.5, 4, 5, 6, 7, 8) for i, t in rows], CLASHING)
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, sf_dir)
        empty = stage(spark, docs.where("1 = 0"), sf_dir)
        assert empty.count() == 0, name
        if k < 4:
            assert out.columns == docs.columns == empty.columns and out.count() <= len(rows), name
    by = {x.doc_id: x for x in corpus_pipeline.near_duplicates(spark, docs, sf_dir).collect() if x.doc_id is not None}
    assert set(by) == {1, 3, 4, 7} and by[4].text == long_text and by[4].g == 1
    cut = {x.doc_id: x.text for x in corpus_pipeline.repeated_passages(spark, docs, sf_dir).collect() if x.doc_id is not None}
    assert cut[4] == long_text and cut[5] == "" and cut[3] == "same row here"
    assert corpus_pipeline.benchmark_leaks(spark, docs, sf_dir).count() == len(rows)
    assert corpus_pipeline.packing(spark, docs, sf_dir).count() >= len(rows)


def test_run_keeps_clean_documents(spark, sf_dir):
    rows = corpus_pipeline.run(spark, sf_dir).toPandas()
    assert len(set(rows.doc_id)) > 100 and random.Random(0)
