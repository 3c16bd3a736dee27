"""The pipeline's stages, each on its predecessor's output."""

import collections

import corpus_pipeline
from graphsplit.llm import storage

DIR = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = storage.table(spark, DIR, "documents")
    first = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
    seen = {}
    for name, stage in corpus_pipeline.STAGES:
        docs = storage.spill(stage(spark, docs, DIR), name)
        seen[name] = docs.toPandas()
        if name != corpus_pipeline.STAGES[-1][0]:
            assert docs.columns == list(corpus_pipeline.COLUMNS)
    assert 0 < len(seen["toxicity"]) <= len(first)
    kept = seen["ngram_jaccard_join"]
    grams = {}
    for i, t in zip(kept.doc_id, kept.text, strict=True):
        w = t.encode().lower().split()
        grams[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} or {tuple(w)}
    for a in grams:
        for b in grams:
            if a < b:
                assert 10 * len(grams[a] & grams[b]) < 8 * len(grams[a] | grams[b])
    windows = collections.Counter()
    for t in kept.text:
        w = t.encode().split()
        windows.update(tuple(w[i : i + 35]) for i in range(len(w) - 34))
    after = dict(zip(seen["substring_dedup"].doc_id, seen["substring_dedup"].text, strict=True))
    for i, t in zip(kept.doc_id, kept.text, strict=True):
        w = t.encode().split()
        gone = {j for i2 in range(len(w) - 34) if windows[tuple(w[i2 : i2 + 35])] > 1 for j in range(i2, i2 + 35)}
        assert after[i] == (b" ".join(x for j, x in enumerate(w) if j not in gone).decode() if gone else t)
    clean = seen["secret_scan"]
    assert (clean.text.str.len() == clean.n_chars).all() and len(clean) == len(kept)
    packed = seen["best_fit_packing"]
    assert set(packed.doc_id) == set(kept.doc_id) and packed.groupby("sequence_id").length.sum().max() <= 2048


def test_nulls_repeats_clashing_columns_and_an_empty_table(spark):
    long = " ".join(f"word{i}" for i in range(60))
    rows = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, long, "en", "a", 9), (3, long, "en", "a", 9), (4, long, None, None, None), (None, "a text without an id", "en", "b", 20), (5, "password = hunter2hunter2hunter2", "en", "b", 1)]
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    docs = spark.createDataFrame([(*r, "x", 1.0) for r in rows], schema + ", mark string, toxic_score double")
    for name, stage in corpus_pipeline.STAGES:
        docs = storage.spill(stage(spark, docs, DIR), name)
        if name != corpus_pipeline.STAGES[-1][0]:
            assert docs.columns == list(corpus_pipeline.COLUMNS)
    found = {r.doc_id for r in docs.collect()}
    assert found == {1, 2, 3, 5, None}
    empty = spark.createDataFrame([], schema)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, DIR).count() == 0
