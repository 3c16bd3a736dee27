"""Scores of the learnt operators against plain versions that go word by word and tree by tree, on whole tables."""

import math

import duckdb
import numpy as np

from graphsplit.llm import quality, storage, toxicity

DIR = "/root/testdata/sf0.01"


def plain_hits(lexicon, folded):
    """Longest term that begins each word, unless a phrase that begins at or before the word reaches the term's end."""
    starts, at = [], 0
    for w in folded.split():
        at += 1
        starts.append((at, w))
        at += len(w)
    excused = [(a, a + len(p)) for a, _ in starts for p in lexicon.exceptions if folded.startswith(p, a)]
    total = 0.0
    for a, w in starts:
        n = max((k for k in range(1, len(w) + 1) if w[:k] in lexicon.terms), default=0)
        if n and not any(b <= a and a + n <= e for b, e in excused):
            total += lexicon.terms[w[:n]]
    return total, len(starts)


def test_toxicity_scores_equal_plain_matching(spark):
    docs = storage.table(spark, DIR, "documents").select("doc_id", "text")
    lexicon = toxicity.train(docs, storage.table(spark, DIR, "labels"))
    assert lexicon.terms
    a, b, c = lexicon.coefficients
    texts = dict(duckdb.sql(f"select doc_id, text from '{DIR}/documents.parquet'").fetchall())
    got = toxicity.op10_toxicity(spark, DIR).collect()
    assert sorted(r.doc_id for r in got) == sorted(texts)
    some = 0
    for r in got:
        total, n = plain_hits(lexicon, toxicity.fold(texts[r.doc_id]))
        want = 1 / (1 + math.exp(-(a + b * math.log1p(total) + c * min(3.0, 20.0 * total / (n + 20)))))
        assert math.isclose(r.score, want, rel_tol=1e-9, abs_tol=1e-12) and r.predicted == int(want >= toxicity.THRESHOLD)
        some += total > 0
    assert some


def test_lexicon_does_not_see_held_out_labels(spark):
    docs, labels = storage.table(spark, DIR, "documents"), storage.table(spark, DIR, "labels")
    turned = labels.selectExpr("doc_id", "quality", "case when crc32(cast(cast(doc_id as string) as binary)) % 4 = 2 then 1 - toxic else toxic end as toxic")
    assert toxicity.train(docs, labels) == toxicity.train(docs, turned)


def test_anomaly_scores_equal_a_walk_through_each_tree():
    rng = np.random.default_rng(8)
    rows = np.r_[rng.normal(size=(300, 5)), np.repeat(rng.normal(size=(1, 5)), 40, axis=0), np.zeros((20, 5))]  # with ties
    forest = quality.IsolationForest(rows, trees=20, tree_rows=64, depth=6)

    def depth(t, x):
        node = level = 0
        while forest.axis[t, node] >= 0:
            node = 2 * node + (2 if x[forest.axis[t, node]] >= forest.at[t, node] else 1)
            level += 1
        left = forest.path[t, node] - level  # what the rows left in a leaf would take
        assert left >= 0 and (level == forest.depth or left == 0 or forest.axis[t, node] < 0)
        return forest.path[t, node]

    usual = 2 * sum(1 / i for i in range(1, 64)) - 2 * 63 / 64
    got = forest.score(rows)
    for x, score in zip(rows, got, strict=True):
        mean = sum(depth(t, x) for t in range(20)) / 20
        assert math.isclose(score, 2 ** (-mean / forest.usual), rel_tol=1e-9)
    assert math.isclose(forest.usual, usual, rel_tol=0.01)


def test_verdict_follows_score_and_rules(spark):
    docs, labels = storage.table(spark, DIR, "documents"), storage.table(spark, DIR, "labels")
    judged = quality.judge(docs, labels).toPandas()
    refused = judged[~judged.base_failed & ~judged.kept].anomaly
    assert len(judged) == docs.count() and not judged[judged.base_failed].kept.any()
    assert refused.min() > judged[judged.kept].anomaly.max()
    marks = duckdb.sql(f"select doc_id, quality from '{DIR}/labels.parquet'").df().merge(judged, on="doc_id")
    assert 1 - marks[marks.quality == 0].kept.mean() >= 0.9 and marks[marks.quality == 1].kept.mean() >= 0.9


def test_forest_and_threshold_come_from_all_rows(spark):
    rng, rows = np.random.default_rng(9), []
    for i in range(7000):
        w = [f"w{x}" for x in rng.integers(0, 60, int(rng.integers(25, 90)))]
        if i % 7 == 0:
            w[: int(rng.integers(1, 5))] = ["#|"] * 3
        rows.append((i, " ".join(w)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 7 > 0 or i % 3 == 0), 0) for i in range(7000)] * 2, "doc_id long, quality int, toxic int")
    judged = quality.judge(docs, labels).toPandas().sort_values("doc_id")
    passed = judged[~judged.base_failed]
    forest = quality.IsolationForest.over(quality.rule_statistics(docs.repartition(5)).where(f"doc_id in ({','.join(map(str, passed.doc_id))})"))
    x = quality.features({c: passed[c].to_numpy() for c in quality.COUNTED})
    assert forest.rows == len(passed) > 6500
    for t in range(0, quality.TREES, 9):
        leaves, n = np.unique(forest.reached(t, x, forest.depth), return_counts=True)
        level = np.floor(np.log2(leaves + 1))
        assert np.allclose(forest.path[t, leaves], level + quality.mean_depth(n))  # leaves count every row
        a = forest.axis[t, 0]
        assert x[:, a].min() < forest.at[t, 0] < x[:, a].max()
    assert np.allclose(passed.anomaly, forest.score(x), atol=1 / quality.SCORE_STEPS)  # however rows are dealt
    good = ((passed.doc_id % 7 > 0) | (passed.doc_id % 3 == 0)).to_numpy()
    s = passed.anomaly.to_numpy()
    balance = lambda refused: refused[~good].mean() - refused[good].mean()
    assert math.isclose(balance(~passed.kept.to_numpy()), max(balance(s > at) for at in np.unique(s)), abs_tol=1e-12)  # the best of all labelled rows
