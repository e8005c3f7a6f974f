import numpy as np

from blockforest.llm.quality import above_quantile, fit_bradley_terry, fit_from_labels, op1_bradley_terry, score_documents


def auc(score, y):
    order = np.argsort(score, kind="stable")
    rank = np.empty(len(y))
    rank[order] = np.arange(len(y))
    pos = y == 1
    return (rank[pos].sum() - pos.sum() * (pos.sum() - 1) / 2) / (pos.sum() * (~pos).sum())


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.1"
    got = {r.doc_id: r for r in op1_bradley_terry(spark, sf).collect()}
    rows = [(got[r.doc_id], r.quality) for r in spark.read.parquet(f"{sf}/labels.parquet").collect() if got[r.doc_id].held_out]
    y = np.array([q for _, q in rows])
    s = np.array([r.score for r, _ in rows])
    p = np.array([r.predicted for r, _ in rows])
    print("auc", auc(s, y), "accuracy", (p == y).mean(), "recall of 1", (p[y == 1]).mean(), "recall of 0", 1 - p[y == 0].mean())
    assert auc(s, y) > 0.95 and (p == y).mean() > 0.95 and p[y == 1].mean() > 0.97
    assert all((r.score >= 0.7) == (r.predicted == 1) and 0 <= r.score <= 1 for r in got.values())


def test_recovers_a_known_order():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(400, 3))
    true = x @ np.array([2.0, -1.0, 0.0])
    a, b = rng.integers(0, 400, 6000), rng.integers(0, 400, 6000)
    wins = rng.random(6000) < 1 / (1 + np.exp(true[b] - true[a]))
    r = fit_bradley_terry(x, np.where(wins, a, b), np.where(wins, b, a))
    assert np.corrcoef(r.raw(x), true)[0, 1] > 0.995


def test_all_labelled_documents_and_pairs_count(spark):
    from blockforest.llm import quality

    sf = "/root/testdata/sf0.001"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    rows = docs.join(labels, "doc_id").select("text", "quality").toArrow().combine_chunks()
    x, y = quality.features(rows["text"].combine_chunks()), rows["quality"].to_numpy()
    good, bad = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    want = fit_bradley_terry(x, np.repeat(good, len(bad)), np.tile(bad, len(good)))
    got = fit_from_labels(docs, labels)
    np.testing.assert_allclose(got.mean, want.mean, rtol=1e-9)
    np.testing.assert_allclose(got.scale, want.scale, rtol=1e-6)
    assert np.abs(got.weights - want.weights).max() < 0.01 * np.abs(want.weights).max()


def test_edges(spark):
    docs = spark.createDataFrame([(1, "good words here", "q"), (2, "bad%%% bad%%% bad%%%", "q"), (3, None, "q"), (4, "", "q"), (None, "x", "q"), (1, "good words here", "q"), (5, "w " * 90_000, "q")], "doc_id long, text string, y string")
    labels = spark.createDataFrame([(1, 1), (2, 0), (None, 1), (3, None), (77, 0)], "doc_id long, quality int")
    ranker = fit_from_labels(docs, labels)
    out = score_documents(docs, ranker).collect()
    assert len(out) == 7 and all(0 <= r.score <= 1 for r in out)
    by = {r.doc_id: r.score for r in out}
    assert by[1] > by[2] and by[3] == by[4]
    clash = docs.selectExpr("doc_id", "text", "y as lid", "y as sample_id", "y as x", "y as id")
    assert sorted(map(tuple, score_documents(clash, fit_from_labels(clash, labels)).collect()), key=repr) == sorted(map(tuple, out), key=repr)
    assert {r.score for r in score_documents(docs, fit_from_labels(docs, labels.limit(0))).collect()} == {0.7}
    assert score_documents(docs.limit(0), ranker).count() == 0
    assert above_quantile(score_documents(docs, ranker), 1.0).count() >= 1
