import itertools

import numpy as np

from blockforest.llm.language import UNKNOWN, fit_model, label_languages, op9_script_viterbi, script_of, viterbi


def test_held_out_accuracy(spark, sf):
    got = {r.doc_id: r for r in op9_script_viterbi(spark, sf).collect()}
    rows = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang").collect()
    hits = [got[r.doc_id].lang_pred == r.lang for r in rows if got[r.doc_id].held_out]
    print("held-out accuracy", np.mean(hits), len(hits))
    assert len(got) == len(rows) and np.mean(hits) > 0.97
    assert all(0 <= r.score <= 1 for r in got.values())


def test_viterbi_is_best():
    rng = np.random.default_rng(2)
    for _ in range(40):
        sizes = rng.integers(0, 6, 5)
        bound = np.concatenate([[0], np.cumsum(sizes)])
        s = rng.normal(size=(bound[-1], 3)) * 3
        tags = viterbi(s, bound, 2.0)
        for a, b in zip(bound, bound[1:], strict=False):
            value = lambda p: sum(s[a + i, t] for i, t in enumerate(p)) - 2.0 * sum(x != y for x, y in zip(p, p[1:], strict=False))  # noqa: B023, E731
            if b > a:
                assert abs(value(tags[a:b].tolist()) - max(map(value, itertools.product(range(3), repeat=b - a)))) < 1e-9


def test_mixed_text_and_edges(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = fit_model(docs)
    first = {r.lang: r.text for r in docs.groupBy("lang").agg({"text": "max"}).withColumnRenamed("max(text)", "text").collect()}
    mixed = first["de"][:400] + "\n" + first["es"][:900]
    df = spark.createDataFrame([(1, mixed), (2, None), (3, ""), (4, "12 !? 34"), (5, "¿… — 🤖"), (None, first["fr"][:300]), (1, mixed), (6, "the of and " * 40_000)], "doc_id long, text string").selectExpr("*", "'q' as lang", "1 as id")
    out = label_languages(df, model).collect()
    by = {r.doc_id: r for r in out}
    assert [s.lang for s in by[1].spans] == ["de", "es"] and by[1].lang_pred == "es" and 0.5 < by[1].score < 0.9
    assert abs(by[1].spans[1].start - 401) < 40
    assert {by[i].lang_pred for i in (2, 3, 4, 5)} == {UNKNOWN} and by[None].lang_pred == "fr" and by[6].lang_pred == "en"
    assert label_languages(df.limit(0), model).count() == 0
    nothing = fit_model(df.limit(0))
    assert {r.lang_pred for r in label_languages(df, nothing).collect()} == {UNKNOWN}
    text = "aΩж中".encode()
    assert len(set(script_of(np.frombuffer(text, np.uint8), np.array([0, 1, 3, 5])).tolist())) == 4


def test_no_language_is_dropped(spark):
    import pytest

    rows = [(i, f"word{chr(97 + i % 26)} text", f"l{i:03d}") for i in range(6)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    assert sorted(fit_model(df, max_languages=6).languages) == [r[2] for r in rows]
    with pytest.raises(ValueError, match="max_languages"):
        fit_model(df, max_languages=5)
