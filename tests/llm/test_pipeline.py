from pyspark.sql import functions as F

import corpus_pipeline as cp
from blockforest.llm import pieces

from .test_near_dedup import brute as duplicate_groups
from .test_secrets import brute as base_secrets


def windows(text):
    from .test_licenses import words

    w = words(text)
    return {tuple(w[i : i + min(10, len(w))]) for i in range(len(w) - min(10, len(w)) + 1)} if w else set()


def test_stages_against_brute_force(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    before = {r.doc_id: r.text for r in docs.collect()}
    for name, stage in cp.STAGES:
        out = stage(spark, docs, tiny).cache()
        after = {r.doc_id: r.text for r in out.collect()}
        if name == "quality":
            assert 0.6 * len(before) < len(after) < len(before)
        if name == "near duplicates":
            assert set(after) == {i for i, (_, _, kept) in duplicate_groups(before.items(), 5).items() if kept}
        if name == "decontamination":
            bench = set().union(*(windows(r.text) for r in spark.read.parquet(f"{tiny}/benchmark.parquet").collect()))
            assert set(after) == {i for i, t in before.items() if not windows(t) & bench}
        if name == "secrets":
            assert set(after) == set(before)
            assert all(base_secrets(t)[1] == "" for t in after.values())
            assert all(after[i] == t for i, t in before.items() if base_secrets(t)[1] == "")
        if name == "pieces":
            model = pieces.load_model()
            assert after == before and all(model.decode(r.pieces) == r.text for r in out.collect())
        else:
            assert out.columns == cp.COLUMNS
        docs, before = out, after


def test_run_on_odd_rows(spark, tiny, tmp_path):
    odd = spark.read.parquet(f"{tiny}/documents.parquet").limit(20)
    odd = odd.unionByName(odd.limit(3)).unionByName(odd.limit(1).select(F.lit(None).cast("long").alias("doc_id"), F.lit(None).cast("string").alias("text"), F.lit(None).cast("string").alias("lang"), F.lit(None).cast("string").alias("source"), F.lit(None).cast("long").alias("n_chars")))
    odd.write.parquet(str(tmp_path / "documents.parquet"))
    for t in ("labels", "benchmark"):
        spark.read.parquet(f"{tiny}/{t}.parquet").write.parquet(str(tmp_path / f"{t}.parquet"))
    kept = cp.run(spark, str(tmp_path)).select("doc_id").collect()
    assert len(kept) > 5 and len(kept) == len(set(kept))  # of repeated rows one stays
    spark.read.parquet(f"{tiny}/documents.parquet").limit(0).write.parquet(str(tmp_path / "none/documents.parquet"))
    for t in ("labels", "benchmark"):
        spark.read.parquet(f"{tiny}/{t}.parquet").write.parquet(str(tmp_path / f"none/{t}.parquet"))
    assert cp.run(spark, str(tmp_path / "none")).count() == 0
