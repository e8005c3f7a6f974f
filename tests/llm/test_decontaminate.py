import numpy as np

from blockforest.llm.decontaminate import OP6_SQL, TestSide, contamination, longest_matches, op6_suffix_search, pack, search

from .oracle import assert_same


def test_against_sql(spark, sf):
    out = op6_suffix_search(spark, sf)
    assert_same(out, sf, OP6_SQL)
    assert out.where("contaminated").count() > 5


def test_edges(spark):
    item = " ".join(f"q{i}" for i in range(14))
    bench = spark.createDataFrame([(1, item, "x"), (2, "Solo word", "x"), (3, None, "x"), (None, "w0 w1", "x"), (4, "...", "x")], "item_id long, text string, doc_id string")
    docs = spark.createDataFrame(
        [(1, "a " + item.upper() + " b"), (2, None), (3, ""), (4, "x solo--WORD solo word é"), (5, " ".join(item.split()[:9])), (6, "w0 w1"), (7, "pad " * 50_000 + item), (7, "pad " * 50_000 + item), (None, item)],
        "doc_id long, text string",
    )
    rows = contamination(docs, bench).collect()
    got = sorted((r.doc_id or 0, r.n_words, r.n_hit, tuple(r["items"])) for r in rows)
    assert got == [(0, 14, 14, (1,)), (1, 16, 14, (1,)), (2, 0, 0, ()), (3, 0, 0, ()), (4, 6, 4, (2,)), (5, 9, 0, ()), (6, 2, 0, ()), (7, 50_014, 14, (1,)), (7, 50_014, 14, (1,))]
    runs = {tuple(r)[1:] for r in longest_matches(docs, bench).where("doc_id in (1, 4)").collect()}
    assert runs == {(1, 0, 1, 14), (2, 0, 1, 2), (2, 0, 3, 2)}
    everything = lambda **o: sorted((repr(r.doc_id), r.n_words, r.n_hit, sorted(r["items"]), sorted(map(tuple, r.matches))) for r in contamination(docs, bench, **o).collect())
    assert everything(max_test_bytes=20) == everything()
    assert contamination(docs.limit(0), bench).count() == 0
    assert {r.n_hit for r in contamination(docs, bench.limit(0)).collect()} == {0}


def test_slices_and_clashing_names(spark, tiny):
    docs, bench = spark.read.parquet(f"{tiny}/documents.parquet"), spark.read.parquet(f"{tiny}/benchmark.parquet")
    odd = docs.selectExpr("doc_id", "text", "lang as id", "source as items", "n_chars as n_words", "'m' as matches", "1L as rn")
    odd = odd.unionAll(odd.where("doc_id % 3 = 0")).unionAll(odd.selectExpr("cast(null as long)", "text", "id", "items", "n_words", "matches", "rn"))
    rows = lambda n: sorted((repr(r.doc_id), r.n_words, r.n_hit, sorted(r["items"]), sorted(map(tuple, r.matches))) for r in contamination(odd, bench.unionAll(bench), max_test_bytes=n).collect())
    whole = rows(32 << 20)
    assert rows(6000) == whole and sum(r[2] for r in whole) > 0


def test_keys_of_many_words_keep_the_order():
    rng = np.random.default_rng(2)
    rows = rng.integers(0, 4, (300, 10)).astype(np.uint64)
    for bits in (21, 32):
        keys = pack(rows.T, bits)
        order = np.lexsort(keys.T[::-1])
        assert rows[order].tolist() == sorted(rows.tolist())
        assert search(keys[order], keys, False).tolist() == [sum(o < r for o in rows.tolist()) for r in rows.tolist()]
    assert TestSide([1], ["a b c d e f g h i j k"], 10).length.tolist() == [10, 10]
