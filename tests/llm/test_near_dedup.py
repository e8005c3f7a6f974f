import re

from blockforest.llm.near_dedup import near_duplicates, op4_circulant_minhash


def shingle_set(text, k):
    words = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate({c: c + 32 for c in range(65, 91)}))
    if not words:
        return frozenset()
    k = min(k, len(words))
    return frozenset(tuple(words[i : i + k]) for i in range(len(words) - k + 1))


def brute(rows, k, percent=80):
    sets = {i: shingle_set(t, k) for i, t in rows}
    ids, root = sorted(sets), {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            x, y = sets[a], sets[b]
            if x and y and 100 * len(x & y) >= percent * len(x | y):
                p, q = sorted((find(a), find(b)))
                root[q] = p
    return {i: (len(sets[i]), find(i), find(i) == i) for i in ids}


def test_against_all_pairs(spark, sf):
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in op4_circulant_minhash(spark, sf).collect()}
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    assert got == brute(rows, 4)
    assert sum(not k for _, _, k in got.values()) > 50


def test_chains_and_edge_cases(spark):
    words = [f"w{i}" for i in range(60)]
    rows = [(10 + s, " ".join(words[s : s + 50])) for s in range(0, 11, 2)]  # a chain: neighbours alike, ends not
    rows += [(1, None), (2, ""), (3, " \t\n"), (4, "one two"), (5, "ONE  two"), (6, "one"), (7, "x " * 30_000), (8, "X\n" * 30_000)]
    df = spark.createDataFrame([(i, t, "z", i) for i, t in rows] + [(None, "one two", "z", 0)], "doc_id long, text string, id string, n long")
    got = near_duplicates(df, k=4).collect()
    known = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in got if r.doc_id is not None}
    assert known == brute(rows, 4)
    assert [r.kept for r in got if r.doc_id is None] == [True]
    assert near_duplicates(df.limit(0), k=4).count() == 0
    twice = near_duplicates(df.where("doc_id = 4").union(df.where("doc_id = 4")), k=4).collect()
    assert [r.kept for r in twice] == [True, True]
