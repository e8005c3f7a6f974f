import hashlib
import re
from collections import Counter

import numpy as np

from blockforest.llm.fingerprints import SIZE, edited_fingerprints, op7_weighted_sampling


def edited(rows):
    rows = sorted(rows, key=lambda r: ((r[0] is not None), r[0] or 0, r[1] or ""), reverse=True)
    texts = [t or "" for _, t in rows]
    out = {}
    for n, (i, _) in enumerate(rows):
        t, nxt = texts[n], texts[(n + 1) % len(rows)]
        k = len(t) // 3
        out.setdefault(i, []).append((len(t), t, t[: len(t) - k] + nxt[:k], nxt))
    return out


def jaccard(a, b):
    x, y = (Counter(w for w in re.split(r"[\W_]+", t.lower()) if w) for t in (a, b))
    top = sum((x | y).values())
    return sum((x & y).values()) / top if top else 1.0


def test_against_exact_similarity(spark, sf):
    out = op7_weighted_sampling(spark, sf).collect()
    want = edited([(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()])
    err, by_text = [], {}
    for r in out:
        n, t, e, nxt = want[r.doc_id][0]
        assert (r.n_chars, r.edited_sha256) == (n, hashlib.sha256(e.encode()).hexdigest())
        assert by_text.setdefault(t, r.fingerprint) == r.fingerprint
        assert len(r.fingerprint) == 4 * SIZE
        err.append((r.near_edited - jaccard(t, e), r.near_next - jaccard(t, nxt)))
    err = np.array(err)
    assert len(out) == len(want) and abs(err.mean()) < 0.01 and np.abs(err).mean() < 0.07


def test_edges(spark):
    rows = [(1, None), (2, ""), (3, "..."), (4, "a b"), (4, "a b"), (4, "c"), (None, "one two three"), (9, "é word " * 20_000), (7, "Tie"), (8, "tie")]
    df = spark.createDataFrame([(i, t, "x", 1) for i, t in rows], "doc_id long, text string, id string, bucket int")
    out = edited_fingerprints(df).collect()
    assert len(out) == len(rows)
    want = edited(rows)
    for r in out:
        assert (r.n_chars, r.edited_sha256) in [(n, hashlib.sha256(e.encode()).hexdigest()) for n, _, e, _ in want[r.doc_id]]
        assert 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
    prints = {}
    for r in out:
        prints.setdefault(r.doc_id, set()).add(r.fingerprint)
    assert prints[1] == prints[2] == prints[3] == {""} and prints[7] == prints[8] and len(prints[4]) == 2
    assert [r.near_edited for r in out if r.doc_id == 1] == [1.0]
    assert edited_fingerprints(df.limit(0)).count() == 0
    assert [r.near_next for r in edited_fingerprints(df.where("doc_id = 9")).collect()] == [1.0]
