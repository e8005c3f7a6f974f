import hashlib

import numpy as np
import pytest

from blockforest.llm import suffix_dedup as sd


def brute(rows, width=100):
    seen, out = set(), {}
    for i, text in sorted((r for r in rows if r[0] is not None), key=lambda r: r[0]):
        raw = (text or "").encode()
        gone = np.zeros(len(raw), bool)
        for a in range(len(raw) - width + 1):
            w = raw[a : a + width]
            if w in seen:
                gone[a : a + width] = True
            seen.add(w)
        edges = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        kept = bytes(b for b, g in zip(raw, gone, strict=True) if not g)
        out[i] = (len(raw), int(gone.sum()), edges, hashlib.sha256(kept).hexdigest())
    return out


def test_suffix_array_and_lcp():
    rng = np.random.default_rng(5)
    for n in (1, 2, 3, 10, 200, 3000):
        for sigma in (1, 2, 4, 200, 2500):
            s = np.append(rng.integers(1, sigma + 1, n), 0)
            if n == 3000:
                s[1000:2000] = s[:1000]
            want = sorted(range(n + 1), key=lambda i: s[i:].tolist())
            sa = sd.suffix_array(s)
            assert sa.tolist() == want
            lcp = sd.permuted_lcp(s, sa)
            for a, b in list(zip(want, want[1:], strict=False))[:400]:
                k = 0
                while max(a, b) + k <= n and s[a + k] == s[b + k]:
                    k += 1
                assert lcp[b] == k


def test_large_alphabets_recurse():
    """Reduced strings of far over 1,024 names, at several levels, and names beyond 16 bits."""
    rng = np.random.default_rng(6)
    for top in (3000, 90_000):
        s = np.append(rng.integers(1, top + 1, 20_000), 0)
        s[9000:15_000] = s[:6000]
        sa = sd.suffix_array(s)
        rank = np.empty(len(s), np.int64)
        rank[sa] = np.arange(len(s))
        a, b = sa[:-1].astype(np.int64), sa[1:].astype(np.int64)
        follow = np.append(rank, -1)
        assert sorted(sa.tolist()) == list(range(len(s))) and ((s[a] < s[b]) | (s[a] == s[b]) & (follow[a + 1] < follow[b + 1])).all()


def test_long_texts_in_slices(monkeypatch):
    rng = np.random.default_rng(8)
    data = rng.integers(97, 101, 5000).astype(np.uint8)
    data[3000:3400] = data[500:900]
    covered = lambda parts: {(int(r), int(a) + k) for r, a, n, *_ in zip(*parts, strict=True) for k in range(n)}
    offsets = np.array([0, 4500, 5000])
    whole = covered(sd.chunk_segments(data, offsets, 100))
    monkeypatch.setattr(sd, "SLICE_BYTES", 700)
    sliced = sd.chunk_segments(data, offsets, 100)
    assert covered(sliced) == whole and int(sliced[2].sum()) == len(whole) == 4401 + 401


@pytest.mark.parametrize("per_shard", [2000, 2])
def test_against_brute_force(spark, tiny, monkeypatch, per_shard):
    monkeypatch.setattr(sd, "SEGMENTS_PER_SHARD", per_shard)
    got = {r.doc_id: tuple(r)[1:] for r in sd.op5_induced_suffix_array(spark, tiny).collect()}
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{tiny}/documents.parquet").select("doc_id", "text").collect()]
    assert got == brute(rows)
    assert sum(v[1] for v in got.values()) > 1000


def test_edges(spark):
    rng = np.random.default_rng(1)
    base = "".join(rng.choice(list("abcdé "), 400))
    rows = [(1, base), (2, base[:50] + "X" + base[50:]), (3, "a" * 1000), (4, "a" * 150), (5, None), (6, ""), (7, base[:99]), (8, "é" * 120), (9, base + "tail " + base), (10, "xy" * 40_000)]
    df = spark.createDataFrame([(i, t, "n") for i, t in rows] + [(None, base, "n")], "doc_id long, text string, start string")
    out = sd.repeated_passages(df).collect()
    got = {r.doc_id: (r.n_bytes, sum(s.end - s.start for s in r.removed), len(r.removed), hashlib.sha256(bytes(r.kept)).hexdigest()) for r in out if r.doc_id is not None}
    assert got == brute(rows)
    assert [r.removed for r in out if r.doc_id is None] == [[]]
    assert sd.repeated_passages(df.limit(0)).count() == 0
