import hashlib

import numpy as np
import pytest

from blockforest.llm.pieces import MARKER, decode_pieces, encode_pieces, load_model, op10_unigram_pieces, read_model
from blockforest.llm.token_counts import vocabulary_path


@pytest.fixture(scope="module")
def model():
    return load_model()


@pytest.fixture(scope="module")
def plain():
    pieces, settings = read_model(vocabulary_path("piece_bpe_32k.model"))
    assert settings == {"prefix": True, "squeeze": False}
    return {p: (i, s) for i, (p, s, k) in enumerate(pieces) if k == 1}, {int(p[3:5], 16): i for i, (p, _, k) in enumerate(pieces) if k == 6}


def brute(text, plain):
    """Viterbi over the whole text, character by character, with a dictionary."""
    pieces, bytes_ = plain
    if not text:
        return []
    t = MARKER + text.replace(" ", MARKER)
    low = min(s for _, s in pieces.values()) - 10
    best, back = [0.0] + [-1e18] * len(t), [None] * (len(t) + 1)
    for i in range(len(t)):
        for j in range(i + 1, min(len(t), i + 16) + 1):
            p = pieces.get(t[i:j])
            if p is None and j > i + 1:
                continue
            gain = best[i] + (p[1] if p else low)
            if gain > best[j]:
                best[j], back[j] = gain, (i, p[0] if p else None)
    out, j = [], len(t)
    while j:
        i, p = back[j]
        out = ([p] if p is not None else [bytes_[b] for b in t[i:j].encode()]) + out
        j = i
    return out


def test_against_brute_force(spark, tiny, plain):
    got = {r.doc_id: r for r in op10_unigram_pieces(spark, tiny).collect()}
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()}
    assert len(got) == len(texts)
    for i, t in list(texts.items())[:60]:
        ids = np.array(brute(t, plain), "<i4")
        assert got[i].n_pieces == len(ids) and got[i].ids_sha256 == hashlib.sha256(ids.tobytes()).hexdigest()
    assert all(r.round_trip for r in got.values())


def test_trie_holds_exactly_the_pieces(model, plain):
    for p, (i, _) in list(plain[0].items())[::37]:
        s = np.zeros(1, np.int64)
        for b in p.encode():
            s = model.trie.step(s, np.array([b], np.int32))
        assert model.trie.value[s[0]] == i


def test_edges(spark, model, plain):
    texts = ["", " ", "  two  spaces ", "\n\t x", "é２🤖中", "a" * 5000, "Hello world. " * 3000, f"real {MARKER} marker", "<s> <0x41> <unk>", None]
    df = spark.createDataFrame([(i, t, "p") for i, t in enumerate(texts)] + [(None, "x", "p"), (0, "", "p")], "doc_id long, text string, pieces string")
    encoded = encode_pieces(df, model)
    rows = {r.doc_id: r.pieces for r in encoded.collect()}
    for i, t in enumerate(texts):
        assert rows[i] == brute(t or "", plain)
    back = {r.doc_id: r.text for r in decode_pieces(encoded, model).collect()}
    assert [back[i] for i in range(len(texts))] == [(t or "").replace(MARKER, " ") for t in texts]
    assert encode_pieces(df.limit(0), model).count() == 0
