from blockforest.llm.token_counts import op8_pretoken_counts, token_counts, vocabulary_path


def reference(texts):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(vocabulary_path("byte_bpe_50k.json"))
    return [len(e.ids) for e in t.encode_batch(texts, add_special_tokens=False)]


def test_against_the_library(spark, sf):
    got = {r.doc_id: (r.n_bytes, r.n_tokens, r.over_limit) for r in op8_pretoken_counts(spark, sf).collect()}
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    n = reference([t for _, t in rows])
    assert got == {i: (len(t.encode()), k, k > 512) for (i, t), k in zip(rows, n, strict=True)}


def test_edges(spark):
    odd = ["", "a<|endoftext|>b <|endoftext|><|endoftext|>", "<|endoftext", "  \n\t  x  ", "naïve 🤖🤖 ２３ ½ ٣", "don't WE'LL 's", "  a​", "x" * 100_000, "é́\u0000\x1c\x1f\x85 b", "<|endoftext|> a", "a <|endoftext|>  "]
    df = spark.createDataFrame([(i, t, "z") for i, t in enumerate(odd)] + [(99, None, "z"), (None, "one", "z"), (1, odd[1], "z")], "doc_id long, text string, id string")
    rows = [(r.doc_id, r.n_tokens) for r in token_counts(df).collect()]
    want = [*zip(range(len(odd)), reference(odd), strict=True), (99, 0), (None, reference(["one"])[0]), (1, reference(odd)[1])]
    assert sorted(rows, key=repr) == sorted(want, key=repr)
    assert token_counts(df.limit(0)).count() == 0
