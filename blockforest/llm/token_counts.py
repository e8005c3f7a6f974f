"""Token counts without token ids: pieces are counted once for each distinct pre-token.

A text is cut into pre-tokens (the vocabulary file's own pattern); in every batch the distinct ones are encoded
once, their piece counts are looked up for each document's pre-token frequencies, and summed. Counts of known
pre-tokens stay with the worker up to ``CACHE_ENTRIES``. Joining inside the batch gives the same sums as one join
over the corpus and spares the shuffle of (document, pre-token) rows, which are several times the input.
"""

from __future__ import annotations

import json
import os
from collections import Counter
from functools import lru_cache, partial

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._text import map_batches

#: Pre-tokens whose piece counts a worker remembers.
CACHE_ENTRIES = 500_000


def vocabulary_path(name: str) -> str:
    """Place of a public vocabulary file on this machine, or the name itself if it is a path."""
    if os.path.sep in name:
        return name
    import public_tokenizers

    return public_tokenizers.path(name)


class PieceCounter:
    """Counts for one byte-level BPE vocabulary file (.json)."""

    #: The pre-token pattern of byte-level BPE with ``use_regex``.
    PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"

    def __init__(self, path: str):
        import regex
        from tokenizers import Tokenizer

        spec = json.load(open(path))
        pre = spec["pre_tokenizer"] or {}
        if spec["normalizer"] or pre.get("type") != "ByteLevel" or pre.get("add_prefix_space") or not pre.get("use_regex") or spec["model"]["type"] != "BPE":
            raise ValueError("only byte-level BPE files without normalizer and prefix space are counted by pre-token")
        self._tokenizer = Tokenizer.from_file(path)
        self._tokenizer.no_truncation()
        self._tokenizer.no_padding()
        added = spec["added_tokens"]
        if any(t["single_word"] or t["lstrip"] or t["rstrip"] for t in added):
            raise ValueError("added tokens with stripping or word limits are not supported")
        self._special = regex.compile("|".join(regex.escape(t["content"]) for t in sorted(added, key=lambda t: -len(t["content"])))) if added else None
        self._pattern = regex.compile(self.PATTERN)
        self._known: dict[str, int] = {}

    def frequencies(self, text: str) -> tuple[Counter, int]:
        """Pre-tokens with their counts, and the special strings, each of which is one token."""
        if self._special is None:
            return Counter(self._pattern.findall(text)), 0
        parts = self._special.split(text)
        seen = Counter(self._pattern.findall(parts[0]))
        for p in parts[1:]:
            seen.update(self._pattern.findall(p))
        return seen, len(parts) - 1

    def learn(self, pretokens: set[str]) -> None:
        new = [p for p in pretokens if p not in self._known]
        if len(self._known) + len(new) > CACHE_ENTRIES:
            self._known = {}
            new = list(pretokens)
        for at in range(0, len(new), 4096):
            part = new[at : at + 4096]
            self._known.update((p, len(e.ids)) for p, e in zip(part, self._tokenizer.encode_batch(part, add_special_tokens=False), strict=True))

    def counts(self, texts: list[str | None]) -> list[int]:
        out = []
        for at in range(0, len(texts), 256):
            seen = [self.frequencies(t or "") for t in texts[at : at + 256]]
            self.learn(set().union(*(f for f, _ in seen)))
            known = self._known
            out.extend(special + sum(known[p] * n for p, n in f.items()) for f, special in seen)
        return out


@lru_cache(2)
def _counter(name: str) -> PieceCounter:
    return PieceCounter(vocabulary_path(name))


def _count(batches, name: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    counter = _counter(name)
    for batch in batches:
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(counter.counts(batch.column(2).to_pylist()), pa.int64())], names=["id", "n_bytes", "n_tokens"])


def token_counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = "byte_bpe_50k.json") -> DataFrame:
    """One row per document: ``id_col, n_bytes, n_tokens``, as the vocabulary's library counts whole texts.

    No begin, end or added special tokens, no truncation or padding; a special string inside a text is the one
    token that the library takes it for. ``vocabulary`` is a public file's name or a path that every worker
    can open. Null and empty texts have 0 bytes and tokens; ids are passed through, null and repeated ones too. An empty
    table gives an empty result; texts of any length are counted whole. Extra columns are ignored, whatever their names.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).alias("id"), F.octet_length(text).cast("long").alias("n_bytes"), text.alias("text"))
    return map_batches(rows, partial(_count, name=vocabulary), f"id {kind}, n_bytes long, n_tokens long").withColumnRenamed("id", id_col)


def op8_pretoken_counts(spark, sf_dir: str, vocabulary: str = "byte_bpe_50k.json") -> DataFrame:
    out = token_counts(spark.read.parquet(f"{sf_dir}/documents.parquet"), vocabulary=vocabulary)
    return out.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > 512).alias("over_limit"))
