"""Unigram piece encoding: Viterbi over a double-array trie of pieces with log scores, and decoding.

A text gets one space in front, spaces are written as the marker, and the best-scoring cut into pieces is
taken; a character that is no piece becomes its UTF-8 bytes (byte fallback). No piece has a marker behind
another character, so a text falls into segments (a run of markers and what follows) that are cut apart.
Equal segments of a batch are cut once; the trie is walked for all of them in step.
"""

from __future__ import annotations

import hashlib
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._text import RollingHash, chunks, map_batches
from .token_counts import vocabulary_path

MARKER = "▁"
_MARK = MARKER.encode()
#: Score of an unknown character below the lowest piece score.
UNKNOWN_PENALTY = 10.0


def _varint(raw: bytes, at: int) -> tuple[int, int]:
    value = shift = 0
    while True:
        b = raw[at]
        value |= (b & 0x7F) << shift
        at, shift = at + 1, shift + 7
        if b < 0x80:
            return value, at


def _fields(raw: bytes, at: int, stop: int):
    """(number, value) of the fields of a protocol buffer message: an integer, or the place of the bytes."""
    while at < stop:
        key, at = _varint(raw, at)
        if key & 7 == 0:
            value, at = _varint(raw, at)
        else:
            n, at = _varint(raw, at) if key & 7 == 2 else (4 if key & 7 == 5 else 8, at)
            value, at = (at, at + n), at + n
        yield key >> 3, value


def read_model(path: str) -> tuple[list[tuple[str, float, int]], dict[str, bool]]:
    """(piece, score, type) of a model file, and its settings: a space in front (``prefix``), and blanks cut (``squeeze``).

    Pieces are field 1 of the file's message, the normaliser is field 3; one that maps characters is refused.
    """
    raw = open(path, "rb").read()
    out, settings = [], {"prefix": True, "squeeze": True}
    for number, value in _fields(raw, 0, len(raw)):
        if number == 1:
            piece, score, kind = "", 0.0, 1
            for n, v in _fields(raw, *value):
                if n == 1:
                    piece = raw[v[0] : v[1]].decode()
                elif n == 2:
                    score = float(np.frombuffer(raw[v[0] : v[1]], "<f4")[0])
                elif n == 3:
                    kind = v
            out.append((piece, score, kind))
        elif number == 3:
            for n, v in _fields(raw, *value):
                if n == 2 and v[1] > v[0]:
                    raise ValueError("the model's normaliser maps characters: such files are not supported")
                if n in (3, 4):
                    settings["prefix" if n == 3 else "squeeze"] = bool(v)
    return out, settings


class Trie:
    """Double array over bytes: the child of state s by byte b is base[s] + b + 1, if its check is s."""

    def __init__(self, keys: list[tuple[bytes, int]]):
        keys = sorted(keys)
        size = 4 * sum(len(k) for k, _ in keys) + 1024
        self.base, self.check, self.value = np.zeros(size, np.int32), np.full(size, -1, np.int32), np.full(size, -1, np.int32)
        base, check = self.base, self.check
        check[0] = 0
        free, top = 1, 1
        stack = [(0, 0, len(keys), 0)]
        while stack:
            state, lo, hi, depth = stack.pop()
            if len(keys[lo][0]) == depth:
                self.value[state] = keys[lo][1]
                lo += 1
            groups = []
            while lo < hi:
                b = keys[lo][0][depth]
                end = lo
                while end < hi and keys[end][0][depth] == b:
                    end += 1
                groups.append((b, lo, end))
                lo = end
            if not groups:
                continue
            at = np.array([g[0] for g in groups]) + 1
            if len(groups) == 1:  # most states: the first hole that is far enough for the byte
                while check[free] >= 0 or free <= at[0]:
                    free += 1
                start = free - int(at[0])
            else:  # others: from where the last one was found
                start = top
                while (check[start + at] >= 0).any():
                    start += 1
                top = start
            base[state] = start
            for b, i, j in groups:
                check[start + b + 1] = state
                stack.append((start + b + 1, i, j, depth + 1))
        used = int(np.flatnonzero(check >= 0).max()) + 258
        self.base, self.check, self.value = base[:used].copy(), check[:used].copy(), self.value[:used].copy()
        self.check[0] = -1

    def step(self, state: np.ndarray, byte: np.ndarray) -> np.ndarray:
        """Next states, -1 where there is none."""
        to = np.minimum(self.base[state] + byte + 1, len(self.check) - 1)
        return np.where((self.check[to] == state) & (self.base[state] > 0), to, -1)


class PieceModel:
    """Pieces, log scores and the trie; ids are the file's."""

    def __init__(self, pieces: list[tuple[str, float, int]], prefix: bool = True, squeeze: bool = False):
        if squeeze:
            raise ValueError("the model drops blanks: texts would not come back")
        self.prefix = prefix
        normal = [(p.encode(), i) for i, (p, _, kind) in enumerate(pieces) if kind == 1 and p]
        if any(MARKER in p.lstrip(MARKER) for p, _, kind in pieces if kind == 1):
            raise ValueError("a piece has a marker behind another character: segments can't be cut apart")
        self.score = np.array([s for _, s, _ in pieces])
        self.unknown_score = min(self.score[i] for _, i in normal) - UNKNOWN_PENALTY
        self.trie = Trie(normal)
        self.byte_id = np.full(256, -1, np.int32)
        for i, (p, _, kind) in enumerate(pieces):
            if kind == 6:
                self.byte_id[int(p[3:5], 16)] = i
        if (self.byte_id < 0).any():
            raise ValueError("the vocabulary has no byte pieces")
        self.piece_bytes = [bytes([int(p[3:5], 16)]) if kind == 6 else p.replace(MARKER, " ").encode() if kind == 1 else b"" for p, _, kind in pieces]
        self.width = max(len(p) for p, _ in normal)

    def segment(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the best cut of each byte range, flat, and the number of ids of each (bytes of unknown characters count)."""
        n, length = len(start), end - start
        offset = np.concatenate([[0], np.cumsum(length + 1)])
        best = np.full(offset[-1], -np.inf)
        came, piece = np.zeros(offset[-1], np.int64), np.full(offset[-1], -1, np.int64)
        best[offset[:-1]] = 0.0
        order = np.argsort(-length, kind="stable")
        longest = int(length.max(initial=0))
        alive = np.searchsorted(-length[order], -np.arange(longest + 1), "left")
        data = np.concatenate([data, np.zeros(4, np.uint8)]).astype(np.int32)
        boundary = (data & 0xC0) != 0x80
        for i in range(longest):
            who = order[: alive[i]]
            who = who[boundary[start[who] + i]]
            here = best[offset[who] + i]
            byte = data[start[who] + i]
            width = np.where(byte < 0x80, 1, np.where(byte < 0xE0, 2, np.where(byte < 0xF0, 3, 4)))
            width = np.minimum(width, length[who] - i)
            single = np.zeros(len(who), bool)
            at, state, go = np.arange(len(who)), np.zeros(len(who), np.int64), i
            while len(at):
                state = self.trie.step(state, data[start[who[at]] + go])
                ok = state >= 0
                at, state = at[ok], state[ok]
                go += 1
                value = self.trie.value[state]
                hit = value >= 0
                if hit.any():
                    w, v = at[hit], value[hit]
                    target = offset[who[w]] + go
                    gain = here[w] + self.score[v]
                    single[w] |= width[w] == go - i
                    better = gain > best[target]
                    target = target[better]
                    best[target], came[target], piece[target] = gain[better], i, v[better]
                more = length[who[at]] > go
                at, state = at[more], state[more]
            lone = np.flatnonzero(~single)
            if len(lone):
                target = offset[who[lone]] + i + width[lone]
                gain = here[lone] + self.unknown_score
                better = gain > best[target]
                target = target[better]
                best[target], came[target], piece[target] = gain[better], i, -2
        # backward: mark where pieces end
        ends = np.zeros(offset[-1], bool)
        at = offset[:-1] + length
        who = np.flatnonzero(length > 0)
        while len(who):
            ends[at[who]] = True
            at[who] = offset[who] + came[at[who]]
            who = who[at[who] > offset[who]]
        stop = np.flatnonzero(ends)
        owner = np.searchsorted(offset, stop, "right") - 1
        begin = came[stop]
        known = piece[stop] >= 0
        n_ids = np.where(known, 1, stop - offset[owner] - begin)
        flat = np.repeat(piece[stop], n_ids)
        if not known.all():
            inner = np.arange(n_ids.sum()) - np.repeat(np.cumsum(n_ids) - n_ids, n_ids)
            lost = ~np.repeat(known, n_ids)
            flat[lost] = self.byte_id[data[(np.repeat(start[owner] + begin, n_ids) + inner)[lost]]]
        return flat, np.bincount(owner, weights=n_ids, minlength=n).astype(np.int64)

    def encode_rows(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids and the number of ids of each row of a run of texts."""
        rows = len(offsets) - 1
        # a space in front of every text that isn't empty, then markers for spaces
        filled = np.flatnonzero(np.diff(offsets) > 0) if self.prefix else np.zeros(0, np.int64)
        text = np.insert(data, offsets[filled], 32)
        moved = offsets + np.searchsorted(filled, np.arange(rows + 1), "left")
        blank = text == 32
        first = np.zeros(len(text) + 1, bool)
        first[1:-1] = blank[1:] & ~blank[:-1]
        first[moved] = True
        start = np.flatnonzero(first[:-1])
        size = np.where(blank, 3, 1)
        place = np.concatenate([[0], np.cumsum(size)])
        wide = np.repeat(text, size)
        marks = np.flatnonzero(np.repeat(blank, size)).reshape(-1, 3)
        for k in range(3):
            wide[marks[:, k]] = _MARK[k]
        end = np.append(start[1:], len(text)) if len(start) else start
        start, end = place[start], place[end]
        key = RollingHash(wide, 10).of(start, end)
        _, one, inverse = np.unique(key, return_index=True, return_inverse=True)
        flat, n = self.segment(wide, start[one], end[one])
        begin = np.cumsum(n) - n
        counts = n[inverse]
        where = np.repeat(begin[inverse] - (np.cumsum(counts) - counts), counts) + np.arange(counts.sum())
        row = np.searchsorted(moved, np.searchsorted(place, start), "right") - 1
        return flat[where], np.bincount(row, weights=counts, minlength=rows).astype(np.int64)

    def decode(self, ids) -> str:
        """Text of ids: byte pieces joined, markers as spaces, the space in front taken off."""
        raw = b"".join(map(self.piece_bytes.__getitem__, ids))
        return (raw[1:] if self.prefix and raw[:1] == b" " else raw).decode("utf-8", "replace")


def load_model(name: str = "piece_bpe_32k.model") -> PieceModel:
    pieces, settings = read_model(vocabulary_path(name))
    return PieceModel(pieces, **settings)


def _encode(batches, model, checks: bool):
    m: PieceModel = model.value
    for batch in batches:
        parts, counts, same = [], [], []
        for _, _, data, offsets in chunks(batch.column(1)):
            flat, n = m.encode_rows(data, offsets)
            parts.append(flat.astype(np.int32))
            counts.append(n)
            if checks:
                bounds = np.concatenate([[0], np.cumsum(n)])
                ids, raw = flat.tolist(), data.tobytes()
                for r in range(len(n)):
                    piece = b"".join(map(m.piece_bytes.__getitem__, ids[bounds[r] : bounds[r + 1]]))
                    same.append(piece[m.prefix :] == raw[offsets[r] : offsets[r + 1]])
        n = np.concatenate(counts) if counts else np.zeros(0, np.int64)
        flat = np.concatenate(parts) if parts else np.zeros(0, np.int32)
        lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(n)]), pa.int32()), pa.array(flat))
        kept = [batch.column(i) for i in range(batch.num_columns) if i != 1]
        names = [batch.schema.names[i] for i in range(batch.num_columns) if i != 1]
        if checks:
            byte = np.isin(flat, m.byte_id)
            total = np.concatenate([[0], np.cumsum(byte)])
            at = np.concatenate([[0], np.cumsum(n)])
            sums = [hashlib.sha256(flat[a:b].astype("<i4").tobytes()).hexdigest() for a, b in zip(at, at[1:], strict=False)]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(n), pa.array(total[at[1:]] - total[at[:-1]]), pa.array(sums, pa.string()), pa.array(same, pa.bool_())], names=[*names, "n_pieces", "n_byte_pieces", "ids_sha256", "round_trip"])
        else:
            yield pa.RecordBatch.from_arrays([*kept, lists], names=[*names, "pieces"])


def _decode(batches, model):
    for batch in batches:
        texts = [None if ids is None else model.value.decode(ids) for ids in batch.column(1).to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=["id", "text"])


def encode_pieces(docs: DataFrame, model: PieceModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, pieces array<int>`` for every row.

    Null and empty texts have no pieces; ids are passed through, null ones too; repeated rows get equal pieces. Of cuts with
    equal scores the one found first stays, the same in every run. An empty table gives an empty result; texts of any length
    are cut whole. Extra columns are ignored, whatever their names.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return map_batches(rows, partial(_encode, model=shared, checks=False), f"id {kind}, pieces array<int>").withColumnRenamed("id", id_col)


def decode_pieces(encoded: DataFrame, model: PieceModel, id_col: str = "doc_id", pieces_col: str = "pieces") -> DataFrame:
    """``id_col, text``: the texts of piece ids. A marker character in the original comes back as a space."""
    kind = encoded.schema[id_col].dataType.simpleString()
    shared = encoded.sparkSession.sparkContext.broadcast(model)
    rows = encoded.select(F.col(id_col).alias("id"), F.col(pieces_col).cast("array<int>").alias("pieces"))
    return map_batches(rows, partial(_decode, model=shared), f"id {kind}, text string").withColumnRenamed("id", id_col)


def piece_facts(docs: DataFrame, model: PieceModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, n_pieces, n_byte_pieces, ids_sha256 (of little-endian 32-bit ids), round_trip`` (decoding gives the text)."""
    kind = docs.schema[id_col].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return map_batches(rows, partial(_encode, model=shared, checks=True), f"id {kind}, n_pieces long, n_byte_pieces long, ids_sha256 string, round_trip boolean").withColumnRenamed("id", id_col)


def op10_unigram_pieces(spark, sf_dir: str, vocabulary: str = "piece_bpe_32k.model") -> DataFrame:
    return piece_facts(spark.read.parquet(f"{sf_dir}/documents.parquet"), load_model(vocabulary))
