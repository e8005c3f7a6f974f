"""Secret scans: fixed patterns, and a linear-chain conditional random field over tokens decoded by Viterbi.

Tokens are tagged B (a secret begins), I (it goes on) or O. A token's score comes from its own word and shape,
its neighbours' words and shapes, and what the file looks like; neighbouring tags have transition scores.
The field is trained on a bounded sample of documents: on the spans that the patterns find there, and on assignments put
into the same texts, of made secrets under names of every kind and of plain values beside them. So it learns what a secret
looks like and where one stands rather than the patterns' few names, and adds spans that no pattern covers.

Scoring is vectorised over all tokens. A token whose O score leads by more than any transitions could make up is
O in every best tagging, so Viterbi runs exactly on the few stretches between such tokens, and of these only on the ones in
which a tag other than O can pay.
"""

from __future__ import annotations

import hashlib
import re
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._tables import cut, drop_cut
from ._text import RollingHash, chunks, lower_ascii, map_batches, mix64

#: Documents with a pattern match, and as many without, that the field is trained on at most.
SAMPLE_BOUND = 2000
#: Tokens on each side of a training secret.
_AROUND = 8
_SLOTS = 1 << 14
_B, _I, _O = 0, 1, 2

KINDS = ("assign", "access", "hex")
_ASSIGN = re.compile(rb"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE)
_ACCESS = re.compile(rb"AKIA[A-Z0-9]{14,}")
_HEX = re.compile(rb"[0-9a-f]{16,}")
_NAMES = (b"password", b"passwd", b"secret", b"token", b"apikey", b"api_key")


def base_spans(raw: bytes, low: bytes) -> list[tuple[int, int, int, int]]:
    """(start, kind, end, start of the secret) in bytes, by start, then kind. ``low`` is the text in lower case."""
    out = []
    if any(n in low for n in _NAMES):
        out = [(m.start(), 0, m.end(), m.start(2)) for m in _ASSIGN.finditer(raw) if m.end(2) - m.start(2) >= 12]
    if b"AKIA" in raw:
        out += [(m.start(), 1, m.end(), m.start()) for m in _ACCESS.finditer(raw)]
    out += [(m.start(), 2, m.end(), m.start()) for m in _HEX.finditer(raw)]
    return sorted(out)


# -- tokens and features --------------------------------------------------------------------------------

_CLASS = np.full(256, 3, np.uint8)  # 0 blank, 1 word of a secret's characters, 2 other letters, 3 sign
_CLASS[[9, 10, 11, 12, 13, 32]] = 0
_CLASS[list(b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_-")] = 1
_CLASS[128:] = 2


def tokenize(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of word characters and single signs: starts, ends, index of each row's first token."""
    kind = _CLASS[data]
    join = np.zeros(len(data) + 1, bool)  # no break before this byte
    joins = (kind[1:] == kind[:-1]) & ((kind[1:] == 1) | (kind[1:] == 2))
    join[1:-1] = joins | ((kind[1:] > 0) & (kind[1:] < 3) & (kind[:-1] > 0) & (kind[:-1] < 3))
    join[offsets] = False
    start = np.flatnonzero((kind > 0) & ~join[:-1])
    after = np.flatnonzero((kind > 0) & ~join[1:]) + 1
    return start, after, np.searchsorted(start, offsets)


def _bucket(x: np.ndarray) -> np.ndarray:
    return np.minimum(np.log2(x + 1.0) * 2, 30).astype(np.uint64)


def token_features(data: np.ndarray, offsets: np.ndarray, start: np.ndarray, end: np.ndarray, bound: np.ndarray) -> np.ndarray:
    """Hashed feature slots, one row for each token."""
    low = lower_ascii(data)
    n = end - start
    word = RollingHash(low, 8).of(start, end)

    def count(mask):
        total = np.concatenate([[0], np.cumsum(mask)])
        return total[end] - total[start]

    digits = count((data >= 48) & (data <= 57))
    upper = count((data >= 65) & (data <= 90))
    lower = count((data >= 97) & (data <= 122))
    hexes = count((data >= 48) & (data <= 57) | (data >= 97) & (data <= 102))
    other = n - digits - upper - lower
    cls = np.where((data >= 48) & (data <= 57), 1, np.where((data >= 65) & (data <= 90), 2, np.where((data >= 97) & (data <= 122), 3, 4)))
    turns = np.concatenate([[0], np.cumsum(np.concatenate([[0], cls[1:] != cls[:-1]]))]) if len(data) else np.zeros(1, int)
    changes = np.maximum(turns[end] - turns[np.minimum(start + 1, end)], 0)
    one = np.uint64
    parts = (digits > 0).astype(one) | (upper > 0).astype(one) << one(1) | (lower > 0).astype(one) << one(2) | (other > 0).astype(one) << one(3) | (hexes == n).astype(one) << one(4)
    shape = mix64(_bucket(n) << one(8) | parts, 1)
    mixed = mix64(_bucket(changes) << one(16) | _bucket(n) << one(8) | (digits * 8 // np.maximum(n, 1)).astype(one), 2)
    long_word = n >= 12
    row = np.repeat(np.arange(len(offsets) - 1), np.diff(bound))

    def near(x, by):
        """The same of the token ``by`` places on, in the same document; 0 outside."""
        out = np.zeros(len(x), np.uint64)
        if by < 0:
            out[-by:] = np.where(row[-by:] == row[:by], x[:by], one(0)) if len(x) > -by else out[-by:]
        else:
            out[:-by] = np.where(row[:-by] == row[by:], x[by:], one(0)) if len(x) > by else out[:-by]
        return out

    # The file: how much of it is signs and digits, and its length.
    rows = len(offsets) - 1
    size = np.maximum(np.diff(offsets), 1)
    sign = np.concatenate([[0], np.cumsum((_CLASS[data] == 3) | ((data >= 48) & (data <= 57)))])
    file = mix64((8 * (sign[offsets[1:]] - sign[offsets[:-1]]) // size).astype(one) << one(8) | _bucket(size) // one(4), 3)[row] if rows else np.zeros(0, np.uint64)
    kind = np.where(long_word, one(1), one(0))
    coarse = mix64(np.minimum(changes, 6).astype(one) << one(8) | parts << one(1) | kind, 7)
    columns = [
        kind, shape, mixed, np.where(long_word, one(7), word), near(word, -1), near(word, -2), near(word, -3),
        near(word, 1), near(shape, -1), near(shape, 1), file + kind, mix64(near(word, -1) + shape, 4), mix64(near(word, -2) + near(word, -1) + kind, 5),
        coarse, mix64(near(coarse, -2) + near(word, -1) + kind, 6), mix64(mix64(near(coarse, -1), 8) + near(coarse, 1) + np.where(long_word, one(7), word), 9),
    ]
    return np.stack([(mix64(c, 40 + j) >> one(64 - 14)).astype(np.int32) for j, c in enumerate(columns)], axis=1) if len(start) else np.zeros((0, len(columns)), np.int32)


# -- the field ------------------------------------------------------------------------------------------


class Field:
    """Weights by slot and tag, and transition scores [from, to]."""

    def __init__(self):
        self.weights = np.zeros((_SLOTS, 3), np.float32)
        self.weights[:, _O] = 0.0
        self.transitions = np.zeros((3, 3))
        self.transitions[_O, _I] = -8.0
        self.bias = np.array([-4.0, -4.0, 4.0])

    def emissions(self, slots: np.ndarray) -> np.ndarray:
        out = np.tile(self.bias, (len(slots), 1))
        for j in range(slots.shape[1]):
            out += self.weights[slots[:, j]]
        return out

    def margin(self) -> float:
        """The most that transitions can gain when one token stops being O."""
        t = self.transitions
        outer = np.vstack([t, np.zeros(3)])  # or a document's end, which has no score
        inner = np.hstack([t, np.zeros((3, 1))])
        return max(float((outer[:, y][:, None] + inner[y][None, :] - outer[:, _O][:, None] - inner[_O][None, :]).max()) for y in (_B, _I))

    def viterbi(self, emissions: np.ndarray, left: bool, right: bool) -> list[int]:
        """Best tags of a stretch; left/right: an O token stands there (else the document ends)."""
        t = self.transitions.tolist()
        best = [e + (t[_O][y] if left else (-1e9 if y == _I else 0.0)) for y, e in enumerate(emissions[0].tolist())]
        back = []
        for e in emissions[1:].tolist():
            came = [max(range(3), key=lambda p, y=y: (best[p] + t[p][y], -p)) for y in range(3)]
            best = [best[came[y]] + t[came[y]][y] + e[y] for y in range(3)]
            back.append(came)
        if right:
            best = [b + t[y][_O] for y, b in enumerate(best)]
        tags = [max(range(3), key=lambda y: (best[y], y))]
        for came in reversed(back):
            tags.append(came[tags[-1]])
        return tags[::-1]


def train(slots: np.ndarray, tags: np.ndarray, epochs: int = 40, rate: float = 0.3, ridge: float = 1e-3) -> Field:
    """Maximum likelihood by forward-backward over windows and adaptive gradient steps.

    ``slots`` [window, token, feature] and ``tags`` [window, token], -1 behind a window's end.
    """
    field = Field()
    if not len(tags):
        return field
    mask = tags >= 0
    slots, tags = slots.astype(np.int64), np.where(mask, tags, _O)
    n, width, j = slots.shape
    flat = slots[mask].ravel()
    memory, tmemory = np.full((_SLOTS, 3), 1e-3), np.full((3, 3), 1e-3)
    weights = np.zeros((_SLOTS, 3))
    for _ in range(epochs):
        e = np.zeros((n, width, 3)) + field.bias
        for c in range(j):
            e += weights[slots[:, :, c]]
        t = field.transitions
        # Forward and backward in scaled probabilities.
        odds, step = np.exp(np.maximum(e - e.max(axis=2, keepdims=True), -60.0)), np.exp(t)
        alpha, beta = np.empty((n, width, 3)), np.ones((n, width, 3))
        alpha[:, 0] = odds[:, 0] / odds[:, 0].sum(axis=1, keepdims=True)
        for k in range(1, width):
            here = (alpha[:, k - 1] @ step) * odds[:, k]
            alpha[:, k] = np.where(mask[:, k, None], here / here.sum(axis=1, keepdims=True), alpha[:, k - 1])
        pairs = np.zeros((3, 3))
        for k in range(width - 2, -1, -1):
            ahead, live = odds[:, k + 1] * beta[:, k + 1], mask[:, k + 1]
            p = alpha[:, k, :, None] * step * ahead[:, None, :]
            pairs += (p / p.sum(axis=(1, 2), keepdims=True))[live].sum(axis=0)
            back = ahead @ step.T
            beta[:, k] = np.where(live[:, None], back / back.sum(axis=1, keepdims=True), 1.0)
        marginal = alpha * beta
        marginal /= marginal.sum(axis=2, keepdims=True)
        gap = (np.eye(3)[tags] - marginal)[mask]
        gradient = np.stack([np.bincount(flat, np.repeat(gap[:, y], j), _SLOTS) for y in range(3)], axis=1) - ridge * weights
        seen = np.zeros((3, 3))
        both = mask[:, 1:]
        np.add.at(seen, (tags[:, :-1][both], tags[:, 1:][both]), 1)
        tgradient = seen - pairs - ridge * t
        memory += gradient**2
        tmemory += tgradient**2
        weights += rate * gradient / np.sqrt(memory)
        field.transitions = np.clip(t + rate * tgradient / np.sqrt(tmemory), -8, 8)
    field.weights = weights.astype(np.float32)
    return field


def _tag_base(spans, start, end, first, last):
    """B/I/O of the tokens first..last of one document from its pattern spans (byte positions)."""
    tags = np.full(last - first, _O)
    for s in sorted(spans, key=lambda s: -s[3]):
        a = np.searchsorted(end[first:last], s[3], "right")
        b = np.searchsorted(start[first:last], s[2], "left")
        if b > a:
            tags[a:b] = _I
            tags[a] = _B
    return tags


#: Names for made assignments (half of them take a word of the text instead), and what may stand between.
MADE_NAMES = (b"auth", b"credential", b"access_code", b"private_key", b"client_id", b"license", b"session", b"login", b"db_url", b"key")
SEPARATORS = (b" = ", b"=", b": ", b":", b" := ", b" => ")
_QUOTES = (b'"', b"'", b"")
_ALNUM = np.frombuffer(b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789", np.uint8)
_LOWER = _ALNUM[26:52]


def made_value(rng: np.random.Generator, words: list[bytes], secret: bool) -> bytes:
    """A random secret (mixed characters, base 64, with signs, dotted parts, prefixed), or a plain value (words, numbers, hosts, paths, dates)."""
    some = lambda n, of=_ALNUM: of[rng.integers(0, len(of), n)].tobytes()
    word = lambda: words[int(rng.integers(len(words)))] if words else some(7, _LOWER)
    n, way = int(rng.integers(16, 49)), int(rng.integers(5))
    if secret:
        signs = np.concatenate([_ALNUM, np.frombuffer(b"+/" if way == 1 else b"-_", np.uint8)])
        return (some(n), some(n, signs) + b"=" * int(rng.integers(3)), some(n, signs), b".".join(some(int(k)) for k in rng.integers(10, 30, 3)), some(int(rng.integers(2, 6)), _LOWER) + b"_" + some(n))[way]
    number = lambda k: str(int(rng.integers(10**k))).zfill(k).encode()
    return (word() + word() + word(), number(int(rng.integers(4, 15))), word() + b"." + word() + b".com", b"/".join(word() for _ in range(4)), (b"_".join(word() for _ in range(3)), number(4) + b"-" + number(2) + b"-" + number(2))[n % 2])[way]


def with_made_assignment(raw: bytes, rng: np.random.Generator, secret: bool, names: tuple[bytes, ...] = MADE_NAMES) -> tuple[bytes, int, int]:
    """A text with an assignment behind one of its blanks: (new text, start and end of the value)."""
    words = [w for w in raw.split()[:2000] if w.isalpha()]
    blanks = np.flatnonzero(np.frombuffer(raw, np.uint8) == 32)
    at = int(blanks[rng.integers(len(blanks))]) + 1 if len(blanks) else 0
    name = words[int(rng.integers(len(words)))] if words and names is MADE_NAMES and rng.random() < 0.5 else names[int(rng.integers(len(names)))]
    name = (name, name.upper(), name.title())[int(rng.integers(3))]
    quote, value = _QUOTES[int(rng.integers(3))], made_value(rng, words, secret)
    lead = name + SEPARATORS[int(rng.integers(len(SEPARATORS)))] + quote
    return raw[:at] + lead + value + quote + b" " + raw[at:], at + len(lead), at + len(lead) + len(value)


def _training_windows(batches):
    """Stretches around pattern spans, around a made secret and a plain value, and one from elsewhere, of every document: tags, then slots."""
    for batch in batches:
        out = []
        for first, end_row, data, offsets in chunks(batch.column(0)):
            raw, texts, made = data.tobytes(), [], []
            for r in range(end_row - first):
                own = raw[offsets[r] : offsets[r + 1]]
                rng = np.random.default_rng([len(own), int(RollingHash(data[offsets[r] : offsets[r + 1]], 8).of(np.zeros(1, int), np.array([len(own)]))[0])])
                texts.append(own)
                made.append(None)
                for secret in (True, False) if own else ():
                    text, a, b = with_made_assignment(own, rng, secret)
                    texts.append(text)
                    made.append((a, b, secret))
            for row, end_of, part, place in chunks(pa.array(texts, pa.binary())):
                start, end, bound = tokenize(part, place)
                x = token_features(part, place, start, end, bound)
                low, whole = lower_ascii(part).tobytes(), part.tobytes()
                for r in range(end_of - row):
                    a, b, p, q = bound[r], bound[r + 1], int(place[r]), int(place[r + 1])
                    if a == b:
                        continue
                    spans = [(s + p, k, e + p, c + p) for s, k, e, c in base_spans(whole[p:q], low[p:q])]
                    known = made[row + r]
                    if known:
                        near = int(np.searchsorted(end[a:b], known[0] + p, "right"))
                        spans += [(known[0] + p, 3, known[1] + p, known[0] + p)] * known[2]
                        centres = [near]
                    y = _tag_base(spans, start, end, a, b)
                    if not known:
                        centres = [*np.flatnonzero(y == _B)[:3].tolist(), int(mix64(np.array([b - a], np.uint64))[0] % np.uint64(b - a))]
                    for at in centres:
                        u, v = max(0, at - _AROUND), min(b - a, at + _AROUND)
                        window, marks = np.zeros((2 * _AROUND, x.shape[1]), "<i2"), np.full(2 * _AROUND, -1, np.int8)
                        window[: v - u], marks[: v - u] = x[a + u : a + v], y[u:v]
                        out.append(marks.tobytes() + window.tobytes())
        yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], names=["window"])


def windows_as_arrays(windows: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Slots and tags of training windows, in an order that does not depend on how they came."""
    raw = np.frombuffer(b"".join(sorted(windows)), np.uint8).reshape(len(windows), -1) if windows else np.zeros((0, 2 * _AROUND), np.uint8)
    tags = raw[:, : 2 * _AROUND].view(np.int8).astype(np.int64)
    return raw[:, 2 * _AROUND :].copy().view("<i2").reshape(len(windows), 2 * _AROUND, -1) if windows else np.zeros((0, 2 * _AROUND, 1)), tags


def _flag(batches):
    """Does a pattern match in the text?"""
    for batch in batches:
        has = []
        for first, end_row, data, offsets in chunks(batch.column(1)):
            raw, low = data.tobytes(), lower_ascii(data).tobytes()
            has.extend(bool(base_spans(raw[offsets[r] : offsets[r + 1]], low[offsets[r] : offsets[r + 1]])) for r in range(end_row - first))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(has, pa.bool_())], names=["id", "has"])


def fit_field(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bound: int = SAMPLE_BOUND) -> Field:
    """A field trained on at most ``bound`` documents in which a pattern matches, and half as many others.

    Documents are chosen by the hash of their ids in one scan, and read in a second; rows without id or text are passed
    over, and of rows that share an id one is taken.
    """
    source = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).where("id is not null and text is not null")
    flags = cut(map_batches(source, _flag, "id long, has boolean").groupBy("id").agg(F.max("has").alias("has")))
    by_hash = lambda rows, n: rows.orderBy(F.xxhash64("id"), "id").limit(n).select(F.col("id").alias("sample_id"))
    chosen = by_hash(flags.where("has"), bound).unionAll(by_hash(flags.where("not has"), bound // 2))
    rows = source.join(F.broadcast(chosen), F.col("id") == F.col("sample_id"), "left_semi").groupBy("id").agg(F.min("text").alias("text"))
    windows = map_batches(rows.select("text"), _training_windows, "window binary").toArrow()["window"].to_pylist()
    drop_cut(flags)
    return train(*windows_as_arrays(windows))


def field_spans(field: Field, data: np.ndarray, offsets: np.ndarray):
    """(row, start, end) in bytes of the tagged secrets of a run of rows."""
    start, end, bound = tokenize(data, offsets)
    if not len(start):
        return []
    e = field.emissions(token_features(data, offsets, start, end, bound))
    lead = np.maximum(e[:, _B], e[:, _I]) - e[:, _O]
    unsure = lead >= -field.margin()
    row = np.searchsorted(bound, np.arange(len(start)), "right") - 1
    at = np.flatnonzero(unsure)
    if not len(at):
        return []
    cut = np.flatnonzero((np.diff(at) != 1) | (row[at[1:]] != row[at[:-1]])) + 1
    first = np.concatenate([[0], cut])
    # n tags other than O change at most n + 1 transitions, each by ``gain`` at best: one of them must lead by -2 gains at least.
    gain = float(field.transitions.max() - field.transitions[_O, _O])
    worth = np.flatnonzero(np.maximum.reduceat(lead[at], first) >= -2 * gain)
    last, out = np.append(cut, len(at))[worth] - 1, []
    for a, b in zip(at[first[worth]].tolist(), (at[last] + 1).tolist(), strict=True):
        r = row[a]
        tags = field.viterbi(e[a:b], a > bound[r], b < bound[r + 1])
        open_at = None
        for k, tag in enumerate([*tags, _O]):
            if tag != _I and open_at is not None:
                out.append((int(r), int(start[open_at]), int(end[a + k - 1])))
                open_at = None
            if tag == _B or (tag == _I and open_at is None and k < len(tags)):
                open_at = a + k
    return out


def _scan(batches, field):
    for batch in batches:
        counts, bases, alls = [[], [], []], [], []
        for first, end_row, data, offsets in chunks(batch.column(1)):
            raw, low = data.tobytes(), lower_ascii(data).tobytes()
            point = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
            extra: dict[int, list] = {}
            for r, a, b in field_spans(field.value, data, offsets):
                extra.setdefault(r, []).append((a, b))
            for r in range(end_row - first):
                p, q = int(offsets[r]), int(offsets[r + 1])
                spans = base_spans(raw[p:q], low[p:q])
                for k in range(3):
                    counts[k].append(sum(s[1] == k for s in spans))
                base = [(int(point[p + s] - point[p]), k, int(point[p + e] - point[p])) for s, k, e, _ in spans]
                added = [(int(point[a] - point[p]), 3, int(point[b] - point[p])) for a, b in extra.get(r, ())]
                added = [x for x in added if not any(x[0] < e and s < x[2] for s, _, e in base)]
                bases.append([{"kind": KINDS[k], "start": s, "end": e} for s, k, e in base])
                alls.append([{"kind": (*KINDS, "field")[k], "start": s, "end": e} for s, k, e in sorted(base + added)])
        span = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))
        yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, pa.int64()) for c in counts), pa.array(bases, span), pa.array(alls, span)], names=["id", "n_assign", "n_access", "n_hex", "base", "spans"])


def find_secrets(docs: DataFrame, field: Field, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``id_col, n_assign, n_access, n_hex, base, spans``.

    ``base`` lists the pattern matches (whole matches; code points, end exclusive) by start, then kind;
    ``spans`` has these and, as kind ``field``, what the field adds where no pattern matches. Null and empty texts
    have none. Ids are passed through; repeated rows get equal results; extra columns are ignored, whatever their names. An
    empty table gives an empty result; texts of any length are scanned whole.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(field)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    span = "array<struct<kind:string,start:int,end:int>>"
    return map_batches(rows, partial(_scan, field=shared), f"id {kind}, n_assign long, n_access long, n_hex long, base {span}, spans {span}").withColumnRenamed("id", id_col)


def redact(text, spans, mark: str = "[secret]"):
    """Column of a text with its spans replaced by a mark; overlapping spans make one mark. Null stays null."""
    merged = F.aggregate(
        spans, F.array().cast("array<struct<start:int,end:int>>"),
        lambda acc, s: F.when(
            (F.size(acc) > 0) & (s["start"] <= F.element_at(acc, -1)["end"]),
            F.concat(F.slice(acc, 1, F.greatest(F.size(acc) - 1, F.lit(0))), F.array(F.struct(F.element_at(acc, -1)["start"].alias("start"), F.greatest(F.element_at(acc, -1)["end"], s["end"]).alias("end")))),
        ).otherwise(F.concat(acc, F.array(F.struct(s["start"].alias("start"), s["end"].alias("end"))))),
    )
    begin = F.struct(F.lit("").alias("out"), F.lit(0).alias("at"))
    step = lambda acc, s: F.struct(F.concat(acc["out"], F.substring(text, acc["at"] + 1, s["start"] - acc["at"]), F.lit(mark)).alias("out"), s["end"].alias("at"))
    return F.when(F.size(spans) == 0, text).otherwise(F.aggregate(merged, begin, step, lambda acc: F.concat(acc["out"], F.substring(text, acc["at"] + 1, F.char_length(text)))))


def _digest(spans):
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def op2_random_field(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = find_secrets(docs, fit_field(docs))
    return out.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2(_digest("base"), 256).alias("base_sha256"), _digest("spans").alias("spans"))
