"""Language spans of mixed text: script ranges narrow the candidates, Viterbi labels the words.

Every word has a log score for each language from its character runs. Only languages that use the word's script
are candidates. The best labelling of a document's words, where every change of language costs a penalty, gives
its spans; the language with most letters is the document's. All documents of a batch step through Viterbi together.
"""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._text import RollingHash, chunks, lower_ascii, map_batches

#: Documents of one language that a model is trained on (the hash keeps close to this number).
PER_LANGUAGE_BOUND = 2000
#: Cost, in log score, of changing the language between two words.
SWITCH_PENALTY = 12.0
#: Bytes of text whose documents step through Viterbi together: the more, the fewer steps.
STEP_BYTES = 1 << 20
_SLOTS = 1 << 15
_RUNS = (2, 3, 4)
UNKNOWN = "und"

#: First code points of script ranges (Unicode blocks) and the script from there on.
SCRIPT_RANGES = [
    (0x0000, "latin"), (0x0370, "greek"), (0x0400, "cyrillic"), (0x0530, "armenian"), (0x0590, "hebrew"), (0x0600, "arabic"), (0x0700, "other"),
    (0x0900, "devanagari"), (0x0980, "indic"), (0x0E00, "thai"), (0x0E80, "other"), (0x10A0, "georgian"), (0x1100, "hangul"), (0x1200, "other"),
    (0x1E00, "latin"), (0x1F00, "greek"), (0x2000, "other"), (0x2C60, "latin"), (0x2C80, "other"), (0x3040, "kana"), (0x3100, "han"), (0x3130, "hangul"),
    (0x3190, "han"), (0xA000, "other"), (0xA720, "latin"), (0xA800, "other"), (0xAC00, "hangul"), (0xD800, "other"), (0xF900, "han"), (0xFB00, "latin"),
    (0xFB1D, "hebrew"), (0xFB50, "arabic"), (0xFE00, "other"), (0xFE70, "arabic"), (0xFF00, "other"), (0x20000, "han"), (0x30000, "other"),
]
SCRIPTS = sorted({s for _, s in SCRIPT_RANGES})
_FIRST = np.array([a for a, _ in SCRIPT_RANGES])
_SCRIPT = np.array([SCRIPTS.index(s) for _, s in SCRIPT_RANGES])

_LETTER = np.zeros(256, bool)
_LETTER[65:91] = _LETTER[97:123] = _LETTER[128:] = True


def script_of(data: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Script number of the first character of each word (UTF-8 is decoded in place)."""
    d = np.concatenate([data, np.zeros(4, np.uint8)]).astype(np.int64)
    b = d[start]
    two, three, four = (b >= 0xC0) & (b < 0xE0), (b >= 0xE0) & (b < 0xF0), b >= 0xF0
    c1, c2, c3 = (d[start + i] & 0x3F for i in (1, 2, 3))
    code = np.where(two, (b & 0x1F) << 6 | c1, np.where(three, (b & 0x0F) << 12 | c1 << 6 | c2, np.where(four, (b & 0x07) << 18 | c1 << 12 | c2 << 6 | c3, b)))
    return _SCRIPT[np.searchsorted(_FIRST, code, "right") - 1]


def letter_words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of letters; signs beyond ASCII that are no letters are taken for letters of script ``other``."""
    inside = np.zeros(len(data) + 2, bool)
    inside[1:-1] = _LETTER[data]
    breaks = np.zeros(len(data) + 1, bool)
    breaks[offsets] = True
    start = np.flatnonzero(inside[1:] & (~inside[:-1] | breaks))
    end = np.flatnonzero(inside[:-1] & (~inside[1:] | breaks))
    return start, end, np.searchsorted(start, offsets)


def _slots(data: np.ndarray) -> list[np.ndarray]:
    """Slot of the character run of each length that begins at each byte; all but letters are one blank."""
    text = np.where(_LETTER[data], lower_ascii(data), np.uint8(32))
    text = np.concatenate([np.array([32], np.uint8), text, np.full(max(_RUNS), 32, np.uint8)])
    rolling = RollingHash(text, 9)
    at = np.arange(len(data) + 1)
    return [(rolling.of(at, at + n) >> np.uint64(64 - 15)).astype(np.int64) for n in _RUNS]


class Model:
    """log scores [run length, slot, language] and which scripts a language uses."""

    def __init__(self, counts: dict[str, np.ndarray], scripts: dict[str, np.ndarray]):
        self.languages = sorted(counts)
        self.scores = np.zeros((len(_RUNS), _SLOTS, len(self.languages)), np.float32)
        for k, lang in enumerate(self.languages):
            c = counts[lang].reshape(len(_RUNS), _SLOTS) + 0.05
            self.scores[:, :, k] = np.log(c / c.sum(axis=1, keepdims=True))
        self.scores /= len(_RUNS)
        uses = np.zeros((len(SCRIPTS), len(self.languages)), bool)
        for k, lang in enumerate(self.languages):
            s = scripts[lang]
            uses[:, k] = s >= np.maximum(1, 0.002 * s.sum())
        uses[~uses.any(axis=1)] = True  # a script of no known language leaves all candidates
        self.excluded = np.where(uses, 0.0, -60.0)

    def word_scores(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """[word, language]: sums over runs that begin at the blank before the word up to its last letters."""
        out = self.excluded[script_of(data, start)] if len(start) else np.zeros((0, len(self.languages)))
        for k, slots in enumerate(_slots(data)):
            n = _RUNS[k]
            total = np.zeros((len(slots) + 1, len(self.languages)))
            np.cumsum(self.scores[k][slots], axis=0, out=total[1:])
            stop = np.maximum(end + 3 - n, start + 1)  # runs may take in one blank behind the word
            out = out + total[np.minimum(stop, len(slots))] - total[start]
        return out


def viterbi(scores: np.ndarray, bound: np.ndarray, penalty: float = SWITCH_PENALTY) -> np.ndarray:
    """Best language of every word of all documents at once (first language on ties)."""
    n, languages = scores.shape
    length = np.diff(bound)
    order = np.argsort(-length, kind="stable")
    begin, size = bound[:-1][order], length[order]
    stay = np.ones((n, languages), bool)
    jump = np.zeros(n, np.int64)
    active = int((size > 0).sum())
    best = scores[begin[:active]].copy()
    tags = np.zeros(n, np.int64)
    steps = int(size[0]) if len(size) else 0
    alive = np.searchsorted(-size, -np.arange(1, steps + 1), "right")  # documents with at least so many words
    finals = [best]
    for t in range(1, steps):
        a = alive[t]
        best = best[:a]
        top = best.argmax(axis=1)
        high = best[np.arange(a), top] - penalty
        at = begin[:a] + t
        keep = best >= high[:, None]
        stay[at], jump[at] = keep, top
        best = np.maximum(best, high[:, None]) + scores[at]
        finals.append(best)
    if not steps:
        return tags
    last = np.zeros(len(size), np.int64)
    for t in range(steps - 1, -1, -1):
        a, after = alive[t], alive[t + 1] if t + 1 < steps else 0
        last[after:a] = finals[t][after:a].argmax(axis=1)
        at = begin[:a] + t
        tags[at] = last[:a]
        if t:
            last[:a] = np.where(stay[at, last[:a]], last[:a], jump[at])
    return tags


def _count(batches):
    for batch in batches:
        found: dict[str, list] = {}
        langs = batch.column(1).to_pylist()
        for first, end_row, data, offsets in chunks(batch.column(0)):
            start, end, bound = letter_words(data, offsets)
            script = script_of(data, start) if len(start) else np.zeros(0, np.int64)
            slots = _slots(data)
            for r in range(end_row - first):
                c = found.setdefault(langs[first + r], [np.zeros(len(_RUNS) * _SLOTS, np.int64), np.zeros(len(SCRIPTS), np.int64)])
                a, b = offsets[r], offsets[r + 1]
                for k, s in enumerate(slots):
                    c[0] += 0 if a == b else np.bincount(s[a:b] + k * _SLOTS, minlength=len(c[0]))
                c[1] += np.bincount(script[bound[r] : bound[r + 1]], minlength=len(SCRIPTS))
        rows = [(lang, int(i), int(v)) for lang, (c, s) in found.items() for x, base in ((c, 0), (s, len(_RUNS) * _SLOTS)) for i, v in zip(np.flatnonzero(x) + base, x[np.flatnonzero(x)], strict=True)]
        yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.string(), pa.int32(), pa.int64()))], names=["lang", "slot", "n"])


def fit_model(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", bound: int = PER_LANGUAGE_BOUND, max_languages: int = 500) -> Model:
    """A model from about ``bound`` documents of each language, chosen by hash in one scan.

    Every language is learned; more than ``max_languages``, which bounds the model's memory, are an error. Rows without language or
    text are passed over.
    """
    source = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"), F.col(lang_col).cast("string").alias("lang")).where("lang is not null and text is not null")
    sizes = source.groupBy("lang").agg(F.count(F.lit(1)).alias("size")).orderBy(F.desc("size"), "lang")
    languages = [r.lang for r in sizes.limit(max_languages + 1).collect()]
    if len(languages) > max_languages:
        raise ValueError(f"there are more than {max_languages} languages: raise max_languages, the model grows with it")
    counts, scripts = {}, {}
    if languages:
        share = F.pmod(F.xxhash64("id"), F.lit(1 << 30)) / float(1 << 30)
        rows = source.join(F.broadcast(sizes), "lang").where(share < float(bound) / F.col("size"))
        found = map_batches(rows.select("text", "lang"), _count, "lang string, slot int, n long").groupBy("lang", "slot").agg(F.sum("n").alias("n")).collect()
        for lang in languages:
            counts[lang], scripts[lang] = np.zeros(len(_RUNS) * _SLOTS), np.zeros(len(SCRIPTS))
        for r in found:
            if r.slot < len(_RUNS) * _SLOTS:
                counts[r.lang][r.slot] = r.n
            else:
                scripts[r.lang][r.slot - len(_RUNS) * _SLOTS] = r.n
    return Model(counts, scripts)


def _has_letter(raw: bytes) -> bool:
    return any(c.isalpha() for c in raw.decode("utf-8", "replace"))


def _label(batches, model, penalty: float, with_spans: bool):
    m: Model = model.value
    for batch in batches:
        preds, score, spans = [], [], []
        for _, _, data, offsets in chunks(batch.column(1), STEP_BYTES):
            rows = len(offsets) - 1
            start, end, bound = letter_words(data, offsets)
            tags = viterbi(m.word_scores(data, start, end), bound, penalty) if m.languages else np.zeros(len(start), np.int64)
            n = max(1, len(m.languages))
            row = np.repeat(np.arange(rows), np.diff(bound))
            weight = np.bincount(row * n + tags, weights=end - start, minlength=rows * n).reshape(rows, n) if len(start) else np.zeros((rows, n))
            top, total = weight.argmax(axis=1), weight.sum(axis=1)
            ascii_letters = np.concatenate([[0], np.cumsum(_LETTER[data] & (data < 128))])
            plain = ascii_letters[offsets[1:]] > ascii_letters[offsets[:-1]]
            point = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)]) if with_spans else None
            for r in range(rows):
                known = bool(m.languages) and total[r] > 0 and (plain[r] or _has_letter(data[offsets[r] : offsets[r + 1]].tobytes()))
                preds.append(m.languages[top[r]] if known else UNKNOWN)
                score.append(float(weight[r, top[r]] / total[r]) if known else 0.0)
                if with_spans:
                    a, b = bound[r], bound[r + 1]
                    cut = np.flatnonzero(np.diff(tags[a:b])) + 1 if known else []
                    edge = [0, *cut, b - a] if known else []
                    spans.append([{"lang": m.languages[tags[a + i]], "start": int(point[start[a + i]] - point[offsets[r]]), "end": int(point[end[a + j - 1]] - point[offsets[r]])} for i, j in zip(edge, edge[1:], strict=False)])
        columns, names = [batch.column(0), pa.array(preds, pa.string()), pa.array(score, pa.float64())], ["id", "lang_pred", "score"]
        if with_spans:
            columns.append(pa.array(spans, pa.list_(pa.struct([("lang", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))))
            names.append("spans")
        yield pa.RecordBatch.from_arrays(columns, names=names)


def label_languages(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", penalty: float = SWITCH_PENALTY, with_spans: bool = True) -> DataFrame:
    """One row per document: ``id_col, lang_pred, score`` and, if asked for, ``spans`` (code points, end exclusive).

    ``score`` is the share of letters in spans of the predicted language. Texts that are null or have no letter are
    ``und`` with score 0 and no spans. Ids are passed through, null ones too; repeated rows get equal results. An empty table
    gives an empty result; texts of any length are labelled whole; of equal languages the first by name wins. Extra columns are
    ignored, whatever their names.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    schema = f"id {kind}, lang_pred string, score double" + (", spans array<struct<lang:string,start:int,end:int>>" if with_spans else "")
    return map_batches(rows, partial(_label, model=shared, penalty=penalty, with_spans=with_spans), schema).withColumnRenamed("id", id_col)


def op9_script_viterbi(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    remainder = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(3))
    model = fit_model(docs.where(remainder != 1))
    return label_languages(docs, model, with_spans=False).select("doc_id", (remainder == 1).alias("held_out"), "lang_pred", "score")
