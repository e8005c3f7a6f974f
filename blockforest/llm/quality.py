"""Quality scores by Bradley-Terry ranking of documents, cut at a quantile of the scores.

A preference pair says that one document is better than another. The probability of that is the logistic
function of the difference of two scores, each linear in a document's features; the weights minimise the
logistic loss over pairs. Scores are then placed on 0..1 so that the cut quantile lies at ``CUT``.
"""

from __future__ import annotations

import pickle
from dataclasses import dataclass
from functools import partial, reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._tables import cut, drop_cut
from ._text import BLANK_SEPARATED, RollingHash, chunks, lower_ascii, map_batches, word_bounds

#: Pairs that all pairs count as against the ridge, at most.
PAIR_WEIGHT = 100_000
#: Bins of raw scores from -REACH to REACH; scores beyond lie in the outermost ones.
BINS, REACH = 512, 16.0
#: The score at the cut quantile.
CUT = 0.7

_SIGNS = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"


def _classes() -> list[np.ndarray]:
    b = np.arange(256)
    upper, lower, digit = (b >= 65) & (b <= 90), (b >= 97) & (b <= 122), (b >= 48) & (b <= 57)
    return [upper, lower, digit, b >= 0xC0, np.isin(b, list(_SIGNS)), np.isin(b, [9, 10, 13]), b == 32, b < 32, *(b == c for c in _SIGNS)]


_CLASSES = _classes()
N_FEATURES = 2 * len(_CLASSES) + 12


def features(column: pa.Array) -> np.ndarray:
    """One row of numbers for each text: shares of character classes and signs, words, lines, repetition."""
    out = []
    for first, end, data, offsets in chunks(column):
        n = end - first
        size = np.maximum(np.diff(offsets), 1).astype(float)
        start, stop, bound = word_bounds(data, offsets, BLANK_SEPARATED)
        words = RollingHash(lower_ascii(data), 1).of(start, stop)
        length = (stop - start).astype(float)
        count = np.maximum(np.diff(bound), 1).astype(float)
        block = np.zeros((n, N_FEATURES))
        for k, member in enumerate(_CLASSES):
            total = np.concatenate([[0], np.cumsum(member[data])])
            share = (total[offsets[1:]] - total[offsets[:-1]]) / size
            block[:, 2 * k], block[:, 2 * k + 1] = share, np.sqrt(share)
        at = 2 * len(_CLASSES)
        last = data[np.maximum(stop - 1, 0)] if len(stop) else data[:0]
        head = data[start] if len(start) else data[:0]
        alpha = (lower_ascii(data) >= 97) & (lower_ascii(data) <= 122) | (data >= 0x80)
        signs = np.concatenate([[0], np.cumsum(~alpha)])
        per_word = {
            "length": length, "length2": length**2, "ends_alone": ~alpha[np.maximum(stop - 1, 0)] if len(stop) else length, "doubled": (stop - start > 1) & (last == data[np.maximum(stop - 2, 0)]) & ~alpha[np.maximum(stop - 1, 0)] if len(stop) else length,
            "upper": (head >= 65) & (head <= 90), "no_letter": (signs[stop] - signs[start]) == (stop - start),
        }
        for k, v in enumerate(per_word.values()):
            total = np.concatenate([[0.0], np.cumsum(v.astype(float))])
            block[:, at + k] = (total[bound[1:]] - total[bound[:-1]]) / count
        at += len(per_word)
        raw = data.tobytes()
        for row in range(n):
            w = words[bound[row] : bound[row + 1]]
            lines = [x for x in raw[offsets[row] : offsets[row + 1]].split(b"\n") if x.strip()]
            tally = np.unique(w, return_counts=True)[1] if len(w) else np.zeros(1)
            pairs = np.unique(w[1:] * np.uint64(3) + w[:-1], return_counts=True)[1] if len(w) > 1 else np.ones(1)
            block[row, at : at + 6] = len(tally) / count[row], tally.max(initial=0) / count[row], len(set(lines)) / max(1, len(lines)), np.log1p(size[row]), np.log1p(len(lines)), len(pairs) / max(1, pairs.sum())
        out.append(block)
    return np.concatenate(out) if out else np.zeros((0, N_FEATURES))


@dataclass
class Ranker:
    """Standardised features, weights, and the line that maps raw scores to 0..1."""

    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    at: float = 0.0
    slope: float = 1.0

    def standard(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.mean) / self.scale, -8, 8)

    def raw(self, x: np.ndarray) -> np.ndarray:
        return self.standard(x) @ self.weights

    def score(self, x: np.ndarray) -> np.ndarray:
        z = self.slope * (self.raw(x) - self.at) + np.log(CUT / (1 - CUT))
        return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def fit_bradley_terry(x: np.ndarray, better: np.ndarray, worse: np.ndarray, ridge: float = 1.0, rounds: int = 25) -> Ranker:
    """Weights from preference pairs (row ``better[i]`` beats row ``worse[i]``) by Newton steps on the logistic loss."""
    mean, scale = x.mean(axis=0), x.std(axis=0)
    scale = np.where(scale > 1e-9, scale, 1.0)
    z = np.clip((x - mean) / scale, -8, 8)
    d = z[better] - z[worse]
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(np.clip(d @ w, -40, 40)))  # of the pair being the other way round
        gradient = d.T @ p - ridge * w
        hessian = (d * (p * (1 - p))[:, None]).T @ d + ridge * np.eye(len(w))
        step = np.linalg.solve(hessian, gradient)
        w += step
        if np.abs(step).max() < 1e-6:
            break
    return Ranker(mean, scale, w)


def place_scores(ranker: Ranker, raw: np.ndarray, quantile: float, spread: float | None = None) -> Ranker:
    """Put the given quantile of raw scores at ``CUT``."""
    ranker.at = float(np.quantile(raw, quantile)) if len(raw) else 0.0
    ranker.slope = 1.0 / max(spread or float(np.std(raw)), 1e-6) if len(raw) else 1.0
    return ranker


def _gather(rows: DataFrame, work, state=None) -> list:
    """What ``work(so far, x, y, state)`` has made of every partition of ``(y, x)``, in the order of partitions."""
    shared = rows.sparkSession.sparkContext.broadcast(state)
    table = map_batches(rows.select("y", "x"), partial(_folded, work=work, shared=shared), "part int, made binary").toArrow().sort_by("part")
    shared.unpersist()
    return [pickle.loads(v) for v in table["made"].to_pylist()]


def _folded(batches, work, shared):
    made = None
    for batch in batches:
        if batch.num_rows:
            x = pc.list_flatten(batch.column(1)).to_numpy().reshape(-1, N_FEATURES)
            made = work(made, x, batch.column(0).to_numpy(), shared.value)
    if made is not None:
        yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()], pa.int32()), pa.array([pickle.dumps(made)], pa.binary())], names=["part", "made"])


def _merged(a, b):
    """Counts of both labels, means and squared deviations of two sets of rows as one."""
    if a is None:
        return b
    n, m, d = a[0].sum(), b[0].sum(), b[1] - a[1]
    return a[0] + b[0], a[1] + d * (m / (n + m)), a[2] + b[2] + d * d * (n * m / (n + m))


def _moments(made, x, y, _):
    mean = x.mean(axis=0)
    return _merged(made, (np.bincount(y, minlength=2)[:2].astype(float), mean, ((x - mean) ** 2).sum(axis=0)))


def _bins(raw: np.ndarray) -> np.ndarray:
    return np.clip((raw + REACH) * (BINS / (2 * REACH)), 0, BINS - 1).astype(np.int64)


def _sums(made, x, y, ranker):
    """Rows and sums of their features by label and bin of their scores."""
    made = made if made is not None else np.zeros((2, BINS, 1 + N_FEATURES))
    z = ranker.standard(x)
    np.add.at(made, (y, _bins(z @ ranker.weights)), np.concatenate([np.ones((len(z), 1)), z], axis=1))
    return made


def _squares(made, x, y, state):
    """Sum of the features' products, each row weighted by its label and bin."""
    ranker, weight = state
    z = ranker.standard(x)
    out = (z * weight[y, _bins(z @ ranker.weights)][:, None]).T @ z
    return out if made is None else made + out


def _raws(made, x, y, ranker):
    return [*(made or []), (ranker.raw(x), y.astype(np.int8))]


def fit_all_pairs(rows: DataFrame, ridge: float = 1.0, rounds: int = 25) -> Ranker | None:
    """The weights of ``fit_bradley_terry`` over all pairs of a label-1 and a label-0 row of ``(y, x)``; None without both labels.

    A pair's part in the loss depends on two scores, so rows meet as sums by bins of their scores, each at its mean:
    512 bins, 1/16 wide, whose second-order error is all that sets this apart from a loop over pairs. A Newton step is two
    passes over the rows. Against the ridge all pairs count as ``PAIR_WEIGHT`` ones at most.
    """
    facts = reduce(_merged, _gather(rows, _moments), None)
    if facts is None or not facts[0].all():
        return None
    scale = np.sqrt(facts[2] / facts[0].sum())
    ranker = Ranker(facts[1], np.where(scale > 1e-9, scale, 1.0), np.zeros(N_FEATURES))
    pairs = facts[0].prod()
    unit = min(PAIR_WEIGHT, pairs) / pairs
    for _ in range(rounds):
        (bad, bad_sum), (good, good_sum) = ((s[:, 0], s[:, 1:]) for s in sum(_gather(rows, _sums, ranker)))
        at = lambda n, total: total @ ranker.weights / np.maximum(n, 1)
        p = 1 / (1 + np.exp(np.clip(at(good, good_sum)[:, None] - at(bad, bad_sum)[None, :], -40, 40)))  # of the pair being the other way round
        h = p * (1 - p)
        gradient = unit * ((p @ bad) @ good_sum - (good @ p) @ bad_sum) - ridge * ranker.weights
        cross = good_sum.T @ h @ bad_sum
        squares = sum(_gather(rows, _squares, (ranker, np.stack([good @ h, h @ bad]))))
        step = np.linalg.solve(unit * (squares - cross - cross.T) + ridge * np.eye(N_FEATURES), gradient)
        ranker.weights = ranker.weights + step
        if np.abs(step).max() < 1e-5:
            break
    return ranker


def fit_from_labels(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> Ranker:
    """A ranker from 0/1 labels: every labelled-1 document is preferred to every labelled-0 one.

    All labelled documents (of rows that share an id one) and all pairs of them are used. The cut is the quantile of their
    scores that best parts the two labels, ties towards keeping more. Without both labels every document scores ``CUT``.
    """
    known = labels.select(F.col(id_col).cast("long").alias("lid"), F.col(label_col).cast("int").alias("y")).where("y in (0, 1) and lid is not null")
    known = known.groupBy("lid").agg(F.max("y").alias("y"))
    source = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    one = source.join(known, F.col("id") == F.col("lid")).groupBy("id", "y").agg(F.min("text").alias("text"))
    rows = cut(map_batches(one.select("text", "y"), _featurise, "y int, x array<double>"))
    try:
        ranker = fit_all_pairs(rows)
        if ranker is None:
            return Ranker(np.zeros(N_FEATURES), np.ones(N_FEATURES), np.zeros(N_FEATURES))
        parts = [part for made in _gather(rows, _raws, ranker) for part in made]
    finally:
        drop_cut(rows)
    raw, y = np.concatenate([r for r, _ in parts]), np.concatenate([y for _, y in parts])
    by = np.lexsort((y, raw))
    # Errors of every cut: labelled-0 documents at or above it, labelled-1 documents below it.
    wrong = np.concatenate([[0], np.cumsum(y[by] == 1)]) + (y == 0).sum() - np.concatenate([[0], np.cumsum(y[by] == 0)])
    best = np.flatnonzero(wrong == wrong.min())
    # Half a place below the first one kept: the quantile is midway between the scores on either side.
    quantile = min(max((best[0] - 0.5) / max(len(by) - 1, 1), 0.0), 1.0)
    place_scores(ranker, raw, quantile, float(np.median(np.abs(raw - np.median(raw)))) or 1.0)
    return ranker


def _featurise(batches):
    for batch in batches:
        x = features(batch.column(0))
        yield pa.RecordBatch.from_arrays([batch.column(1), pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * N_FEATURES, pa.int32()), pa.array(x.ravel()))], names=["y", "x"])


def _score(batches, ranker):
    for batch in batches:
        s = ranker.value.score(features(batch.column(1)))
        yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(batch.num_columns) if i != 1), pa.array(s)], names=[*(batch.schema.names[i] for i in range(batch.num_columns) if i != 1), "score"])


def score_documents(docs: DataFrame, ranker: Ranker, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, score`` for every row; null texts score as empty ones, ids are passed through as they are.

    Repeated rows get equal scores, an empty table gives an empty result, long texts are scored whole, and other columns are
    ignored, whatever their names.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(ranker)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return map_batches(rows, partial(_score, ranker=shared), f"id {kind}, score double").withColumnRenamed("id", id_col)


def above_quantile(scored: DataFrame, quantile: float, score_col: str = "score") -> DataFrame:
    """The rows whose score reaches the given quantile of all scores (ties stay)."""
    at = scored.agg(F.percentile_approx(score_col, quantile, 100_000).alias("at"))
    return scored.join(F.broadcast(at), F.col(score_col) >= F.col("at"), "left_semi")


def op1_bradley_terry(spark, sf_dir: str) -> DataFrame:
    docs, labels = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    remainder = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4))
    ranker = fit_from_labels(docs, labels.where(remainder != 2))
    out = score_documents(docs, ranker)
    return out.select("doc_id", (remainder == 2).alias("held_out"), "score", (F.col("score") >= CUT).cast("int").alias("predicted"))
