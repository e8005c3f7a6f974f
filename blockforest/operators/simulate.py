"""Simulated ensembles: points with a random share of votes, stopped by a rule and voted out in full."""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import derive_seed
from ..functions.stopping import Rule, threshold_table

_STEP = 64


def draw_points(rng: np.random.Generator, n: int, rule: Rule, leads: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
    """(p, votes used, lazy class, full class): votes are drawn only until a point stops, the rest as one binomial."""
    m, leads = rule.m, threshold_table(rule) if leads is None else leads
    p = rng.random(n)
    ones, used = np.zeros(n, np.int64), np.full(n, m)
    lazy = np.full(n, -1)
    active = np.arange(n)
    seen = 0
    while len(active) and seen < m:
        width = min(_STEP, m - seen)
        votes = rng.random((len(active), width)) < p[active, None]
        run = ones[active, None] + np.cumsum(votes, axis=1)
        at = np.arange(seen + 1, seen + width + 1)
        lead = np.maximum(run, at - run)
        stop = lead >= leads[at]
        if seen + width == m:
            stop[:, -1] = True
        first = np.where(stop.any(axis=1), stop.argmax(axis=1), -1)
        done = first >= 0
        col = np.where(done, first, width - 1)
        ones[active] = run[np.arange(len(active)), col]
        who = active[done]
        used[who] = seen + first[done] + 1
        lazy[who] = 2 * ones[who] > used[who]
        active, seen = active[~done], seen + width
    total = ones + rng.binomial(m - used, p)
    return p, used, lazy, (2 * total > m).astype(int)


def _simulate(batches, tables: list[tuple[Rule, np.ndarray]], seed: int):
    for batch in batches:
        ids = batch.column(0).to_numpy()
        rows = []
        for rule, leads in tables:
            rng = np.random.default_rng(derive_seed(seed, rule, int(ids[0]) if len(ids) else 0))
            p, used, lazy, full = draw_points(rng, len(ids), rule, leads)
            truth = p >= 0.5
            rows.append((rule.name, rule.m, rule.alpha, len(ids), int(used.sum()), int((lazy == truth).sum()), int((full == truth).sum()), int((lazy != full).sum())))
        names = ["rule", "m", "alpha", "points", "votes", "lazy_right", "full_right", "differ"]
        yield pa.RecordBatch.from_pylist([dict(zip(names, r, strict=True)) for r in rows], schema=pa.schema([("rule", pa.string()), ("m", pa.int32()), ("alpha", pa.float64()), *((c, pa.int64()) for c in names[3:])]))


def simulate(spark: SparkSession, n_points: int, rules: list[Rule], seed: int = 42, parts: int = 8) -> DataFrame:
    """``rule, m, alpha, points, eval_fraction, relative_error, disagreement`` for every rule.

    The tables of thresholds are built once, on the driver: a Bayesian one is quadratic in m.
    """
    tables = [(r, threshold_table(r)) for r in rules]
    raw = spark.range(0, n_points, 1, parts).mapInArrow(partial(_simulate, tables=tables, seed=seed), "rule string, m int, alpha double, points long, votes long, lazy_right long, full_right long, differ long")
    total = raw.groupBy("rule", "m", "alpha").agg(*[F.sum(c).alias(c) for c in ("points", "votes", "lazy_right", "full_right", "differ")])
    return total.select("rule", "m", "alpha", "points", (F.col("votes") / F.col("points") / F.col("m")).alias("eval_fraction"), (1 - F.col("lazy_right") / F.col("full_right")).alias("relative_error"), (F.col("differ") / F.col("points")).alias("disagreement"))
