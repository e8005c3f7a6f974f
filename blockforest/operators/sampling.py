"""Bites: the small samples that trees are fitted on, and the out-of-bag votes that steer them."""

from __future__ import annotations

import numpy as np


def _draw(pool: np.ndarray, n: int, rng: np.random.Generator, replace: bool) -> np.ndarray:
    return rng.choice(pool, n if replace else min(n, len(pool)), replace=replace)


def draw_bite(right: np.ndarray, wrong: np.ndarray, size: int, rng: np.random.Generator, replace: bool = True) -> tuple[np.ndarray, bool]:
    """Half from either pool (the wrong one gets the odd row); all from one if the other is empty (second value True)."""
    if not len(right) or not len(wrong):
        return _draw(right if len(right) else wrong, size, rng, replace), True
    return np.concatenate([_draw(wrong, size - size // 2, rng, replace), _draw(right, size // 2, rng, replace)]), False


def accept_probability(error: float) -> float:
    """Odds that a row the ensemble gets right is taken, kept within [0, 1]."""
    return 1.0 if error >= 0.5 else max(0.0, error / (1 - error))


def draw_bite_rejection(is_wrong: np.ndarray, error: float, size: int, rng: np.random.Generator, max_draws: int = 1000) -> tuple[np.ndarray, bool]:
    """Uniform draws; wrong rows are always taken, right ones by ``accept_probability``."""
    n, out, p = len(is_wrong), [], accept_probability(error)
    for _ in range(max_draws):
        rows = rng.integers(0, n, size)
        out.append(rows[is_wrong[rows] | (rng.random(size) < p)])
        if sum(map(len, out)) >= size:
            return np.concatenate(out)[:size], False
    short = size - sum(map(len, out))
    return np.concatenate([*out, rng.integers(0, n, short)]), True


def update_oob(votes: np.ndarray, predicted: np.ndarray, bite: np.ndarray) -> np.ndarray:
    """Add a tree's votes on the rows that its bite left out, in place; returns the mask of these rows."""
    out = np.ones(len(votes), bool)
    out[bite] = False
    for c in range(votes.shape[1]):  # class by class: masks of all rows are smaller than lists of their numbers
        votes[:, c] += out & (predicted == c)
    return out


def leaders(votes: np.ndarray) -> np.ndarray:
    """The class with most votes; ties go to the lowest class."""
    return (votes[:, 1] > votes[:, 0]).view(np.int8) if votes.shape[1] == 2 else votes.argmax(axis=1)


def voted(votes: np.ndarray) -> np.ndarray:
    """Rows that have a vote."""
    out = votes[:, 0] != 0
    for c in range(1, votes.shape[1]):
        out |= votes[:, c] != 0
    return out


def split_pools(votes: np.ndarray, y: np.ndarray, unvoted: str = "both") -> tuple[np.ndarray, np.ndarray]:
    """Rows that out-of-bag voting gets right and wrong; ties go to the lowest class."""
    right = leaders(votes) == y
    wrong = ~right
    if unvoted != "class_order":
        silent = ~voted(votes)
        right = right | silent if unvoted == "both" else right & ~silent
        wrong |= silent
    return np.flatnonzero(right).astype(np.int32), np.flatnonzero(wrong).astype(np.int32)


def oob_error(votes: np.ndarray, y: np.ndarray) -> float:
    """Share of voted rows that out-of-bag voting gets wrong; NaN before the first vote."""
    seen = voted(votes)
    n = np.count_nonzero(seen)
    return np.count_nonzero(seen & (leaders(votes) != y)) / n if n else float("nan")
