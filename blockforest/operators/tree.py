"""The base learner: decision trees by information gain over a random subset of attributes in every node."""

from __future__ import annotations

import math
from dataclasses import dataclass
from typing import Protocol

import numpy as np


def n_attributes(d: int) -> int:
    """Attributes tried in a node."""
    return int(math.floor(1 + math.log2(d))) if d else 0


def entropy(counts: np.ndarray) -> np.ndarray:
    """Entropy in bits along the last axis."""
    total = counts.sum(axis=-1, keepdims=True)
    p = counts / np.maximum(total, 1e-300)
    return -(p * np.log2(np.where(p > 0, p, 1.0))).sum(axis=-1)


def best_split(x: np.ndarray, y: np.ndarray, n_classes: int) -> tuple[int, float, float] | None:
    """(column, threshold, gain) of the best cut between two neighbouring values, over all columns at once."""
    n = len(y)
    order = np.argsort(x, axis=0, kind="stable")
    values = np.take_along_axis(x, order, axis=0)
    left = np.cumsum(np.eye(n_classes)[y][order], axis=0)[:-1]
    differ = values[1:] > values[:-1]
    if not differ.any():
        return None
    total = np.bincount(y, minlength=n_classes)
    size = np.arange(1, n)[:, None]
    after = (size * entropy(left) + (n - size) * entropy(total - left)) / n
    gain = np.where(differ, entropy(total) - after, -np.inf)
    # Compared to ten digits, so that equal gains are equal in every engine; ties go to the first column, then to the lowest cut.
    column, row = np.unravel_index(np.argmax(np.round(gain, 10).T), gain.T.shape)
    low, high = values[row, column], values[row + 1, column]
    middle = (low + high) / 2
    return int(column), float(middle if middle < high else low), float(gain[row, column])


@dataclass
class Tree:
    """Flat arrays; feature -1 marks a leaf."""

    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    right: np.ndarray
    leaf_class: np.ndarray
    counts: np.ndarray | None
    depth: int

    def predict(self, x: np.ndarray) -> np.ndarray:
        """Classes of all rows, level by level."""
        at = np.zeros(len(x), np.int64)
        active = np.flatnonzero(self.feature[at] >= 0)
        while len(active):
            node = at[active]
            small = x[active, self.feature[node]] <= self.threshold[node]
            at[active] = np.where(small, self.left[node], self.right[node])
            active = active[self.feature[at[active]] >= 0]
        return self.leaf_class[at]


def fit_tree(x: np.ndarray, y: np.ndarray, n_classes: int, rng: np.random.Generator, min_leaf: int = 10, max_depth: int | None = None, n_attr: int | None = None, resample: bool = False) -> Tree:
    """A full-grown tree: nodes that are pure, have fewer than ``min_leaf`` rows or can't be cut are leaves."""
    d = x.shape[1]
    width = min(d, n_attr or n_attributes(d))
    feature, threshold, left, right, klass, counts = [], [], [], [], [], []
    stack, deepest = [(np.arange(len(y)), -1, False, 0)], 0
    while stack:
        rows, parent, is_right, depth = stack.pop()
        me = len(feature)
        if parent >= 0:
            (right if is_right else left)[parent] = me
        c = np.bincount(y[rows], minlength=n_classes)
        feature.append(-1), threshold.append(0.0), left.append(-1), right.append(-1), klass.append(int(c.argmax())), counts.append(c)
        deepest = max(deepest, depth)
        if len(rows) < min_leaf or c.max() == len(rows) or depth == max_depth:
            continue
        tried = rng.permutation(d)
        split = None
        for at in range(0, d if resample else width, max(width, 1)):
            columns = np.sort(tried[at : at + width])
            split = best_split(x[np.ix_(rows, columns)], y[rows], n_classes)
            if split:
                break
        if not split:
            continue
        feature[me], threshold[me] = int(columns[split[0]]), split[1]
        small = x[rows, feature[me]] <= threshold[me]
        stack.append((rows[~small], me, True, depth + 1))
        stack.append((rows[small], me, False, depth + 1))
    return Tree(np.array(feature, np.int32), np.array(threshold), np.array(left, np.int32), np.array(right, np.int32), np.array(klass, np.int32), np.array(counts, np.int32), deepest)


class BaseLearner(Protocol):
    """What trains one member: anything that gives a ``Tree`` may stand in for the trees."""

    def __call__(self, x: np.ndarray, y: np.ndarray, n_classes: int, rng: np.random.Generator, **options) -> Tree: ...


def fit_stump(x, y, n_classes, rng, **options) -> Tree:
    return fit_tree(x, y, n_classes, rng, **(options | {"max_depth": 1}))


def fit_majority(x, y, n_classes, rng, **options) -> Tree:
    return fit_tree(x, y, n_classes, rng, max_depth=0)


#: Base learners by name.
LEARNERS: dict[str, BaseLearner] = {"tree": fit_tree, "stump": fit_stump, "majority": fit_majority}


def fit_base(learner: str | BaseLearner, x, y, n_classes, rng, **options) -> Tree:
    """A member by the named base learner, or by one that is given as a function."""
    return (learner if callable(learner) else LEARNERS[learner])(x, y, n_classes, rng, **options)
