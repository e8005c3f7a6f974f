"""Schemas of the derived tables and the parameters of a forest."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import asdict, dataclass, field

from pyspark.sql import DataFrame

TREE = (
    "ens_part int, tree_id bigint, block int, iter int, seed bigint, feature array<int>, threshold array<double>, left array<int>, right array<int>, "
    "leaf_class array<int>, class_counts array<int>, n_train int, depth int, n_nodes int, oob_error double, pool_fallback boolean, fit_ms bigint"
)
PREDICTION = "row_id bigint, prediction int, votes_used int, stopped_early boolean, leader_share double, stage string"
METRIC = "workload string, metric string, value double, params map<string,string>"


def check(df: DataFrame, *columns: str) -> DataFrame:
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {', '.join(missing)}")
    return df


@dataclass(frozen=True)
class ForestParams:
    """How every block trains its local ensemble.

    ``sampler``: ``importance`` (half the bite from rows that the ensemble so far gets wrong, half from the others),
    ``rejection`` (wrong rows always, right ones with odds e / (1 - e)), ``bagging`` (uniform) or ``full`` (the block).
    ``unvoted``: rows without an out-of-bag vote count as ``both`` right and wrong, ``wrong``, or by ``class_order``.
    ``learner``: the name of a base learner (see ``tree.LEARNERS``), or a function of its own (``tree.BaseLearner``).
    ``draws``: ``numpy``, or ``portable`` ones that a SQL engine can repeat.
    """

    n_trees: int = 25
    bite_size: int = 300
    sampler: str = "importance"
    replace: bool = True
    unvoted: str = "both"
    max_depth: int | None = None
    min_leaf: int = 10
    n_attr: int | None = None
    n_classes: int = 2
    n_parts: int = 4
    n_blocks: int = 8
    seed: int = 42
    learner: str | Callable = "tree"
    resample: bool = False
    draws: str = "numpy"
    features: tuple[str, ...] = field(default=())

    def __post_init__(self):
        if self.sampler not in ("importance", "rejection", "bagging", "full") or self.unvoted not in ("both", "wrong", "class_order"):
            raise ValueError("unknown sampler or treatment of unvoted rows")
        if not callable(self.learner) and self.learner not in ("tree", "stump", "majority"):
            raise ValueError("unknown base learner")
        if self.draws not in ("numpy", "portable"):
            raise ValueError("unknown draws")
        if min(self.n_trees, self.bite_size, self.n_parts, self.n_blocks, self.n_classes, self.min_leaf) < 1:
            raise ValueError("sizes must be positive")

    def as_map(self) -> dict[str, str]:
        return {k: getattr(v, "__name__", None) or str(v) for k, v in asdict(self).items()}
