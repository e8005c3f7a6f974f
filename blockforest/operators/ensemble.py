"""One block's local ensemble: bite, tree, out-of-bag votes, pools, again."""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np

from ..functions.hashing import PortableRng, derive_seed
from . import sampling
from .compact import Rows
from .schemas import ForestParams
from .tree import Tree, fit_base


def fit_local_ensemble(x: np.ndarray | Rows, y: np.ndarray, params: ForestParams, block: int = 0) -> Iterator[tuple[int, int, Tree, dict]]:
    """(iteration, seed, tree, facts) one after another. Tree i depends on trees before it only, never on how many follow."""
    n = len(y)
    votes = np.zeros((params.n_classes, n), np.int8 if params.n_trees < 128 else np.int32).T  # class by class
    everything = np.arange(n, dtype=np.int32)
    right = wrong = everything
    error = float("nan")
    steered = params.sampler in ("importance", "rejection")
    for i in range(params.n_trees):
        began = time.perf_counter()
        seed = derive_seed(params.seed, block, i) >> 1
        rng = PortableRng(params.seed, block, i) if params.draws == "portable" else np.random.default_rng(seed)
        fallback = False
        if params.sampler == "full":
            bite = everything
        elif params.sampler == "bagging":
            bite = rng.choice(everything, params.bite_size if params.replace else min(params.bite_size, n), replace=params.replace)
        elif params.sampler == "importance":
            bite, fallback = sampling.draw_bite(right, wrong, params.bite_size, rng, params.replace)
        else:
            is_wrong = np.zeros(n, bool)
            is_wrong[wrong] = True
            bite, fallback = sampling.draw_bite_rejection(is_wrong, 1.0 if np.isnan(error) else error, params.bite_size, rng)
        tree = fit_base(params.learner, x[bite], y[bite], params.n_classes, rng, min_leaf=params.min_leaf, max_depth=params.max_depth, n_attr=params.n_attr, resample=params.resample)
        if steered:  # a bagged forest needs no votes: that is why it is the faster one
            sampling.update_oob(votes, x.predict(tree) if isinstance(x, Rows) else tree.predict(x), bite)
            right, wrong = sampling.split_pools(votes, y, params.unvoted)
            error = sampling.oob_error(votes, y)
        facts = {"n_train": len(bite), "oob_error": None if np.isnan(error) else error, "pool_fallback": fallback, "fit_ms": round(1000 * (time.perf_counter() - began))}
        yield i, seed, tree, facts
