"""All queries of the library by name, with their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..sources.tables import views
from ..streaming import streams
from . import methods, relational
from .workloads import CLEAN_BIRDS_SQL

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def _sql(text: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: views(spark, sf_dir, text).sql(text)


for _name, (_spark, _duck) in relational.Q.items():
    QUERIES[_name], ORACLES[_name] = _sql(_spark), _duck
for _name, (_make, _duck) in methods.Q.items():
    QUERIES[_name], ORACLES[_name] = _make, _duck


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..operators.schemas import ForestParams
    from ..operators.scoring import predict_lazy
    from ..operators.train import train_mega_forest
    from .workloads import weblang

    train, test = weblang(spark, sf_dir)
    return predict_lazy(train_mega_forest(train, ForestParams(n_trees=5, bite_size=50, n_blocks=4)), test)


def _workloads() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    """Learned forests and simulations: their rows have no SQL twin."""
    from ..operators.schemas import ForestParams
    from . import workloads as w

    small = ForestParams(n_trees=10, bite_size=100, n_blocks=4)
    big = ForestParams(n_trees=125, bite_size=100, n_blocks=8)
    four = ForestParams(n_trees=10, bite_size=100, n_blocks=8, n_classes=4)
    return {
        "w1_weblang": lambda s, d: w.fit_and_score(s, d),
        "w1_weblang_pages": lambda s, d: w.fit_and_score(s, d, params=ForestParams(n_trees=5, bite_size=50, n_blocks=2), table="pages"),
        "w1_weblang_multiclass": lambda s, d: w.lazy_real(s, d, ms=(80,), alphas=(0.01,), params=four, classes="multi"),
        "w2_birds_like": lambda s, d: w.fit_and_score(s, d, "birds", ForestParams(n_trees=5, bite_size=500, n_blocks=4)),
        "w2_birds_flipped": lambda s, d: w.fit_and_score(s, d, "birds", ForestParams(n_trees=5, bite_size=500, n_blocks=4), flip=0.1),
        "w2_error_days": lambda s, d: w.fit_and_score(s, d, "error_days"),
        "w3_embeddings": lambda s, d: w.fit_and_score(s, d, "embeddings", ForestParams(n_trees=10, bite_size=60, n_blocks=4)),
        "w4_quality": lambda s, d: w.fit_and_score(s, d, "labels", ForestParams(n_trees=10, bite_size=60, n_blocks=2)),
        "w4_toxic": lambda s, d: w.fit_and_score(s, d, "labels", ForestParams(n_trees=10, bite_size=60, n_blocks=2), target="toxic"),
        "w5_simulation_sizes": lambda s, d: w.sim(s),
        "w6_simulation_levels": lambda s, d: w.sim(s, ms=(10_000,), alphas=w.LEVELS),
        "w7_simulation_errors": lambda s, d: w.sim(s, ms=(10_000,), alphas=w.LEVELS).select("rule", "m", "alpha", "relative_error", "disagreement"),
        "w8_threshold_times": lambda s, d: w.threshold_times(s),
        "w9_accuracy_time": lambda s, d: w.accuracy_time(s, d, flip=0.1),
        "w10_blocks_and_sizes": lambda s, d: w.accuracy_blocks(s, d, qs=(1, 2, 4, 8, 14, 20, 30, 40), local_sizes=(1, 5, 10, 25), params=ForestParams(bite_size=100, n_blocks=40), flip=0.1),
        "w11_accuracy_time_birds": lambda s, d: w.accuracy_time(s, d, "birds", local_sizes=(1, 5), serial_sizes=(10,), params=ForestParams(bite_size=500, n_blocks=4)),
        "w12_blocks_birds": lambda s, d: w.accuracy_blocks(s, d, "birds", qs=tuple(range(1, 15)), local_sizes=(5, 10), params=ForestParams(bite_size=500, n_blocks=14)),
        "w13_bite_sizes": lambda s, d: w.bite_sizes(s, d, sizes=(25, 50, 100, 200, 400, 800), params=ForestParams(n_trees=100, n_blocks=2), flip=0.1),
        "w13_bite_sizes_birds": lambda s, d: w.bite_sizes(s, d, "birds", sizes=(100, 500, 1000, 5000), params=ForestParams(n_trees=50, n_blocks=2)),
        "w14_lazy_real_birds": lambda s, d: w.lazy_real(s, d, "birds", alphas=(0.05, 0.01, 1e-3), params=ForestParams(n_trees=25, bite_size=500, n_blocks=8)),
        "w14_lazy_real": lambda s, d: w.lazy_real(s, d, ms=(50, 100, 200, 500, 1000), params=big, flip=0.1),
        "w15_lazy_errors": lambda s, d: w.lazy_real(s, d, ms=(1000,), alphas=w.LEVELS, params=big, flip=0.1).where("metric IN ('relative_error', 'disagreement')"),
        "w15_lazy_errors_birds": lambda s, d: w.lazy_real(s, d, "birds", ms=(200,), alphas=w.LEVELS, params=ForestParams(n_trees=25, bite_size=500, n_blocks=8)).where("metric IN ('relative_error', 'disagreement')"),
        "w16_stop_points": lambda s, d: w.stop_points(s, d, params=big, flip=0.1),
        "w17_shallow": lambda s, d: w.shallow(s, d, flip=0.1),
        "w18_committee": lambda s, d: w.committee(s, d, flip=0.1),
        "w19_clean_birds": lambda s, d: w.clean_birds(s, d),
        "sampler_rejection": lambda s, d: w.fit_and_score(s, d, params=ForestParams(n_trees=10, bite_size=100, n_blocks=4, sampler="rejection")),
        "sampler_full": lambda s, d: w.fit_and_score(s, d, params=ForestParams(n_trees=3, n_blocks=4, sampler="full")),
        "baseline_floors": lambda s, d: w.majority_and_single(s, d),
        "baseline_all_data_forest": lambda s, d: w.mllib_forest(s, d),
        "draw_orders": lambda s, d: w.draw_orders(s, d),
        "multiclass_bayes": lambda s, d: w.multiclass_bayes(s, d, four),
        "plateau": lambda s, d: w.plateau(s, d),
        "skewed_blocks": lambda s, d: w.skewed_blocks(s, d),
        "forest_nodes": lambda s, d: _small_forest(s, d, small).nodes(),
        "flagship": flagship,
    }


def _small_forest(spark: SparkSession, sf_dir: str, params):
    from ..operators.train import train_mega_forest
    from .workloads import weblang

    return train_mega_forest(weblang(spark, sf_dir)[0], params)


def _udf_queries() -> dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]]:
    from ..functions.stopping import Rule, thresholds_sql
    from ..functions.udfs import register
    from . import methods

    def tally(s, d):
        from pyspark.sql import functions as F

        from ..functions.udfs import vote_tally

        return methods.hash_votes(s, d).groupBy("row_id").agg(vote_tally("vote").alias("t")).select("row_id", F.element_at("t", 1).alias("zeros"), F.coalesce(F.try_element_at("t", F.lit(2)), F.lit(0)).alias("ones"))

    votes = methods._VOTES
    arrays = ", ".join(f"transform(a, x -> x.{c}) AS {c}" for c in ("feature", "threshold", "lft", "rgt", "cls"))
    nodes = f"""WITH {methods._NODES}, trees AS (SELECT tree_id, {arrays} FROM (SELECT tree_id, array_sort(collect_list(struct(node, feature, cast(threshold AS double) AS threshold, lft, rgt, cls))) AS a FROM nodes GROUP BY tree_id) t)
SELECT trees.tree_id, n.* FROM trees, LATERAL tree_nodes(trees.feature, trees.threshold, trees.lft, trees.rgt, trees.cls) n"""
    return {
        "udf_scalar": (lambda s, d: views(register(s), d, "documents").sql("SELECT doc_id, round(accept_probability(cast(pmod(doc_id, 60) AS double) / 100), 8) AS p FROM documents"), "SELECT doc_id, round(CASE WHEN doc_id % 60 >= 50 THEN 1.0 ELSE (doc_id % 60)::DOUBLE / 100 / (1 - (doc_id % 60)::DOUBLE / 100) END, 8) AS p FROM documents"),
        "udf_stops": (lambda s, d: register(s).sql(f"SELECT cast(n AS int) AS n, gaussian_stop(lead, n, 200, {Rule('g1', 200, 0.01).square()!r}D, 15) AS gaussian, chebyshev_stop(lead, n, 0.05D) AS chebyshev, cast(lead AS int) AS lead FROM (SELECT id AS n FROM range(1, 201)) a, (SELECT id AS lead FROM range(1, 201)) b WHERE lead <= n AND 2 * lead >= n"),
                      f"SELECT x.n::INT AS n, coalesce(lead >= g.min_lead, false) AS gaussian, coalesce(lead >= c.min_lead, false) AS chebyshev, lead::INT AS lead FROM (SELECT n, lead FROM range(1, 201) a(n), range(1, 201) b(lead) WHERE lead <= n AND 2 * lead >= n) x JOIN ({thresholds_sql(Rule('g1_fpc', 200, 0.01))}) g ON x.n = g.n JOIN ({thresholds_sql(Rule('chebyshev', 200, 0.05))}) c ON x.n = c.n"),
        "udtf_tree_nodes": (lambda s, d: register(s).sql(nodes), f"WITH {methods._NODES} SELECT tree_id, node, feature, threshold::DOUBLE AS threshold, lft, rgt, cls FROM nodes"),
        "udtf_thresholds": (lambda s, d: register(s).sql("SELECT n, min_lead FROM gaussian_thresholds(100, 0.01)"), f"SELECT n, min_lead::INT AS min_lead FROM ({thresholds_sql(Rule('g1_fpc', 100, 0.01))})"),
        "udaf_vote_tally": (tally, f"SELECT row_id, count(*) FILTER (WHERE vote = 0) AS zeros, count(*) FILTER (WHERE vote = 1) AS ones FROM {votes} GROUP BY row_id"),
        "udf_bayes_win": (lambda s, d: register(s).sql("SELECT cast(n AS int) AS n, round(bayes_win(n, n, 21), 8) AS p FROM (SELECT explode(sequence(1, 10)) AS n)"), "SELECT n::INT AS n, round(least(1.0, sum(exp(lgamma(22 - n) - lgamma(k + 1) - lgamma(22 - n - k) + lgamma(n + k + 1) + lgamma(22 - n - k) - lgamma(23) + lgamma(n + 2) - lgamma(n + 1)))), 8) AS p FROM range(1, 11) t(n), range(0, 22) v(k) WHERE k <= 21 - n AND n + k >= 11 GROUP BY n"),
    }


QUERIES |= _workloads()
ORACLES["w19_clean_birds"] = CLEAN_BIRDS_SQL
for _name, (_make, _duck) in _udf_queries().items():
    QUERIES[_name], ORACLES[_name] = _make, _duck
QUERIES |= streams.QUERIES
ORACLES |= streams.ORACLES
QUERIES["agg_approx"] = lambda s, d: views(s, d, "documents").sql("SELECT lang, approx_count_distinct(source) AS sources, approx_percentile(n_chars, 0.5) AS median, hll_sketch_estimate(hll_sketch_agg(text)) AS texts, kll_sketch_get_quantile_double(kll_sketch_agg_double(cast(n_chars AS double)), 0.5) AS kll FROM documents GROUP BY lang")
