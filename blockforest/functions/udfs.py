"""Functions for SQL users: scalars, an aggregate and a table function, each with a native twin."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .stopping import Rule, bayes_final_prob, threshold_table


@F.pandas_udf(T.DoubleType())
def bayes_win(lead: pd.Series, n: pd.Series, m: pd.Series) -> pd.Series:
    """Probability that the leader wins; equal states are computed once."""
    known = {k: bayes_final_prob(*map(int, k)) for k in set(zip(lead, n, m, strict=True))}
    return pd.Series([known[k] for k in zip(lead, n, m, strict=True)])


@F.pandas_udf(T.ArrayType(T.LongType()))
def vote_tally(votes: pd.Series) -> list[int]:
    """Votes by class as one array (classes 0 to the largest seen)."""
    n = int(votes.max()) + 1 if len(votes) else 0
    return [int((votes == c).sum()) for c in range(n)]


@F.udtf(returnType=T.StructType([T.StructField("n", T.IntegerType()), T.StructField("min_lead", T.IntegerType())]))
class GaussianThresholds:
    """``gaussian_thresholds(m, alpha)`` as a table function."""

    def eval(self, m: int, alpha: float) -> Iterator[tuple[int, int | None]]:
        leads = threshold_table(Rule("g1_fpc", m, float(alpha)))
        for n in range(1, m + 1):
            yield n, None if leads[n] > n else int(leads[n])


@F.udtf(returnType="node int, feature int, threshold double, lft int, rgt int, cls int")
class TreeNodes:
    """``tree_nodes(features, thresholds, lefts, rights, classes)``: one row for each node of a tree's arrays."""

    def eval(self, features: list[int], thresholds: list[float], lefts: list[int], rights: list[int], classes: list[int]) -> Iterator[tuple]:
        for node, rest in enumerate(zip(features, thresholds, lefts, rights, classes, strict=True)):
            yield node, *rest


#: Functions that are expressions of SQL: Spark puts them into the plan, so they run in generated code.
SQL_FUNCTIONS = {
    "accept_probability": "(error DOUBLE) RETURNS DOUBLE RETURN CASE WHEN error >= 0.5D THEN 1.0D ELSE greatest(0.0D, error / (1 - error)) END",
    "gaussian_stop": """(lead BIGINT, n BIGINT, m BIGINT, square DOUBLE, least BIGINT) RETURNS BOOLEAN RETURN n >= least AND lead >=
        floor(n * (0.5D + 0.5D * sqrt((square * (CASE WHEN n > 0.05D * m THEN (m - n) / cast(greatest(m - 1, 1) AS DOUBLE) ELSE 1.0D END) / n) / (1 + square * (CASE WHEN n > 0.05D * m THEN (m - n) / cast(greatest(m - 1, 1) AS DOUBLE) ELSE 1.0D END) / n)))) + 1""",
    "chebyshev_stop": "(lead BIGINT, n BIGINT, alpha DOUBLE) RETURNS BOOLEAN RETURN lead >= floor(n * (0.5D + 0.5D * sqrt((1 / alpha / n) / (1 + 1 / alpha / n)))) + 1",
}


def register(spark: SparkSession) -> SparkSession:
    """Names for SQL: ``bayes_win``, ``vote_tally``, ``gaussian_thresholds``, ``tree_nodes``, and as expressions of SQL itself
    ``accept_probability(error)``, ``gaussian_stop(lead, n, m, square, least)`` (square: the rule's z squared) and
    ``chebyshev_stop(lead, n, alpha)``.
    """
    spark.udf.register("bayes_win", bayes_win)
    spark.udf.register("vote_tally", vote_tally)
    spark.udtf.register("gaussian_thresholds", GaussianThresholds)
    spark.udtf.register("tree_nodes", TreeNodes)
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    return spark
