"""Best cuts of whole tables in DataFrame operations: counts by value instead of sorted rows."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Pieces that the values of a feature are cut into, so that no task holds all of them.
PIECES = 64


def entropy_column(counts: list[Column]) -> Column:
    """Entropy in bits of class counts."""
    total = reduce(lambda a, b: a + b, counts)
    part = lambda c: F.when(c > 0, -(c / total) * F.log2(c / total)).otherwise(F.lit(0.0))
    return reduce(lambda a, b: a + b, [part(c) for c in counts])


def class_counts(n_classes: int) -> list[Column]:
    return [F.count_if(F.col("label") == c).alias(f"n{c}") for c in range(n_classes)]


def best_splits(df: DataFrame, n_classes: int = 2, group: tuple[str, ...] = ()) -> DataFrame:
    """``group, feature, threshold, gain``: the cut with the highest information gain of rows ``(features, label)``.

    The numpy form fits a block that a worker holds; this one cuts a table of any size. Class counts of each value are
    summed before the shuffle, running counts are made within pieces of the values and continued from piece to piece. Gains
    are compared to ten digits; ties go to the first feature, then to the lowest cut.
    """
    long = df.select(*group, "label", F.posexplode("features").alias("feature", "value"))
    edges = long.groupBy(F.col("feature").alias("f")).agg(F.percentile_approx("value", [i / PIECES for i in range(1, PIECES)], 1000).alias("edges"))
    cells = long.groupBy(*group, "feature", "value").agg(*class_counts(n_classes))
    cells = cells.join(F.broadcast(edges), F.col("feature") == F.col("f")).withColumn("piece", F.size(F.filter("edges", lambda e: e <= F.col("value")))).drop("f", "edges")
    key = [*group, "feature"]
    classes = [f"n{c}" for c in range(n_classes)]
    along = Window.partitionBy(*key).orderBy("piece")
    sums = cells.groupBy(*key, "piece").agg(*[F.sum(c).alias(c) for c in classes], F.min("value").alias("first"))
    sums = sums.select(
        *key, "piece", F.lead("first").over(along).alias("first_behind"),
        *[F.coalesce(F.sum(c).over(along.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias(f"before_{c}") for c in classes],
        *[F.sum(c).over(Window.partitionBy(*key)).alias(f"all_{c}") for c in classes],
    )
    within = Window.partitionBy(*key, "piece").orderBy("value")
    run = cells.select(*key, "piece", "value", F.lead("value").over(within).alias("next"), *[F.sum(c).over(within.rowsBetween(Window.unboundedPreceding, 0)).alias(c) for c in classes])
    run = run.join(sums, [*key, "piece"]).withColumn("next", F.coalesce("next", "first_behind")).where("next is not null")
    low, whole = [F.col(c) + F.col(f"before_{c}") for c in classes], [F.col(f"all_{c}") for c in classes]
    high = [w - x for w, x in zip(whole, low, strict=True)]
    n_low, n = reduce(lambda a, b: a + b, low), reduce(lambda a, b: a + b, whole)
    gain = F.round(entropy_column(whole) - (n_low * entropy_column(low) + (n - n_low) * entropy_column(high)) / n, 10)
    cuts = run.select(*group, "feature", ((F.col("value") + F.col("next")) / 2).alias("threshold"), gain.alias("gain"))
    best = cuts.groupBy(*group).agg(F.max_by(F.struct("feature", "threshold", "gain"), F.struct("gain", -F.col("feature"), -F.col("threshold"))).alias("b"))
    return best.where("b is not null").select(*group, "b.feature", "b.threshold", "b.gain")
