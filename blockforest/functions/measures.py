"""Cost and accuracy measures over predictions, votes and plans."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _joined(pred: DataFrame, truth: DataFrame) -> DataFrame:
    return pred.select("row_id", "prediction").join(truth.select("row_id", "label"), "row_id")


def accuracy(pred: DataFrame, truth: DataFrame) -> DataFrame:
    return _joined(pred, truth).agg(F.avg((F.col("prediction") == F.col("label")).cast("double")).alias("accuracy"))


def eval_fraction(pred: DataFrame, m: int) -> DataFrame:
    """Share of the ensemble that voted, and its inverse, the saving."""
    return pred.agg((F.avg("votes_used") / m).alias("eval_fraction"), (F.lit(float(m)) / F.avg("votes_used")).alias("savings"))


def relative_error(lazy: DataFrame, full: DataFrame, truth: DataFrame) -> DataFrame:
    """1 - accuracy of the lazy vote / accuracy of the full one (may be slightly negative)."""
    both = lazy.select("row_id", F.col("prediction").alias("l")).join(full.select("row_id", F.col("prediction").alias("f")), "row_id").join(truth.select("row_id", "label"), "row_id")
    right = lambda c: F.avg((F.col(c) == F.col("label")).cast("double"))
    return both.agg((1 - right("l") / right("f")).alias("relative_error"))


def disagreement(lazy: DataFrame, full: DataFrame) -> DataFrame:
    """Share of rows whose early answer is not the full one: what alpha bounds."""
    both = lazy.select("row_id", F.col("prediction").alias("l")).join(full.select("row_id", F.col("prediction").alias("f")), "row_id")
    return both.agg(F.avg((F.col("l") != F.col("f")).cast("double")).alias("disagreement"))


def stop_histogram(pred: DataFrame) -> DataFrame:
    """``bin, low, n``: rows by the power of two of their votes."""
    b = F.floor(F.log2(F.col("votes_used").cast("double")) + 1e-12).cast("int")
    return pred.groupBy(b.alias("bin")).agg(F.count(F.lit(1)).alias("n")).select("bin", F.pow(F.lit(2.0), F.col("bin")).cast("long").alias("low"), "n")


def share_within(pred: DataFrame, limit: int, m: int) -> DataFrame:
    return pred.agg(F.avg((F.col("votes_used") <= limit).cast("double")).alias("share_within"), F.avg((F.col("votes_used") >= m).cast("double")).alias("share_all"))


def confusion(pred: DataFrame, truth: DataFrame, classes: list[int]) -> DataFrame:
    """True class by predicted class, with recall."""
    table = _joined(pred, truth).groupBy("label").pivot("prediction", classes).agg(F.count(F.lit(1))).na.fill(0)
    total = sum((F.col(str(c)) for c in classes), F.lit(0))
    own = F.coalesce(*[F.when(F.col("label") == c, F.col(str(c))) for c in classes])
    return table.withColumn("recall", own / total)


def dataset_summary(train: DataFrame, test: DataFrame) -> DataFrame:
    """``part, rows, features, positive_share``."""
    from ..operators.features import n_features

    both = train.select(F.lit("train").alias("part"), n_features(train).alias("d"), "label").unionAll(test.select(F.lit("test").alias("part"), n_features(test).alias("d"), "label"))
    return both.groupBy("part").agg(F.count(F.lit(1)).alias("rows"), F.max("d").alias("features"), F.avg(F.col("label").cast("double")).alias("positive_share"))


def time_to_accuracy(metrics: DataFrame, target: Column) -> DataFrame:
    """``line, seconds``: the earliest time at which a line reaches the target."""
    return metrics.where(F.col("accuracy") >= target).groupBy("line").agg(F.min("seconds").alias("seconds"))


def plan_facts(df: DataFrame) -> dict[str, int]:
    """Scans and exchanges of a physical plan: how often inputs are read and rows moved."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {"scans": text.count("Scan parquet"), "exchanges": text.count("Exchange ") - text.count("BroadcastExchange "), "broadcasts": text.count("BroadcastExchange ")}


def shuffled_bytes(df: DataFrame) -> int:
    """Bytes that the exchanges of a query wrote: the query runs (its rows go nowhere), then its metrics are read."""
    df.write.format("noop").mode("overwrite").save()
    spark = df.sparkSession
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    store = spark._jsparkSession.sharedState().statusStore()
    last = store.executionsList().apply(int(store.executionsCount()) - 1)
    ids = {str(m.accumulatorId()) for m in _scala(last.metrics()) if m.name() == "shuffle bytes written"}
    text = {str(k): v for k, v in ((p._1(), p._2()) for p in _scala(store.executionMetrics(last.executionId()).toSeq()))}
    return sum(_as_bytes(text.get(i, "0 B")) for i in ids)


def _scala(seq) -> list:
    return [seq.apply(i) for i in range(seq.size())]


def _as_bytes(text: str) -> int:
    """A size as Spark prints it, with the total on the line below its heading if there are several tasks."""
    total = text.strip().splitlines()[-1].split("(")[0].split()
    unit = {"B": 1, "KiB": 1 << 10, "MiB": 1 << 20, "GiB": 1 << 30, "TiB": 1 << 40}
    return int(float(total[0].replace(",", "")) * unit[total[1]])
