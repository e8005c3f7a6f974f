"""Scoring and monitoring of streams around a trained forest."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import committee
from ..operators import features as fx
from ..operators.model import MegaForest
from ..operators.scoring import predict_lazy
from ..plans import methods
from ..sources.tables import shared_path

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def table_stream(spark: SparkSession, sf_dir: str, name: str, schema: str) -> DataFrame:
    """A table as a file stream, be it one file, several of its name, or a folder of parts.

    The name is part of the path: a filter on file names would pass over the parts in a folder.
    """
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{sf_dir}/{name}*.parquet")


def events_stream(spark: SparkSession, sf_dir: str, watermark: str = "1 hour") -> DataFrame:
    """The table ``events`` as a file stream. Watermarks need a timestamp with a zone, so ``ts`` is cast."""
    raw = table_stream(spark, sf_dir, "events", EVENTS)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def score_stream(rows: DataFrame, forest: MegaForest, **options) -> DataFrame:
    """Lazy scoring of a streaming frame ``(row_id, features)``: the batch operator, without state."""
    return predict_lazy(forest, rows, **options)


def committee_stream(rows: DataFrame, forest: MegaForest, sink: str, checkpoint: str, rule: str = "g1_fpc", alpha: float = 0.01, **options):
    """Committee evaluation of every micro-batch (two stages can't be one streaming plan).

    A batch has a folder of its own, so one that runs again after a failure replaces what it wrote.
    """

    def batch(df: DataFrame, number: int) -> None:
        committee.committee_predict(forest, df, rule, alpha, **options).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    return rows.writeStream.option("checkpointLocation", checkpoint).foreachBatch(batch)


def tumbling(events: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """``start, event_type, n`` by tumbling (or sliding) windows."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """``user_id, start, n`` by sessions."""
    return events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


def votes_by_window(predictions: DataFrame, width: str = "1 hour") -> DataFrame:
    """``start, votes, early``: mean votes and share of early stops by window of ``ts``; a rise says that inputs drift."""
    means = predictions.groupBy(F.window("ts", width).alias("w")).agg(F.avg("votes_used").alias("votes"), F.avg(F.col("stopped_early").cast("double")).alias("early"))
    return means.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "votes", "early")


def late_rows(query) -> int:
    """Rows that a query dropped because they came behind its watermark, as far as its progress reports go back."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])


def deduplicated(events: DataFrame) -> DataFrame:
    """Repeats of an event inside the watermark go."""
    return events.dropDuplicatesWithinWatermark(["event_id"])


def label_arrivals(predictions: DataFrame, labels: DataFrame, within: str = "1 hour") -> DataFrame:
    """Predictions with the labels that arrive up to an hour later: a stream-stream join with a time bound.

    ``predictions``: ``row_id, ts, ...``; ``labels``: ``label_row, label_ts, ...``; both with a watermark, which bounds the state.
    """
    return predictions.join(labels, F.expr(f"row_id = label_row AND label_ts >= ts AND label_ts <= ts + INTERVAL {within}"))


def _error_rate(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    seen, errors = state.get if state.exists else (0, 0)
    for b in batches:
        seen, errors = seen + len(b), errors + int((b.event_type == "error").sum())
    state.update((seen, errors))
    yield pd.DataFrame({"user_id": [key[0]], "seen": [seen], "errors": [errors]})


def running_errors(events: DataFrame) -> DataFrame:
    """``user_id, seen, errors``: two counts kept as state for each user.

    There is no timeout: a processing-time one would keep an ``availableNow`` run going for ever.
    """
    return events.groupBy("user_id").applyInPandasWithState(_error_rate, "user_id long, seen long, errors long", "seen long, errors long", "update", GroupStateTimeout.NoTimeout)


def drain(stream: DataFrame, mode: str = "append", keys: tuple[str, ...] = ()) -> DataFrame:
    """Run a stream over what is there (``availableNow``) and return its rows, which pass through files and not the driver.

    ``append``: all rows; ``complete``: those of the last micro-batch; ``update``: the last of each value of ``keys``.
    """
    spark, path = stream.sparkSession, shared_path(stream.sparkSession, "streams")
    batches: list[int] = []

    def save(df: DataFrame, number: int) -> None:
        batches.append(number)
        df.write.mode("overwrite").parquet(f"{path}/rows/batch={number}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).foreachBatch(save).start()
    query.awaitTermination()
    if not batches:
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(f"{path}/rows/batch={max(batches)}")
    rows = spark.read.schema(f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in stream.schema)}, batch int").option("basePath", f"{path}/rows").parquet(*[f"{path}/rows/batch={b}" for b in sorted(set(batches))])
    if mode == "update":
        rows = rows.groupBy(*keys).agg(*[F.max_by(c, "batch").alias(c) for c in stream.columns if c not in keys])
    return rows.select(*stream.columns)


# -- queries: a forest of stumps scores the documents as they come; events stand for predictions and labels ---------------------


def _documents(s, d) -> DataFrame:
    """The test documents with their letter shares, as a file stream."""
    raw = table_stream(s, d, "documents", "doc_id long, text string, lang string, source string, n_chars long")
    return fx.split_grouped(methods.letter_features(raw), F.col("row_id"))[1]


def _scores(s, d) -> DataFrame:
    forest = methods.stump_forest(s, d)[0]
    return drain(score_stream(_documents(s, d), forest, rule="certain", portable=True).select("row_id", "prediction", "votes_used", "stopped_early"))


def _committee(s, d) -> DataFrame:
    path = shared_path(s, "streams")
    query = committee_stream(_documents(s, d), methods.stump_forest(s, d)[0], f"{path}/rows", f"{path}/checkpoint", alpha=0.01, min_votes=3, portable=True)
    query.trigger(availableNow=True).start().awaitTermination()
    schema = "row_id long, prediction int, votes_used int, stopped_early boolean, leader_share double, stage string"
    s.createDataFrame([], schema).write.mode("append").parquet(f"{path}/rows/batch=-1")  # a stream without a file leaves no folder
    return s.read.schema(schema).parquet(f"{path}/rows").select("row_id", "prediction", "votes_used", "stage")


def _arrivals(s, d) -> DataFrame:
    e = events_stream(s, d)
    clicks = e.where("event_type = 'click'").select(F.col("user_id").alias("row_id"), "ts", F.col("event_id").alias("prediction_id"))
    bought = events_stream(s, d).where("event_type = 'purchase'").select(F.col("user_id").alias("label_row"), F.col("ts").alias("label_ts"), F.col("event_id").alias("label_id"))
    return drain(label_arrivals(clicks, bought).select("prediction_id", "label_id"))


def _drift(s, d) -> DataFrame:
    e = events_stream(s, d).withColumn("votes_used", F.pmod("event_id", F.lit(50)).cast("int")).withColumn("stopped_early", F.col("event_type") != "error")
    return drain(votes_by_window(e), "complete").select("start", F.round("votes", 8).alias("votes"), F.round("early", 8).alias("early"))


QUERIES = {
    "stream_tumbling": lambda s, d: drain(tumbling(events_stream(s, d)), "complete"),
    "stream_sliding": lambda s, d: drain(tumbling(events_stream(s, d), "2 days", "1 day"), "complete"),
    "stream_sessions": lambda s, d: drain(sessions(events_stream(s, d)), "complete"),
    "stream_dedup": lambda s, d: drain(deduplicated(events_stream(s, d)).select("event_id", "user_id")),
    "stream_static_join": lambda s, d: drain(events_stream(s, d).join(s.read.parquet(f"{d}/customer.parquet"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment")),
    "stream_running_errors": lambda s, d: drain(running_errors(events_stream(s, d)), "update", ("user_id",)),
    "stream_lazy_scores": _scores,
    "stream_committee": _committee,
    "stream_label_arrivals": _arrivals,
    "stream_votes_by_window": _drift,
}
#: Batch twins in DuckDB.
ORACLES = {
    "stream_tumbling": "SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') - INTERVAL 1 DAY]) AS start FROM events) GROUP BY 1, 2",
    "stream_sessions": "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s",
    "stream_dedup": "SELECT DISTINCT event_id, user_id FROM events",
    "stream_static_join": "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey",
    "stream_running_errors": "SELECT user_id, count(*) AS seen, count(*) FILTER (WHERE event_type = 'error') AS errors FROM events GROUP BY user_id",
    "stream_lazy_scores": methods.STUMP_LAZY_SQL,
    "stream_committee": methods.COMMITTEE_SQL,
    "stream_label_arrivals": "SELECT p.event_id AS prediction_id, l.event_id AS label_id FROM events p JOIN events l ON p.user_id = l.user_id AND l.ts >= p.ts AND l.ts <= p.ts + INTERVAL 1 HOUR WHERE p.event_type = 'click' AND l.event_type = 'purchase'",
    "stream_votes_by_window": "SELECT time_bucket(INTERVAL 1 HOUR, ts, TIMESTAMP '1970-01-01') AS start, round(avg(event_id % 50), 8) AS votes, round(avg((event_type <> 'error')::INT), 8) AS early FROM events GROUP BY 1",
}
