"""A training corpus from raw documents in five stages; each works on what its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockforest.llm import decontaminate, near_dedup, pieces, quality, secrets
from blockforest.llm._tables import cut

#: Names of the columns that every stage but the last returns.
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def _whole_rows(docs: DataFrame) -> DataFrame:
    """Rows as one column beside their text: operators pass it through, so nothing is joined back."""
    return docs.select(F.struct(*COLUMNS).alias("row"), "text")


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose Bradley-Terry score is below the cut go.

    Null and empty texts are scored like any; rows with null ids too, though they can't be labelled. Repeated rows share their
    score. Without labels of both kinds all stay. An empty table stays empty; texts of any length are scored whole; columns
    beside those of documents are dropped.
    """
    ranker = quality.fit_from_labels(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = quality.score_documents(_whole_rows(docs), ranker, "row", "text")
    return scored.where(F.col("score") >= quality.CUT).select("row.*")


def near_duplicate_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates stays: the one with the smallest id.

    Of rows that share an id the smallest by all columns stays. Documents without words (null and empty texts) and rows with
    null ids have no duplicates and stay. An empty table stays empty; texts of any length are compared whole; columns beside
    those of documents are dropped.
    """
    judged = cut(near_dedup.near_duplicates(docs, k=5, percent=80).select("doc_id", "kept"))
    dropped = judged.where("not kept").select("doc_id").distinct()
    repeated = judged.where("kept and doc_id is not null").groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("doc_id")
    single = docs.select(*COLUMNS).join(dropped.unionAll(repeated), "doc_id", "left_anti")
    one = docs.join(repeated, "doc_id", "left_semi").groupBy("doc_id").agg(F.min(F.struct(*COLUMNS)).alias("row")).select("row.*")
    return single.unionByName(one)


def benchmark_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go.

    Null and empty texts hold none and stay; rows are judged one by one, repeated ones and those with null ids too. An empty
    table stays empty; texts of any length are searched whole; columns beside those of documents are dropped.
    """
    judged = decontaminate.contamination(_whole_rows(docs), spark.read.parquet(f"{sf_dir}/benchmark.parquet"), "row", "text")
    return judged.where("n_hit = 0").select("row.*")


def secret_redaction(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by a mark; all documents stay, and ``n_chars`` follows the new text.

    A null text stays null, an empty one empty; repeated rows and null ids are treated like any. An empty table stays empty;
    texts of any length are scanned whole; columns beside those of documents are dropped.
    """
    found = secrets.find_secrets(_whole_rows(docs), secrets.fit_field(docs), "row", "text")
    clean = found.select("row", secrets.redact(F.col("row.text"), F.col("spans")).alias("clean"))
    return clean.select("row.doc_id", F.col("clean").alias("text"), "row.lang", "row.source", F.when(F.col("clean") == F.col("row.text"), F.col("row.n_chars")).otherwise(F.char_length("clean").cast("long")).alias("n_chars"))


def piece_encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with the ids of their pieces.

    Null and empty texts have none; repeated rows and null ids are encoded like any. An empty table stays empty; texts of any
    length are cut whole; columns beside those of documents are dropped.
    """
    encoded = pieces.encode_pieces(_whole_rows(docs), pieces.load_model(), "row", "text")
    return encoded.select("row.*", F.size("pieces").alias("n_pieces"), "pieces")


STAGES = [
    ("quality", quality_filter),
    ("near duplicates", near_duplicate_filter),
    ("decontamination", benchmark_filter),
    ("secrets", secret_redaction),
    ("pieces", piece_encoding),
]
#: Learned scores, tags and pieces are beyond SQL: the tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on the table ``documents`` of a folder; each result is written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
