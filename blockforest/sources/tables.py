"""Reading and writing tables, streams and models."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"no table {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def views(spark: SparkSession, sf_dir: str, text: str | None = None) -> SparkSession:
    """Tables as temporary views: all of them, or those that a query's text names."""
    for name in TABLES if text is None else [t for t in TABLES if re.search(rf"\b{t}\b", text)]:
        load(spark, sf_dir, name).createOrReplaceTempView(name)
    return spark


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """csv, json, orc, text, binaryFile, parquet; jdbc, delta and iceberg where their jars are present."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def read_stream(spark: SparkSession, fmt: str, path: str | None = None, schema: str | None = None, **options) -> DataFrame:
    """File and rate streams."""
    reader = spark.readStream.format(fmt).options(**options)
    reader = reader.schema(schema) if schema else reader
    return reader.load(path) if path else reader.load()


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "error", max_records: int | None = None) -> None:
    writer = df.write.format(fmt).mode(mode)
    writer = writer.option("maxRecordsPerFile", max_records) if max_records else writer
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def write_blocks(df: DataFrame, path: str, mode: str = "error") -> None:
    """Blocks as directories: later runs train on some of them without reading the rest."""
    write(df.repartition("block"), path, partition_by=("block",), mode=mode)


def shared_path(spark: SparkSession, kind: str) -> str:
    """A new path in the folder that the driver and all executors share (``spark.checkpoint.dir``).

    A local session that names none gets a temporary folder; on a cluster that would scatter the files, so it is an error.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        folder = getattr(spark.sparkContext, "_own_path", None) or tempfile.mkdtemp(prefix="blockforest_")
        spark.sparkContext._own_path = folder
    return f"{folder.rstrip('/')}/{kind}/{uuid.uuid4().hex}"


def written(df: DataFrame, kind: str = "tables") -> DataFrame:
    """The rows of ``df``, computed once: written to the shared folder and read from there by all that follows."""
    path = shared_path(df.sparkSession, kind)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def block_storage(spark: SparkSession, path: str) -> DataFrame:
    """``block, rows, files, bytes`` of blocks on disk, from file metadata and one scan of the block column."""
    rows = spark.read.parquet(path).select("block", "_metadata.file_path", "_metadata.file_size")
    files = rows.groupBy("block", "file_path").agg(F.count(F.lit(1)).alias("rows"), F.max("file_size").alias("bytes"))
    return files.groupBy("block").agg(F.sum("rows").alias("rows"), F.count(F.lit(1)).alias("files"), F.sum("bytes").alias("bytes"))


def append_metrics(df: DataFrame, path: str) -> None:
    """Rows of ``workload, metric, value, params`` to a growing table with a folder for each workload."""
    write(df.select("workload", "metric", "value", "params"), path, partition_by=("workload",), mode="append")
