"""Bounded samples for fitting models: the ids with the smallest hashes, at most a stated number."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def sample_ids(rows: DataFrame, id_col: str, bound: int) -> DataFrame:
    """At most ``bound`` distinct non-null ids, chosen by hash: the same ones in every run."""
    ids = rows.select(F.col(id_col).cast("long").alias("sample_id")).where("sample_id is not null").distinct()
    return ids.orderBy(F.xxhash64("sample_id"), "sample_id").limit(bound)
