"""Lineage cuts in the shared checkpoint folder, and connected components over them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import shared_path


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` as Parquet to the session's shared folder and read it back: later stages restart from there."""
    path = shared_path(df.sparkSession, "tables")
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._cut_path = path
    return out


def drop_cut(df: DataFrame) -> None:
    """Delete a table made by ``cut`` that nothing reads any more."""
    spark = df.sparkSession
    path = spark._jvm.org.apache.hadoop.fs.Path(df._cut_path)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def components(edges: DataFrame) -> DataFrame:
    """Connected components of an undirected graph ``edges(a, b)`` as ``(node, component)``.

    ``component`` is the smallest node id reachable. Each round sends every node's smallest known
    label along the edges and then follows labels one step further, so paths shorten by halves. A node's
    messages are combined before they are shuffled. Self-loops keep single nodes; null ends are ignored.
    """
    edges = edges.where("a is not null and b is not null").select("a", "b")
    both = cut(edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    labels = cut(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.col("node")).alias("component")))
    changed = 1
    while changed:
        heard = both.join(labels.withColumnRenamed("node", "b"), "b").select(F.col("a").alias("node"), "component")
        told = labels.select(F.col("component").alias("node"), "component")  # a label is itself a node
        # What a node hears also reaches the node that it had as its label (hooking of whole trees).
        own = labels.withColumnRenamed("component", "old")
        hooked = heard.join(own, "node").select(F.col("old").alias("node"), "component")
        best = heard.union(told).union(hooked).union(labels.select("node", "component")).groupBy("node").agg(F.min("component").alias("component"))
        jump = best.select(F.col("node").alias("via"), F.col("component").alias("further"))
        new = best.join(jump, best.component == jump.via, "left").select("node", F.least("component", F.coalesce("further", "component")).alias("component"))
        new = cut(new)
        changed = new.join(labels.withColumnRenamed("component", "before"), "node").where("component <> before").limit(1).count()
        drop_cut(labels)
        labels = new
    drop_cut(both)
    return labels
