"""Mega-forests as tables of trees: merge, union, restriction, size, storage, and packing for workers."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import portable_hash
from ..sources.tables import written
from .schemas import TREE, ForestParams
from .tree import LEARNERS, Tree


@dataclass(frozen=True)
class MegaForest:
    """All trees, with equal votes."""

    trees: DataFrame
    params: ForestParams

    def restrict(self, blocks: int | None = None, local_size: int | None = None) -> MegaForest:
        """The forest that fewer blocks or fewer trees in each would have given: a prefix of the trees, no training."""
        t = self.trees
        t = t.where(F.col("block") < blocks) if blocks is not None else t
        t = t.where(F.col("iter") < local_size) if local_size is not None else t
        return MegaForest(t, replace(self.params, n_trees=min(local_size or self.params.n_trees, self.params.n_trees), n_blocks=min(blocks or self.params.n_blocks, self.params.n_blocks)))

    def union(self, other: MegaForest) -> MegaForest:
        """Independently trained forests add up; numbers of the second are moved behind the first's."""
        if self.params.features != other.params.features or self.params.n_classes != other.params.n_classes:
            raise ValueError("forests over different features or classes can't be merged")
        clash = self.trees.select("tree_id").join(other.trees.select("tree_id"), "tree_id", "left_semi").limit(1).count()
        theirs = other.trees
        if clash:
            behind = self.trees.agg(F.coalesce(F.max("block"), F.lit(-1)) + 1).first()[0]
            moved = theirs.withColumn("block", (F.col("block") + behind).cast("int"))
            theirs = moved.withColumn("tree_id", F.col("block").cast("long") * 1_000_000 + F.col("iter"))
        params = replace(self.params, n_blocks=self.params.n_blocks + other.params.n_blocks, n_trees=max(self.params.n_trees, other.params.n_trees), n_parts=max(self.params.n_parts, other.params.n_parts))
        return MegaForest(self.trees.unionByName(theirs), params)

    def prune(self, keep: int, by: str = "oob_error") -> MegaForest:
        """The ``keep`` trees with the smallest value."""
        return MegaForest(self.trees.orderBy(F.col(by).asc_nulls_last(), "tree_id").limit(keep), self.params)

    def size(self) -> DataFrame:
        """``trees, nodes, bytes, mean_nodes, max_depth``."""
        per_node = 4 * 4 + 8 + 4 * self.params.n_classes
        return self.trees.agg(F.count(F.lit(1)).alias("trees"), F.sum("n_nodes").cast("long").alias("nodes"), (F.sum("n_nodes") * per_node).cast("long").alias("bytes"), F.avg("n_nodes").alias("mean_nodes"), F.max("depth").alias("max_depth"))

    def nodes(self) -> DataFrame:
        """TREE_NODES: one row for each node."""
        zipped = F.posexplode(F.arrays_zip("feature", "threshold", "left", "right", "leaf_class")).alias("node", "n")
        return self.trees.select("tree_id", zipped).select("tree_id", "node", "n.feature", "n.threshold", "n.left", "n.right", "n.leaf_class")

    def save(self, path: str) -> MegaForest:
        self.trees.write.partitionBy("ens_part").parquet(f"{path}/trees")
        return save_manifest(self.trees.sparkSession, self.params, path)


def merge_ensembles(trees: DataFrame, params: ForestParams, path: str | None = None, mode: str = "reduce") -> MegaForest:
    """Trees by ensemble partition: only they are shuffled. ``mode="map"`` leaves them where they were fitted.

    The trees are written here, once: to ``path``, or else to the session's shared folder. Whatever scores the forest
    reads them, so that no block is fitted twice.
    """
    if mode == "reduce":
        trees = trees.repartitionById(params.n_parts, F.col("ens_part"))
    return MegaForest(trees, params).save(path) if path else MegaForest(written(trees, "trees"), params)


def save_manifest(spark: SparkSession, params: ForestParams, path: str) -> MegaForest:
    spark.createDataFrame([(params.n_parts, params.n_classes, list(params.features), params.as_map())], "n_parts int, n_classes int, features array<string>, params map<string,string>").write.mode("overwrite").parquet(f"{path}/manifest")
    return load(spark, path)


def load(spark: SparkSession, path: str) -> MegaForest:
    row = spark.read.parquet(f"{path}/manifest").first()
    p = row.params
    number = {k: int(p[k]) for k in ("n_trees", "bite_size", "min_leaf", "n_classes", "n_parts", "n_blocks", "seed")}
    maybe = {k: None if p[k] == "None" else int(p[k]) for k in ("max_depth", "n_attr")}
    learner = p["learner"] if p["learner"] in LEARNERS else "tree"  # a function can't be read back: only its trees are
    params = ForestParams(**number, **maybe, sampler=p["sampler"], unvoted=p["unvoted"], learner=learner, draws=p["draws"], replace=p["replace"] == "True", resample=p["resample"] == "True", features=tuple(row.features))
    names = [c.split()[0] for c in TREE.split(", ")]
    return MegaForest(spark.read.parquet(f"{path}/trees").select(*names), params)


def blocks_done(spark: SparkSession, path: str) -> set[int]:
    jpath = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/trees")
    if not jpath.getFileSystem(spark._jsc.hadoopConfiguration()).exists(jpath):
        return set()
    return {r.block for r in spark.read.parquet(f"{path}/trees").select("block").distinct().collect()}


def tree_columns() -> list:
    """What scoring needs of a tree, and the hash that orders members at random, the same in every engine."""
    return [portable_hash("permute", F.col("tree_id")).alias("place"), *map(F.col, ("ens_part", "block", "iter", "tree_id", "feature", "threshold", "left", "right", "leaf_class"))]


class Packed:
    """Trees in one set of arrays, in a fixed random order, so that rows at different trees move in step."""

    def __init__(self, table: pa.Table, n_classes: int):
        table = table.sort_by([("place", "ascending"), ("tree_id", "ascending")]).combine_chunks()
        flat = {c: pc.list_flatten(table[c]).to_numpy() for c in ("feature", "threshold", "left", "right", "leaf_class")}
        sizes = pc.list_value_length(table["feature"]).to_numpy().astype(np.int64)
        self.root = np.cumsum(sizes) - sizes
        base = np.repeat(self.root, sizes)
        self.feature, self.threshold = flat["feature"].astype(np.int32), flat["threshold"].astype(np.float64)
        self.left, self.right = flat["left"] + base, flat["right"] + base
        self.leaf_class, self.n_classes = flat["leaf_class"].astype(np.int32), n_classes
        self.part, self.block, self.iter, self.tree_id = (table[c].to_numpy() for c in ("ens_part", "block", "iter", "tree_id"))

    def __len__(self) -> int:
        return len(self.root)

    def tree(self, t: int) -> Tree:
        """One tree by itself."""
        nodes = slice(self.root[t], self.root[t + 1] if t + 1 < len(self) else len(self.feature))
        inside = [(child[nodes] - self.root[t]).astype(np.int32) for child in (self.left, self.right)]
        return Tree(self.feature[nodes], self.threshold[nodes], *inside, self.leaf_class[nodes], None, 0)

    def votes(self, x: np.ndarray, rows: np.ndarray, trees: np.ndarray) -> np.ndarray:
        """Class that tree ``trees[i]`` gives row ``rows[i]`` of x."""
        at = self.root[trees]
        active = np.flatnonzero(self.feature[at] >= 0)
        while len(active):
            node = at[active]
            small = x[rows[active], self.feature[node]] <= self.threshold[node]
            at[active] = np.where(small, self.left[node], self.right[node])
            active = active[self.feature[at[active]] >= 0]
        return self.leaf_class[at]


def pack(forest: MegaForest, max_mb: float = 512) -> Packed:
    """Collect a forest whose size is within ``max_mb``; larger ones are for committees. The forest keeps it for the next call."""
    kept = forest.__dict__.get("_packed")
    if kept is not None and kept[0] <= max_mb:
        return kept[1]
    mb = (forest.size().first().bytes or 0) / 1e6
    if mb > max_mb:
        raise ValueError(f"the forest has {mb:.0f} MB: score it by committee")
    packed = Packed(forest.trees.select(*tree_columns()).toArrow(), forest.params.n_classes)
    object.__setattr__(forest, "_packed", (mb, packed))
    return packed
