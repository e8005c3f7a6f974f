"""Training in one pass: every block fits its own ensemble, and only trees leave it."""

from __future__ import annotations

from contextlib import contextmanager
from dataclasses import replace
from functools import partial, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import fast_hash, portable_number
from ..sources.tables import shared_path, write_blocks, written
from . import model as store
from .blocks import assign_blocks, partition_by_block
from .compact import Rows, dense, pack_rows, parts_of
from .ensemble import fit_local_ensemble
from .features import features_of
from .schemas import TREE, ForestParams, check

_ARROW = pa.schema([
    ("ens_part", pa.int32()), ("tree_id", pa.int64()), ("block", pa.int32()), ("iter", pa.int32()), ("seed", pa.int64()), ("feature", pa.list_(pa.int32())), ("threshold", pa.list_(pa.float64())),
    ("left", pa.list_(pa.int32())), ("right", pa.list_(pa.int32())), ("leaf_class", pa.list_(pa.int32())), ("class_counts", pa.list_(pa.int32())), ("n_train", pa.int32()), ("depth", pa.int32()),
    ("n_nodes", pa.int32()), ("oob_error", pa.float64()), ("pool_fallback", pa.bool_()), ("fit_ms", pa.int64()),
])
#: Trees that share a number range: ids are block * this + iteration.
TREES_PER_BLOCK = 1_000_000


def matrix(column) -> np.ndarray:
    """A features column as one dense matrix."""
    return dense(*parts_of(column))


def _fit_blocks(batches, params: ForestParams):
    """A partition may hold several blocks; a block's rows are put in the order of ids here, since sorting them in Spark
    spills whole blocks to disk.
    """
    blocks: dict[int, Rows] = {}
    for batch in batches:
        block, y, ids = batch.column(0).to_numpy(), batch.column(2).to_numpy(), batch.column(3).to_numpy()
        numbers, ones, width = parts_of(batch.column(1))
        for b in np.unique(block):
            mine = block == b
            blocks.setdefault(int(b), Rows()).add(ids[mine], numbers[mine], ones[mine], width, y[mine])
    for block in sorted(blocks):
        yield _fit_block(block, blocks.pop(block), params)


def _fit_packed(batches, params: ForestParams, bites: tuple[int, ...]):
    """The partition holds one block, put together by ``pack_rows``; its number names the bite size."""
    held, block = Rows(), None
    for batch in batches:
        for k, packed in zip(batch.column(0), batch.column(1), strict=True):
            block = k.as_py()
            held.add_packed(memoryview(packed.as_buffer()))
    if block is not None:
        yield _fit_block(block, held, replace(params, bite_size=bites[block]))


def _fit_block(block: int, held: Rows, params: ForestParams) -> pa.RecordBatch:
    x, y = held.done()
    rows = []
    for i, seed, tree, facts in fit_local_ensemble(x, y, params, block):
        part = portable_number(f"part-{params.seed}", f"{block}:{i}") % params.n_parts
        rows.append({"ens_part": part, "tree_id": block * TREES_PER_BLOCK + i, "block": block, "iter": i, "seed": seed, "feature": tree.feature, "threshold": tree.threshold, "left": tree.left, "right": tree.right, "leaf_class": tree.leaf_class, "class_counts": tree.counts.ravel(), "depth": tree.depth, "n_nodes": len(tree.feature)} | facts)
    return pa.RecordBatch.from_pylist(rows, schema=_ARROW)


def train_blocks(df: DataFrame, params: ForestParams, slot: str = "block", n_slots: int | None = None) -> DataFrame:
    """TREE rows of all blocks of ``(row_id, features, label, block)``: one exchange of rows; their order is fixed by ids.

    ``slot`` names the column whose numbers (below ``n_slots``) are the partitions, if only some blocks are there.
    """
    check(df, "row_id", "features", "label", "block")
    dealt = partition_by_block(df.select(F.col(slot).alias("slot"), "block", features_of(df), F.col("label").cast("int").alias("label"), F.col("row_id").cast("long").alias("row_id")), n_slots or params.n_blocks, "slot")
    return dealt.select("block", "features", "label", "row_id").mapInArrow(partial(_fit_blocks, params=params), TREE)


def train_mega_forest(df: DataFrame, params: ForestParams, path: str | None = None, block_sample: int | None = None) -> store.MegaForest:
    """Blocks, local ensembles and their union. ``block_sample`` drops blocks before the shuffle (accuracy flattens early)."""
    blocked = df if "block" in df.columns else assign_blocks(df, params.n_blocks, seed=params.seed)
    if block_sample:
        blocked = blocked.where(F.col("block") < block_sample)
    return store.merge_ensembles(train_blocks(blocked, params), params, path)


def train_serial(df: DataFrame, params: ForestParams, block: int = 0) -> store.MegaForest:
    """Baseline: the forest of a single block, in a single task."""
    blocked = df if "block" in df.columns else assign_blocks(df, params.n_blocks, seed=params.seed)
    return store.merge_ensembles(train_blocks(blocked.where(F.col("block") == block), params), params)


def train_in_waves(df: DataFrame, params: ForestParams, path: str, wave: int = 1000) -> store.MegaForest:
    """Blocks in waves, each appended to the model: a run that is cut off goes on with the blocks that are missing.

    Rows are written by block once, so a wave reads its own blocks only and makes no more partitions than it has blocks.
    """
    spark = df.sparkSession
    done = store.blocks_done(spark, path)
    todo = [b for b in range(params.n_blocks) if b not in done]
    if todo:
        blocked = df if "block" in df.columns else assign_blocks(df, params.n_blocks, seed=params.seed)
        blocks = shared_path(spark, "blocks")
        write_blocks(blocked.where(F.col("block").isin(todo)) if done else blocked, blocks)
        dealt = spark.read.parquet(blocks)
    for at in range(0, len(todo), wave):
        now = todo[at : at + wave]
        part = dealt.where(F.col("block").isin(now)).withColumn("slot", (F.array_position(F.array(*map(F.lit, now)), F.col("block")) - 1).cast("int"))
        train_blocks(part, params, slot="slot", n_slots=len(now)).write.mode("append").partitionBy("ens_part").parquet(f"{path}/trees")
    return store.save_manifest(spark, params, path)


def train_until_plateau(df: DataFrame, params: ForestParams, validation: DataFrame, start: int = 1, tolerance: float = 1e-3) -> tuple[store.MegaForest, list[tuple[int, float]]]:
    """Doubles the number of blocks until validation accuracy gains less than ``tolerance``; every block is fitted once."""
    from .scoring import predict_full

    blocked = assign_blocks(df, params.n_blocks, seed=params.seed)
    seen: list[tuple[int, float]] = []
    q, forest = start, None
    while True:
        low = seen[-1][0] if seen else 0
        grown = store.merge_ensembles(train_blocks(blocked.where((F.col("block") >= low) & (F.col("block") < q)), params), replace(params, n_blocks=q - low))
        forest = grown if forest is None else forest.union(grown)
        share = predict_full(forest, validation).join(validation.select("row_id", "label"), "row_id").agg(F.avg((F.col("prediction") == F.col("label")).cast("double"))).first()[0]
        seen.append((q, share))
        if q >= params.n_blocks or (len(seen) > 1 and seen[-1][1] - seen[-2][1] < tolerance):
            return forest, seen
        q = min(2 * q, params.n_blocks)


def salt(df: DataFrame, k: int, key: str = "row_id", column: str = "block") -> DataFrame:
    """Split every block into k (for blocks that are too large for a worker)."""
    return df.withColumn(column, (F.col(column) * k + F.pmod(fast_hash("salt", F.col(key)), F.lit(k))).cast("int"))


@contextmanager
def _with_conf(spark: SparkSession, **values: str):
    """Settings of Spark SQL that hold in here; ``__`` stands for a dot."""
    conf = {f"spark.sql.{k.replace('__', '.')}": v for k, v in values.items()}
    before = {k: spark.conf.get(k, None) for k in conf}
    try:
        for k, v in conf.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def tune_bite_size(df: DataFrame, sizes: list[int], params: ForestParams, validation: DataFrame, block: int = 0) -> DataFrame:
    """``bite_size, accuracy, nodes, fit_ms``: the local ensemble of one block at several bite sizes.

    The block is put together once, column by column, and written; every size is fitted in a task of its own that reads it.
    The validation rows stay where they are and meet all sizes' trees in one scan.
    """
    from .scoring import accuracy_of_parts

    blocked = df if "block" in df.columns else assign_blocks(df, params.n_blocks, seed=params.seed)
    check(blocked, "row_id", "features", "label", "block")
    rows = blocked.where(F.col("block") == block).select(F.col("row_id").cast("long").alias("row_id"), features_of(blocked), F.col("label").cast("int").alias("label"))
    one = written(rows.mapInArrow(pack_rows, "rows binary"), "blocks")
    slowest_first = sorted(range(len(sizes)), key=lambda i: -sizes[i])
    copies = [one.coalesce(1).select(F.lit(i).alias("block"), "rows").mapInArrow(partial(_fit_packed, params=params, bites=tuple(sizes)), TREE) for i in slowest_first]
    # Spark 4.1 would put copies of one partition each into a single task, one after another.
    with _with_conf(df.sparkSession, unionOutputPartitioning="false", execution__arrow__maxRecordsPerBatch="1"):
        forest = store.merge_ensembles(reduce(DataFrame.unionAll, copies), params)
    packed = store.pack(forest)
    shares = accuracy_of_parts(packed, [packed.block == i for i in range(len(sizes))], validation)
    facts = forest.trees.groupBy(F.col("block").alias("part")).agg(F.sum("n_nodes").cast("long").alias("nodes"), F.sum("fit_ms").alias("fit_ms"))
    size = F.element_at(F.array(*[F.lit(int(n)) for n in sizes]), F.col("part") + 1).cast("int")
    return shares.join(facts, "part").select(size.alias("bite_size"), (F.col("correct") / F.col("n")).alias("accuracy"), "nodes", "fit_ms")
