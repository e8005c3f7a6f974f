"""Committee evaluation: a part of the ensemble answers most rows, the whole of it the rest, one part at a time."""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import fast_hash, portable_hash
from ..functions.stopping import Rule
from ..sources.tables import written
from .model import MegaForest, Packed, tree_columns
from .scoring import full_tallies, lazy_votes
from .train import matrix

_ROW = "row_id long, prediction int, votes_used int, stopped_early boolean, leader_share double, features array<double>"


def replicate(df: DataFrame, p: int, column: str = "ens_part") -> DataFrame:
    """Every row p times, once for each ensemble partition."""
    return df.withColumn(column, F.explode(F.sequence(F.lit(0), F.lit(p - 1))))


_TREE = ("place", "block", "iter", "tree_id", "feature", "threshold", "left", "right", "leaf_class")


def _past_partitions(batches, work, n_classes: int):
    """Groups come sorted, the trees of an ensemble partition first: its rows stream past them, batch by batch."""
    key, parts, packed = None, [], None
    for batch in batches:
        part, group, role = (batch.column(c).to_numpy() for c in ("ens_part", "grp", "role"))
        turn = np.flatnonzero((np.diff(part) != 0) | (np.diff(group) != 0) | (np.diff(role) != 0)) + 1
        for a, b in zip([0, *turn.tolist()], [*turn.tolist(), batch.num_rows], strict=True):
            if a == b:
                continue
            if key != (part[a], group[a]):
                key, parts, packed = (part[a], group[a]), [], None
            piece = batch.slice(a, b - a)
            if role[a] == 0:
                parts.append(piece.select(["ens_part", *_TREE]))
                continue
            if packed is None:
                packed, parts = Packed(pa.Table.from_batches(parts, piece.select(["ens_part", *_TREE]).schema), n_classes), []
            yield work(packed, piece)


def default_groups(forest: MegaForest) -> int:
    """Groups that the rows of an ensemble partition are dealt to: two tasks for each core in all."""
    return max(1, -(-2 * forest.trees.sparkSession.sparkContext.defaultParallelism // forest.params.n_parts))


def meet_partitions(forest: MegaForest, rows: DataFrame, work, schema: str, groups: int) -> DataFrame:
    """Rows ``(row_id, ens_part, grp, offset, features)`` and the trees of their ensemble partition, in one exchange.

    A partition's trees are copied to each of its ``groups``, whose number follows the cluster and not the rows. A task holds
    one partition of the ensemble and one batch of rows, however many rows a group has.
    """
    empty = {"block": "int", "iter": "int", "place": "bigint", "feature": "array<int>", "threshold": "array<double>", "left": "array<int>", "right": "array<int>", "leaf_class": "array<int>"}
    none = lambda kind: F.lit(None).cast(kind)
    every = F.explode(F.sequence(F.lit(0), F.lit(groups - 1))).alias("grp")
    trees = forest.trees.select(*tree_columns()).select("*", every).select("ens_part", "grp", F.lit(0).alias("role"), *_TREE, none("bigint").alias("row_id"), none("bigint").alias("offset"), none("array<double>").alias("features"))
    data = rows.select("ens_part", "grp", F.lit(1).alias("role"), *[F.col("row_id").alias(c) if c == "tree_id" else none(empty[c]).alias(c) for c in _TREE], "row_id", "offset", "features")
    dealt = trees.unionByName(data).repartition("ens_part", "grp").sortWithinPartitions("ens_part", "grp", "role", "tree_id")
    return dealt.mapInArrow(partial(_past_partitions, work=work, n_classes=forest.params.n_classes), schema)


def _judge(packed: Packed, rows: pa.RecordBatch, rule: Rule) -> pa.RecordBatch:
    """Rows dealt to an ensemble partition take its votes as long as the rule asks for them."""
    x = matrix(rows.column("features"))
    tally, used, stopped = lazy_votes(packed, x, rule, rows.column("offset").to_numpy() % max(len(packed), 1))
    if len(packed) == rule.m:
        stopped = np.ones(len(x), bool)  # the committee is the ensemble
    share = tally.max(axis=1) / np.maximum(tally.sum(axis=1), 1)
    features = pc.if_else(pa.array(stopped), pa.scalar(None, rows.column("features").type), rows.column("features"))
    return pa.RecordBatch.from_arrays([rows.column("row_id"), pa.array(tally.argmax(axis=1), pa.int32()), pa.array(used, pa.int32()), pa.array(stopped), pa.array(share), features], names=[c.split()[0] for c in _ROW.split(", ")])


def committee_pass(forest: MegaForest, df: DataFrame, rule: str = "g1_fpc", alpha: float = 0.01, m: int | None = None, seed: int = 3, groups: int | None = None, min_votes: int | None = None, portable: bool = False) -> DataFrame:
    """Every row is judged lazily by one ensemble partition, chosen by hash; the rule speaks about the whole ensemble.

    ``portable`` takes hashes that every SQL engine has.
    """
    p, m = forest.params.n_parts, m or forest.trees.count()
    hashed, groups = portable_hash if portable else fast_hash, groups or default_groups(forest)
    rows = df.select(F.col("row_id").cast("long").alias("row_id"), F.col("features").cast("array<double>").alias("features"))
    rows = rows.select("row_id", "features", F.pmod(hashed(f"committee-{seed}", F.col("row_id")), F.lit(p)).cast("int").alias("ens_part"), F.pmod(fast_hash("group", F.col("row_id")), F.lit(groups)).cast("int").alias("grp"), hashed(f"offset-{seed}", F.col("row_id")).alias("offset"))
    return meet_partitions(forest, rows, partial(_judge, rule=Rule(rule, m, alpha, min_votes)), _ROW, groups)


def _votes(ids, tally: np.ndarray) -> pa.RecordBatch:
    n, k = tally.shape
    return pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, k), pa.int64()), pa.array(np.tile(np.arange(k), n), pa.int32()), pa.array(tally.ravel(), pa.int64())], names=["row_id", "vote", "n"])


def _tally(packed: Packed, rows: pa.RecordBatch) -> pa.RecordBatch:
    out = _votes(rows.column("row_id").to_numpy(), full_tallies(packed, matrix(rows.column("features"))))
    return pa.RecordBatch.from_arrays([rows.column("ens_part").take(pa.array(np.repeat(np.arange(rows.num_rows), packed.n_classes))), *out.columns], names=["ens_part", *out.schema.names])


def partition_tallies(forest: MegaForest, undecided: DataFrame, groups: int | None = None) -> DataFrame:
    """``ens_part, row_id, vote, n`` of every ensemble partition for every undecided row; the rows are dealt over many groups."""
    groups = groups or default_groups(forest)
    rows = replicate(undecided.select("row_id", "features"), forest.params.n_parts).withColumn("grp", F.pmod(fast_hash("group", F.col("row_id")), F.lit(groups)).cast("int")).withColumn("offset", F.lit(0).cast("long"))
    return meet_partitions(forest, rows, _tally, "ens_part int, row_id long, vote int, n long", groups)


def _meet(batches, shared, n_classes: int):
    """Batches of trees meet all undecided rows."""
    ids, x = shared.value
    for batch in batches:
        yield _votes(ids, full_tallies(Packed(pa.Table.from_batches([batch]), n_classes), x))


def tallies_by_broadcast(forest: MegaForest, undecided: DataFrame, max_mb: float = 64) -> DataFrame:
    """``row_id, vote, n`` for few undecided rows: these are broadcast, and the trees stay where they are.

    Rows of more than ``max_mb`` in all get their tallies from ``partition_tallies``.
    """
    rows = undecided.select(F.col("row_id").cast("long").alias("row_id"), F.col("features").cast("array<double>").alias("features"))
    bytes_ = rows.agg(F.coalesce(F.sum(F.size("features") * 8 + 8), F.lit(0))).first()[0]
    if bytes_ > max_mb * 1e6:
        return partition_tallies(forest, undecided).drop("ens_part")
    some = rows.toArrow().combine_chunks()
    features = some["features"].combine_chunks()
    x = matrix(features.chunk(0) if isinstance(features, pa.ChunkedArray) else features) if some.num_rows else np.zeros((0, 0))
    shared = forest.trees.sparkSession.sparkContext.broadcast((some["row_id"].to_numpy(), x))
    return forest.trees.select(*tree_columns()).mapInArrow(partial(_meet, shared=shared, n_classes=forest.params.n_classes), "row_id long, vote int, n long")


def sum_tallies(tallies: DataFrame) -> DataFrame:
    """``row_id, prediction, votes, leader_share`` over all partitions; partial sums before the shuffle."""
    summed = tallies.groupBy("row_id", "vote").agg(F.sum("n").alias("n"))
    return summed.groupBy("row_id").agg(F.max_by("vote", F.struct("n", -F.col("vote"))).alias("prediction"), F.sum("n").alias("votes"), (F.max("n") / F.sum("n")).alias("leader_share"))


def union_of_stages(first: DataFrame, tallies: DataFrame) -> DataFrame:
    """PREDICTION rows: those that a committee decided, and the others by the sum of all partitions' votes."""
    decided = first.where("stopped_early").select("row_id", "prediction", "votes_used", "stopped_early", "leader_share", F.lit("committee").alias("stage"))
    rest = sum_tallies(tallies)
    return decided.unionByName(rest.select("row_id", "prediction", F.col("votes").cast("int").alias("votes_used"), F.lit(False).alias("stopped_early"), "leader_share", F.lit("full").alias("stage")))


def committee_predict(forest: MegaForest, df: DataFrame, rule: str = "g1_fpc", alpha: float = 0.01, seed: int = 3, strategy: str = "replicate", **options) -> DataFrame:
    """PREDICTION rows that cover the input once. The first pass is written, since both stages read it."""
    first = written(committee_pass(forest, df, rule, alpha, seed=seed, **options))
    ask = tallies_by_broadcast if strategy == "broadcast_rows" else partition_tallies
    return union_of_stages(first, ask(forest, first.where("not stopped_early")))


def committee_stats(predictions: DataFrame) -> DataFrame:
    """``rows, undecided, undecided_rate, mean_votes``."""
    late = (F.col("stage") == "full").cast("int")
    return predictions.agg(F.count(F.lit(1)).alias("rows"), F.sum(late).alias("undecided"), F.avg(late).alias("undecided_rate"), F.avg("votes_used").alias("mean_votes"))
