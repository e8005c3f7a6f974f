"""Full and lazy evaluation of a mega-forest, and lazy evaluation of given votes in DataFrame operations."""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import derive_seed, fast_hash, portable_hash
from ..functions.stopping import RULES, Rule, table_literal, threshold_table
from .compact import Walk, column_pieces
from .features import features_of, is_compact
from .model import MegaForest, Packed, pack
from .sampling import leaders
from .schemas import PREDICTION
from .train import matrix


def full_tallies(packed: Packed, x: np.ndarray) -> np.ndarray:
    """Votes by row and class, one tree after another over all rows."""
    votes = np.zeros((len(x), packed.n_classes), np.int64)
    rows = np.arange(len(x))
    for t in range(len(packed)):
        votes[rows, packed.votes(x, rows, np.full(len(x), t))] += 1
    return votes


def keyed_place(keys: np.ndarray, step: int, size: int) -> np.ndarray:
    """Element ``step`` of a permutation of 0..size-1 that belongs to each key, without the rest of it.

    Four rounds over two halves of the bits permute the next power of four; places beyond ``size`` are permuted again.
    """
    half = max(1, (max(size - 1, 1).bit_length() + 1) // 2)
    mask = np.uint64((1 << half) - 1)
    out, todo = np.full(len(keys), step, np.uint64), np.arange(len(keys))
    while len(todo):
        left, right, key = out[todo] >> np.uint64(half), out[todo] & mask, keys[todo].astype(np.uint64)
        for turn in range(4):
            z = (right + key + np.uint64(turn * 0x9E3779B9)) * np.uint64(0xBF58476D1CE4E5B9)
            z = (z ^ (z >> np.uint64(31))) * np.uint64(0x94D049BB133111EB)
            left, right = right, left ^ ((z ^ (z >> np.uint64(29))) & mask)
        out[todo] = left << np.uint64(half) | right
        todo = todo[out[todo] >= size]
    return out.astype(np.int64)


def lazy_votes(packed: Packed, x: np.ndarray, rule: Rule, offset: np.ndarray | None, order: str = "offset", seed: int = 0, members: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(tallies, votes used, stopped) of all rows; rows that stop leave the active set.

    ``offset``: members in a fixed random order, every row from a place of its own, around the ring. ``random``: a fresh
    permutation for each row. ``batch``: one offset for all. ``members`` limits the vote to a committee; the rule still
    speaks about all ``rule.m``.
    """
    ring = np.arange(len(packed)) if members is None else members
    size, n = len(ring), len(x)
    tally = np.zeros((n, packed.n_classes), np.int64)
    used, stopped = np.zeros(n, np.int64), np.zeros(n, bool)
    if not size or not n:
        return tally, used, stopped
    binary = packed.n_classes == 2
    leads = threshold_table(rule) if binary else None
    if order == "random":
        keys = np.random.default_rng(seed).integers(0, 1 << 62, n)
    elif order == "batch":
        offset = np.full(n, int(np.random.default_rng(seed).integers(size)))
    active = np.arange(n)
    for step in range(1, size + 1):
        place = keyed_place(keys[active], step - 1, size) if order == "random" else (offset[active] + step - 1) % size
        tally[active, packed.votes(x, active, ring[place])] += 1
        used[active] = step
        if step == rule.m:
            break
        if binary:
            done = tally[active].max(axis=1) >= leads[step]
        else:
            done = rule.stops_tallies(tally[active], step)
        stopped[active[done]] = True
        active = active[~done]
        if not len(active):
            break
    return tally, used, stopped


def _prediction_batch(ids, tally, used, stopped, stage: str) -> pa.RecordBatch:
    total = np.maximum(tally.sum(axis=1), 1)
    return pa.RecordBatch.from_arrays([ids, pa.array(tally.argmax(axis=1), pa.int32()), pa.array(used, pa.int32()), pa.array(stopped), pa.array(tally.max(axis=1) / total), pa.array([stage] * len(used), pa.string())], names=[c.split()[0] for c in PREDICTION.split(", ")])


def _full(batches, packed):
    for batch in batches:
        x = matrix(batch.column(1))
        tally = full_tallies(packed.value, x)
        yield _prediction_batch(batch.column(0), tally, np.full(len(x), len(packed.value)), np.zeros(len(x), bool), "full")


def _lazy(batches, packed, rule, order, seed, also_full):
    p: Packed = packed.value
    for k, batch in enumerate(batches):
        x = matrix(batch.column(1))
        offset = batch.column(2).to_numpy() % max(len(p), 1)
        batch_seed = derive_seed(seed, k, int(offset[0]) if len(offset) else 0)
        tally, used, stopped = lazy_votes(p, x, rule, offset, order, batch_seed)
        out = _prediction_batch(batch.column(0), tally, used, stopped, "lazy")
        if also_full:
            whole = full_tallies(p, x)
            out = pa.RecordBatch.from_arrays([*out.columns, pa.array(whole.argmax(axis=1), pa.int32())], names=[*out.schema.names, "full_prediction"])
        yield out


def _inputs(df: DataFrame) -> DataFrame:
    return df.select(F.col("row_id").cast("long").alias("row_id"), features_of(df))


def predict_full(forest: MegaForest, df: DataFrame, max_mb: float = 512) -> DataFrame:
    """PREDICTION rows by the votes of all trees; ties go to the lowest class."""
    packed = df.sparkSession.sparkContext.broadcast(pack(forest, max_mb))
    return _inputs(df).mapInArrow(partial(_full, packed=packed), PREDICTION)


def predict_lazy(forest: MegaForest, df: DataFrame, rule: str = "g1_fpc", alpha: float = 0.01, min_votes: int | None = None, order: str = "offset", seed: int = 7, also_full: bool = False, max_mb: float = 512, multi: str = "pairwise", portable: bool = False) -> DataFrame:
    """PREDICTION rows by as many votes as the rule asks for; ``also_full`` adds the full vote's class beside it.

    ``multi`` is the Bayesian rule's way with over two classes (see ``Rule``); ``portable`` offsets are the same in SQL engines.
    """
    packed = pack(forest, max_mb)
    chosen = Rule(rule, max(len(packed), 1), alpha, min_votes, multi)
    shared = df.sparkSession.sparkContext.broadcast(packed)
    rows = _inputs(df).withColumn("offset", (portable_hash if portable else fast_hash)(f"offset-{seed}", F.col("row_id")))
    return rows.mapInArrow(partial(_lazy, packed=shared, rule=chosen, order=order, seed=seed, also_full=also_full), PREDICTION + (", full_prediction int" if also_full else ""))


def _by_tree(batches, packed):
    p: Packed = packed.value
    for batch in batches:
        x, n = matrix(batch.column(1)), batch.num_rows
        trees = np.tile(np.arange(len(p)), n)
        votes = p.votes(x, np.repeat(np.arange(n), len(p)), trees)
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(batch.column(0).to_numpy(), len(p))), pa.array(p.tree_id[trees]), pa.array(votes, pa.int32())], names=["row_id", "tree_id", "vote"])


def votes_by_tree(forest: MegaForest, df: DataFrame, max_mb: float = 512) -> DataFrame:
    """``row_id, tree_id, vote``: the vote of every tree on every row."""
    packed = df.sparkSession.sparkContext.broadcast(pack(forest, max_mb))
    return _inputs(df).mapInArrow(partial(_by_tree, packed=packed), "row_id long, tree_id long, vote int")


def _batches_with_votes(batches, p: Packed, narrow: bool):
    """(labels, a function that gives the votes of tree t) for some rows at a time; compact rows are taken column by column."""
    if not narrow:
        for batch in batches:
            x = matrix(batch.column(1))
            yield batch.column(2).to_numpy(), partial(lambda t, x: p.votes(x, np.arange(len(x)), np.full(len(x), t)), x=x)
        return
    walks = [Walk(p.tree(t)) for t in range(len(p))]
    for piece, held in column_pieces(batches):
        yield np.concatenate([b.column(2).to_numpy() for b in held]), lambda t, piece=piece: piece.predict(walks[t])


def _parts_right(batches, packed, masks, narrow):
    p: Packed = packed.value
    for y, vote in _batches_with_votes(batches, p, narrow):
        votes = np.zeros((len(masks), p.n_classes, len(y)), np.int32)
        for t in range(len(p)):
            c = vote(t)
            for g, mask in enumerate(masks):
                if mask[t]:
                    for k in range(p.n_classes):
                        votes[g, k] += c == k
        right = [int((leaders(v.T) == y).sum()) for v in votes]
        yield pa.RecordBatch.from_arrays([pa.array(range(len(masks)), pa.int32()), pa.array(right, pa.int64()), pa.array([len(y)] * len(masks), pa.int64())], names=["part", "correct", "n"])


def accuracy_of_parts(packed: Packed, masks: list[np.ndarray], test: DataFrame) -> DataFrame:
    """``part, correct, n`` of several choices of trees (masks over the packed ones), from one scan of the test rows."""
    shared = test.sparkSession.sparkContext.broadcast(packed)
    rows = test.select(F.col("row_id").cast("long").alias("row_id"), features_of(test), F.col("label").cast("int").alias("label"))
    return rows.mapInArrow(partial(_parts_right, packed=shared, masks=masks, narrow=is_compact(test)), "part int, correct long, n long").groupBy("part").agg(F.sum("correct").alias("correct"), F.sum("n").alias("n"))


def accuracy_grid(forest: MegaForest, test: DataFrame, grid: list[tuple[int, int]]) -> DataFrame:
    """``blocks, local_size, trees, accuracy`` of every (blocks, local size) prefix of a forest, from one scan of the test rows."""
    packed = pack(forest)
    masks = [(packed.block < q) & (packed.iter < k) for q, k in grid]
    cells = test.sparkSession.createDataFrame([(i, q, k, int(m.sum())) for i, ((q, k), m) in enumerate(zip(grid, masks, strict=True))], "part int, blocks int, local_size int, trees long")
    return accuracy_of_parts(packed, masks, test).join(F.broadcast(cells), "part").select("blocks", "local_size", "trees", (F.col("correct") / F.col("n")).alias("accuracy"))


# -- given votes, in DataFrame operations -----------------------------------------------------------------


def tally_votes(votes: DataFrame) -> DataFrame:
    """``row_id, vote, n``: partial counts before the shuffle."""
    return votes.groupBy("row_id", "vote").agg(F.count(F.lit(1)).alias("n"))


def majority(tallies: DataFrame) -> DataFrame:
    """``row_id, prediction``: most votes, ties to the lowest class."""
    return tallies.groupBy("row_id").agg(F.max_by("vote", F.struct("n", -F.col("vote"))).alias("prediction"))


def offset_order(votes: DataFrame, m: int, offset: Column, place: Column) -> DataFrame:
    """Position of every vote when a row starts at its offset on the ring of members."""
    return votes.withColumn("pos", F.pmod(place - offset, F.lit(m)) + 1)


def lazy_from_votes(votes: DataFrame, rule: Rule, n_classes: int = 2) -> DataFrame:
    """Lazy evaluation of a table ``row_id, pos, vote``: running tallies in position order, the first stop wins.

    Binary votes meet integer thresholds; with more classes the leader meets the runner-up.
    """
    running = Window.partitionBy("row_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    tallies = votes.select("row_id", "pos", *[F.sum((F.col("vote") == c).cast("int")).over(running).alias(f"t{c}") for c in range(n_classes)])
    arr = F.array(*[F.col(f"t{c}") for c in range(n_classes)])
    ranked = F.sort_array(arr, asc=False)
    tallies = tallies.select("row_id", "pos", ranked[0].alias("top"), ranked[1].alias("second"), (F.array_position(arr, F.array_max(arr)) - 1).cast("int").alias("leader"))
    tallies = tallies.withColumn("stop", stop_column(rule, F.col("top"), F.col("second"), F.col("pos")))
    order = F.struct(~F.col("stop"), F.when(F.col("stop"), F.col("pos")).otherwise(-F.col("pos")))
    return tallies.groupBy("row_id").agg(F.min_by("leader", order).alias("prediction"), F.min_by("pos", order).cast("int").alias("votes_used"), (F.max(F.col("stop").cast("int")) == 1).alias("stopped_early"))


def stop_column(rule: Rule, top: Column, second: Column, n: Column) -> Column:
    """Does the vote end after n votes? (before the last one)"""
    kind, _, fpc = RULES[rule.name]
    if kind == "certain":
        stop = top > second + (rule.m - n)
    elif kind == "bayes":
        stop = top >= F.element_at(table_literal(rule), n.cast("int"))
    elif kind == "full":
        stop = F.lit(False)
    else:
        import math

        from ..functions.stopping import correction_column

        pair = (top + second).cast("double")
        if kind == "chernoff":
            need = F.floor(pair * (0.5 + F.sqrt(F.lit(math.log(1 / rule.alpha)) / (2.0 * pair)))) + 1
        else:
            rho = correction_column(n, rule.m) if fpc else F.lit(1.0)
            c = F.lit(rule.square()) * rho * rho / pair
            need = F.floor(pair * (0.5 + 0.5 * F.sqrt(c / (1.0 + c)))) + 1
        stop = top >= need
    return (n >= rule.least) & (n < rule.m) & stop
