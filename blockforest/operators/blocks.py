"""Random blocks: the one time that rows move."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import fast_hash, portable_hash


#: Pieces that a group's rows are cut into for numbering.
_PIECES = 256


def numbered(df: DataFrame, group: list[str], piece: Column, order: list[Column], within: list[str]) -> DataFrame:
    """Rows with ``place``: their number from 0 in the order (group, piece, order), counted anew for every value of ``within``.

    Windows hold one piece of one group; only the counts of pieces meet, so no task gets all rows of a group. ``piece``
    must not fall along the order.
    """
    df = df.withColumn("_piece", piece)
    counts = df.groupBy(*group, "_piece").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy(*within).orderBy(*[g for g in group if g not in within], "_piece").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.select(*[F.col(g).alias(f"_{g}") for g in group], F.col("_piece").alias("_p"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    own = F.row_number().over(Window.partitionBy(*group, "_piece").orderBy(*order)) - 1
    on = [F.col(g).eqNullSafe(F.col(f"_{g}")) for g in group] + [F.col("_piece") == F.col("_p")]
    joined = df.withColumn("_own", own).join(counts, on)
    return joined.withColumn("place", F.col("_before") + F.col("_own")).drop("_piece", "_p", "_before", "_own", *[f"_{g}" for g in group])


def assign_blocks(df: DataFrame, n_blocks: int | None = None, rows_per_block: int | None = None, key: str = "row_id", seed: int = 42, portable: bool = True, stratify: str | None = None, mode: str = "random", by: str | None = None) -> DataFrame:
    """Rows with a column ``block``.

    ``random``: by a hash of the key, without a shuffle and the same in a task that runs again. ``stratify`` deals every
    class out evenly. ``sorted`` makes skewed blocks of ``by``, a column of few values, in the order of a numeric key (to show
    what random ones are for).
    """
    if n_blocks is None:
        if not rows_per_block:
            raise ValueError("give n_blocks or rows_per_block")
        n_blocks = max(1, -(-df.count() // rows_per_block))
    hashed = (portable_hash if portable else fast_hash)(f"block-{seed}", F.col(key))
    if mode == "sorted":
        facts = df.agg(F.count(F.lit(1)).alias("n"), F.percentile_approx(key, [i / _PIECES for i in range(1, _PIECES)], 10_000).alias("edges")).first()
        edges = F.array(*[F.lit(e) for e in sorted(set(facts.edges or []))]).cast("array<bigint>")
        ranked = numbered(df, [by], F.size(F.filter(edges, lambda e: e <= F.col(key))), [F.col(key)], [])
        size, larger = divmod(facts.n, n_blocks)
        place, cut = F.col("place"), larger * (size + 1)
        block = F.when(place < cut, F.floor(place / (size + 1))).otherwise(larger + F.floor((place - cut) / max(size, 1)))
        return ranked.withColumn("block", block.cast("int")).drop("place")
    if stratify:
        ranked = numbered(df, [stratify], F.shiftrightunsigned(hashed, 24), [hashed, F.col(key)], [stratify])
        return ranked.withColumn("block", F.pmod(F.col("place"), F.lit(n_blocks)).cast("int")).drop("place")
    return df.withColumn("block", F.pmod(hashed, F.lit(n_blocks)).cast("int"))


def partition_by_block(df: DataFrame, n_blocks: int, column: str = "block") -> DataFrame:
    """One partition for each block, exactly: block numbers are partition numbers, and small ones aren't merged."""
    return df.repartitionById(n_blocks, F.col(column))


def block_balance(df: DataFrame, label: str = "label") -> DataFrame:
    """Per block: rows, share of each class minus the overall share (largest), chi-square against equal shares."""
    cells, rows = df.groupBy("block", label).agg(F.count(F.lit(1)).alias("n")), df.count()
    blocks, classes = Window.partitionBy("block"), Window.partitionBy(label)
    full = cells.select("block", label, "n", F.sum("n").over(blocks).alias("size"), F.sum("n").over(classes).alias("of_class"))
    expected = F.col("size") * F.col("of_class") / F.lit(rows)
    return full.groupBy("block").agg(
        F.max("size").cast("long").alias("rows"),
        F.round(F.max(F.abs(F.col("n") / F.col("size") - F.col("of_class") / F.lit(rows))), 8).alias("max_deviation"),
        F.round(F.sum((F.col("n") - expected) * (F.col("n") - expected) / expected), 6).alias("chi_square"),
    )
