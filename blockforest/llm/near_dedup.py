"""Near-duplicate groups by circulant MinHash, with every link confirmed on whole shingle sets.

Steps; all but the fourth are proportional to the input:

1. One pass makes each document's shingle set, its 128-bit digest and its band keys. All coordinates of
   the signature come from two permutations of a 32-bit universe: the first scatters the shingles, the
   second is used again and again, shifted circularly by the coordinate's number.
2. Documents with equal sets collapse to the one with the smallest id.
3. A bucket (band, key) of several such documents links them to two pivots; sets are compared exactly.
4. Buckets that still hold more than one component after that are compared across components, in blocks
   of bounded size, so a large bucket is dealt over many tasks. Documents outside the bucket's largest component meet
   every block: where many documents share a band by chance and are not alike, that is their number times the blocks.
5. Links make components; the smallest id of a component is kept.

With the defaults (30 bands of 4) a pair at similarity 0.8 is missed with probability below 2e-7.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._tables import components, cut, drop_cut
from ._text import BLANK_SEPARATED, RollingHash, chunks, lower_ascii, map_batches, mix64, signed, word_bounds

#: Shingles that the indexed side of one comparison block holds.
BLOCK_SHINGLES = 1 << 20


def shingle_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """Distinct hashes of a document's k-word shingles, sorted; the whole sequence if it is shorter."""
    n = len(words)
    if n == 0:
        return np.zeros(0, np.uint64)
    width = min(k, n)
    acc = np.zeros(n - width + 1, np.uint64)
    for i in range(width):
        acc = mix64(acc + words[i : n - width + 1 + i], i)
    return np.unique(mix64(acc, 100 + width))


def document_sets(column: pa.Array, k: int) -> Iterator[np.ndarray]:
    """The shingle set of every text of a column, in order."""
    for first, end, data, offsets in chunks(column):
        data = lower_ascii(data)
        start, stop, bound = word_bounds(data, offsets, BLANK_SEPARATED)
        words = RollingHash(data, 1).of(start, stop)
        for row in range(end - first):
            yield shingle_hashes(words[bound[row] : bound[row + 1]], k)


def _second_permutation(x: np.ndarray) -> np.ndarray:
    """A bijection of 32-bit words, in place."""
    x ^= x >> np.uint32(16)
    x *= np.uint32(0x7FEB352D)
    x ^= x >> np.uint32(15)
    x *= np.uint32(0x846CA68B)
    x ^= x >> np.uint32(16)
    return x


def signature(shingles: np.ndarray, size: int) -> np.ndarray:
    """Circulant MinHash: coordinate s is the minimum of the second permutation shifted by s."""
    scattered = (mix64(shingles, 7) >> np.uint64(32)).astype(np.uint32)
    shift = np.arange(size, dtype=np.uint32)[:, None]
    out = np.full(size, 0xFFFFFFFF, np.uint32)
    for at in range(0, len(scattered), 4096):
        out = np.minimum(out, _second_permutation(scattered[None, at : at + 4096] - shift).min(axis=1))
    return out


def band_keys(sig: np.ndarray, bands: int) -> np.ndarray:
    rows = sig.reshape(bands, -1).astype(np.uint64)
    acc = np.arange(bands, dtype=np.uint64)
    for j in range(rows.shape[1]):
        acc = mix64(acc + rows[:, j], j)
    return acc


def _sign(batches, k: int, bands: int, rows: int):
    for batch in batches:
        n, d1, d2, keys = [], [], [], []
        for u in document_sets(batch.column(1), k):
            n.append(len(u))
            d1.append(mix64(u, 11).sum() if len(u) else np.uint64(0))
            d2.append(mix64(u, 12).sum() if len(u) else np.uint64(0))
            keys.append(signed(band_keys(signature(u, bands * rows), bands)) if len(u) else np.zeros(0, np.int64))
        offsets = np.cumsum([0, *map(len, keys)])
        flat = np.concatenate(keys) if keys else np.zeros(0, np.int64)
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(n, pa.int64()), pa.array(signed(np.array(d1, np.uint64))), pa.array(signed(np.array(d2, np.uint64))), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(flat))],
            names=["id", "n_shingles", "d1", "d2", "bands"],
        )


def _sets(batches, k: int):
    for batch in batches:
        sets = list(document_sets(batch.column(1), k))
        offsets = np.cumsum([0, *map(len, sets)])
        flat = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(signed(flat)))], names=["id", "shingles"])


class _Index:
    """Postings of the indexed side of one block."""

    def __init__(self, ids: list[int], groups: list[int], sets: list[np.ndarray]):
        self.ids, self.groups = np.array(ids, np.int64), np.array(groups, np.int64)
        self.sizes = np.array([len(s) for s in sets])
        flat = np.concatenate(sets)
        order = np.argsort(flat, kind="stable")
        self._values, self._owner = flat[order], np.repeat(np.arange(len(ids)), self.sizes)[order]

    def partners(self, doc: int, group: int, shingles: np.ndarray, percent: int) -> np.ndarray:
        lo, hi = np.searchsorted(self._values, shingles, "left"), np.searchsorted(self._values, shingles, "right")
        n = hi - lo
        total = int(n.sum())
        if not total:
            return self.ids[:0]
        at = np.repeat(lo - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(total)
        common = np.bincount(self._owner[at], minlength=len(self.ids))
        union = self.sizes + len(shingles) - common
        return self.ids[(100 * common >= percent * union) & (common > 0) & (self.groups != group) & (self.ids != doc)]


def _compare(batches, percent: int):
    """Rows sorted by (grp, blk, role): role 0 is indexed, role 1 is held against the index; links go out."""
    key, index, ids, groups, sets = None, None, [], [], []
    for batch in batches:
        a, b = [], []
        cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(5)]
        lists = batch.column(5)
        values, bounds = lists.values.to_numpy(), lists.offsets.to_numpy()
        for i in range(batch.num_rows):
            grp, blk, role, doc, group = (c[i] for c in cols)
            if key != (grp, blk):
                key, index, ids, groups, sets = (grp, blk), None, [], [], []
            one = values[bounds[i] : bounds[i + 1]]
            if role == 0:
                ids.append(doc), groups.append(group), sets.append(one.copy())
            elif ids:
                index = index or _Index(ids, groups, sets)
                found = index.partners(doc, group, one, percent)
                a.extend([doc] * len(found))
                b.extend(found.tolist())
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])


def confirmed_links(rows: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) among rows ``(grp, blk, role, doc, comp, shingles)`` whose similarity reaches ``percent``."""
    rows = rows.select("grp", "blk", "role", "doc", "comp", "shingles").repartition("grp", "blk").sortWithinPartitions("grp", "blk", "role", "doc")
    return map_batches(rows, partial(_compare, percent=percent), "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 5, percent: int = 80, bands: int = 30, rows: int = 4) -> DataFrame:
    """One row per document: ``id_col, n_shingles, component_id, kept``.

    Texts are lower-cased (A-Z) and cut into words at ASCII blanks. Documents without words (null or
    empty texts too) have an empty set and are linked with nothing. A row with a null id has a null
    component and is kept. Repeated rows of one id count as one node of the graph, and all are kept or none.
    Other columns are ignored, whatever their names. An empty table gives an empty result.
    """
    source = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    signed_docs = cut(map_batches(source, partial(_sign, k=k, bands=bands, rows=rows), "id long, n_shingles long, d1 long, d2 long, bands array<long>"))
    known = signed_docs.where("id is not null and n_shingles > 0")
    reps = known.groupBy("d1", "d2", "n_shingles").agg(F.min("id").alias("id"))
    nodes = known.join(reps, ["d1", "d2", "n_shingles", "id"], "left_semi").dropDuplicates(["id", "d1", "d2"])
    filed = nodes.select("id", "n_shingles", F.posexplode("bands").alias("band", "key")).select("id", "n_shingles", F.xxhash64("band", "key").alias("bucket"))
    # Two pivots for a bucket: the smallest id, and the smallest after its bits are turned by the bucket's own hash. What joins meet
    # by a hot key is written first: both sides are then plain exchanges, which adaptive execution splits.
    turned = F.xxhash64("bucket")
    pivots = filed.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("p1"), F.min(F.col("id").bitwiseXOR(turned)).alias("p2")).where("n > 1")
    pivots = cut(pivots.select("bucket", "p1", F.col("p2").bitwiseXOR(turned).alias("p2")))
    shared = cut(filed.join(pivots, "bucket"))
    stars = shared.select("id", F.explode(F.array("p1", "p2")).alias("pivot")).where("id <> pivot")
    stars = cut(stars.select(F.greatest("id", "pivot").alias("member"), F.least("id", "pivot").alias("pivot")).distinct())
    wanted = shared.select("id").distinct()
    sets = cut(map_batches(source.join(wanted, "id", "left_semi"), partial(_sets, k=k), "id long, shingles array<long>"))

    # 1st comparison: members against their pivots; a pivot of many members is copied to several tasks.
    load = stars.groupBy("pivot").agg(F.ceil(F.count(F.lit(1)) / 256).alias("blocks"))
    load = cut(load)
    against = stars.join(load, "pivot").join(sets, stars.member == sets.id).select(F.col("pivot").alias("grp"), F.pmod(F.xxhash64("member"), "blocks").cast("int").alias("blk"), F.lit(1).alias("role"), F.col("member").alias("doc"), F.col("member").alias("comp"), "shingles")
    heads = load.join(sets, load.pivot == sets.id).select(F.col("pivot").alias("grp"), F.explode(F.sequence(F.lit(0), (F.col("blocks") - 1).cast("int"))).alias("blk"), F.lit(0).alias("role"), F.col("pivot").alias("doc"), F.col("pivot").alias("comp"), "shingles")
    first = cut(confirmed_links(against.unionByName(heads), percent))
    found = components(first)

    # 2nd: buckets in which several components are left, all members against those outside the largest one.
    placed = shared.select("id", "bucket", "n_shingles").join(found, shared.id == found.node, "left").select("bucket", "id", "n_shingles", F.coalesce("component", "id").alias("comp"))
    sizes = placed.groupBy("bucket", "comp").agg(F.count(F.lit(1)).alias("n"), F.sum("n_shingles").alias("load"))
    open_buckets = sizes.groupBy("bucket").agg(F.count(F.lit(1)).alias("comps"), F.max(F.struct("n", "comp")).alias("main"), F.sum("load").alias("load")).where("comps > 1")
    open_buckets = cut(open_buckets.select("bucket", F.col("main.comp").alias("main"), F.ceil(F.col("load") / BLOCK_SHINGLES).alias("blocks")))
    rest = cut(placed.join(open_buckets, "bucket").select("bucket", "id", "comp", "main", "blocks"))
    block = F.pmod(F.xxhash64("id"), "blocks").cast("int")
    indexed = rest.select("bucket", block.alias("blk"), F.lit(0).alias("role"), "id", "comp")
    queried = rest.where("comp <> main").select("bucket", F.explode(F.sequence(F.lit(0), (F.col("blocks") - 1).cast("int"))).alias("blk"), F.lit(1).alias("role"), "id", "comp")
    both = indexed.unionByName(queried).join(sets, "id").select(F.col("bucket").alias("grp"), "blk", "role", F.col("id").alias("doc"), "comp", "shingles")
    links = first.union(confirmed_links(both, percent)).distinct()
    final = components(links)

    classes = cut(reps.join(final, reps.id == final.node, "left").select("d1", "d2", F.col("n_shingles").alias("n"), F.coalesce("component", "id").alias("component")))
    for table in (pivots, shared, stars, load, sets, first, found, open_buckets, rest, final):
        drop_cut(table)
    s = signed_docs.drop("bands")
    out = s.join(classes, (s.d1 == classes.d1) & (s.d2 == classes.d2) & (s.n_shingles == classes.n) & (s.n_shingles > 0), "left")
    component = F.when(s.id.isNotNull(), F.coalesce("component", s.id))
    return out.select(s.id.alias(id_col), s.n_shingles, component.alias("component_id"), component.eqNullSafe(s.id).alias("kept"))


def op4_circulant_minhash(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return near_duplicates(docs, k=4, percent=80)
