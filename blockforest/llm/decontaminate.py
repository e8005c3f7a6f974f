"""Benchmark decontamination: every test suffix is binary-searched in suffix arrays over shards of training text.

A shard is a run of whole documents. Its suffix array holds the suffixes of all words that some test item has (one that
begins with any other word sorts before every test suffix). Words are compared by their rank in the sorted test vocabulary;
rank 0 is a word that no test item has. Suffixes are ordered by as many words as a test window has: ranges of equal ones give
all verbatim occurrences of every window, and windows that follow each other in a document and in an item make up the longest
verbatim matches with their places. No row is shuffled: the cost is one scan, and only the test side is sent to tasks.
A test side above ``max_test_bytes`` is taken in slices of items, one scan and one broadcast at a time; what they find is
united row by row.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from ._tables import cut, drop_cut
from ._text import ALPHANUMERIC, RollingHash, chunks, lower_ascii, map_batches, word_bounds

#: Bytes of training text whose suffixes make one sorted shard.
SHARD_BYTES = 1 << 20


def hashed_words(column: pa.Array, limit: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, word hashes, index of each row's first word) for runs of rows."""
    for first, end, data, offsets in chunks(column, limit):
        data = lower_ascii(data)
        start, stop, bound = word_bounds(data, offsets, ALPHANUMERIC)
        yield first, end, RollingHash(data, 2).of(start, stop), bound


class TestSide:
    """Windows of the test items as sorted keys' bounds, and the sorted vocabulary."""

    __test__ = False

    def __init__(self, ids: list, texts: list, window: int):
        self.window, self.ids = window, ids
        words, items = [], []
        for first, end, hashes, bound in hashed_words(pa.array(texts, pa.string()), 64 << 20):
            for row in range(first, end):
                words.append(hashes[bound[row - first] : bound[row - first + 1]])
                items.append(row)
        self.vocabulary = np.unique(np.concatenate([*words, np.zeros(0, np.uint64)]))
        self.bits = 21 if len(self.vocabulary) + 1 < 1 << 21 else 32  # ranks of so many bits, as many as fit in 64
        ranks = [self.rank(w) for w in words]
        spans = [(i, at, min(window, len(r))) for i, r in zip(items, ranks, strict=True) if len(r) for at in range(len(r) - min(window, len(r)) + 1)]
        self.item = np.array([x[0] for x in spans], np.int64)
        self.start = np.array([x[1] for x in spans], np.int64)
        self.length = np.array([x[2] for x in spans], np.int64)
        padded = np.zeros((window, len(spans)), np.uint64)
        for n, (i, at, length) in enumerate(spans):
            padded[:length, n] = ranks[i][at : at + length]
        self.low = pack(padded, self.bits)
        for n, length in enumerate(self.length):
            padded[length:, n] = (1 << self.bits) - 1
        self.high = pack(padded, self.bits)

    def rank(self, hashes: np.ndarray) -> np.ndarray:
        if not len(self.vocabulary):
            return np.zeros(len(hashes), np.uint64)
        at = np.minimum(np.searchsorted(self.vocabulary, hashes), len(self.vocabulary) - 1)
        return np.where(self.vocabulary[at] == hashes, at + 1, 0).astype(np.uint64)


def pack(columns, bits: int) -> np.ndarray:
    """Columns of ranks as rows of 64-bit keys with the same order."""
    per_key, out = 64 // bits, []
    for j, column in enumerate(columns):
        if j % per_key == 0:
            out.append(np.zeros(len(column), np.uint64))
        out[-1] |= column << np.uint64(bits * (per_key - 1 - j % per_key))
    return np.stack(out, axis=1)


def _below(keys: np.ndarray, at: np.ndarray, wanted: np.ndarray, or_equal: bool) -> np.ndarray:
    """Is the key at each index smaller than (or equal to) the wanted one?"""
    less = np.zeros(len(at), bool)
    same = np.ones(len(at), bool)
    for j in range(keys.shape[1]):
        a, b = keys[at, j], wanted[:, j]
        less |= same & (a < b)
        same &= a == b
    return less | same if or_equal else less


def search(keys: np.ndarray, wanted: np.ndarray, or_equal: bool) -> np.ndarray:
    """For every wanted key, how many sorted keys are smaller (or equal): one binary search for all at once."""
    lo, hi = np.zeros(len(wanted), np.int64), np.full(len(wanted), len(keys), np.int64)
    while True:
        active = np.flatnonzero(lo < hi)
        if not len(active):
            return lo
        mid = (lo[active] + hi[active]) // 2
        go = _below(keys, mid, wanted[active], or_equal)
        lo[active[go]] = mid[go] + 1
        hi[active[~go]] = mid[~go]


def shard_occurrences(hashes: np.ndarray, bound: np.ndarray, test: TestSide) -> tuple[np.ndarray, np.ndarray]:
    """(word position in the shard, window) of every verbatim occurrence of a test window."""
    none = np.zeros(0, np.int64)
    if not len(test.item) or not len(hashes):
        return none, none
    ranks = test.rank(hashes)
    at = np.flatnonzero(ranks > 0)
    if not len(at):
        return none, none
    # the suffix array; ranks behind the document's end are 0
    end = np.repeat(bound[1:], np.diff(bound))[at]
    padded = np.concatenate([ranks, np.zeros(test.window, np.uint64)])
    keys = pack((np.where(at + i < end, padded[at + i], np.uint64(0)) for i in range(test.window)), test.bits)
    order = np.lexsort(keys.T[::-1])
    keys, suffix = keys[order], at[order]
    # binary search of every test suffix
    lo, hi = search(keys, test.low, False), search(keys, test.high, True)
    count = np.maximum(hi - lo, 0)
    where = np.repeat(lo - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(count.sum())
    return suffix[where], np.repeat(np.arange(len(test.item)), count)


def _maximal(row: np.ndarray, pos: np.ndarray, win: np.ndarray, test: TestSide) -> list[np.ndarray]:
    """Windows that follow each other in a document and in an item, as one match: row, item, its start, the document's, words."""
    item, start = test.item[win], test.start[win]
    order = np.lexsort((pos, pos - start, item, row))
    row, item, start, pos, length = row[order], item[order], start[order], pos[order], test.length[win][order]
    follows = (row[1:] == row[:-1]) & (item[1:] == item[:-1]) & (pos[1:] == pos[:-1] + 1) & (start[1:] == start[:-1] + 1)
    head = np.flatnonzero(np.concatenate([[True], ~follows])) if len(row) else np.zeros(0, np.int64)
    return [row[head], item[head], start[head], pos[head], np.diff(np.append(head, len(row))) + length[head] - 1]


def _scan(batches, test_side, ids_as: pa.DataType):
    test: TestSide = test_side.value
    ids = pa.array(test.ids, ids_as)
    for batch in batches:
        counts, hits, found = [], [], []
        for first, _, hashes, bound in hashed_words(batch.column(batch.num_columns - 1), SHARD_BYTES):
            pos, win = shard_occurrences(hashes, bound, test)
            row = np.searchsorted(bound, pos, "right") - 1
            mark = np.zeros(len(hashes) + 1, np.int64)
            np.add.at(mark, pos, 1)
            np.add.at(mark, pos + test.length[win], -1)
            hit = np.concatenate([[0], np.cumsum(np.cumsum(mark)[:-1] > 0)])
            counts.append(np.diff(bound))
            hits.append(hit[bound[1:]] - hit[bound[:-1]])
            runs = _maximal(row, pos - bound[row], win, test)
            runs[0] += first
            found.append(runs)
        nothing = np.zeros(0, np.int64)
        row, item, *places = (np.concatenate([f[k] for f in found] or [nothing]) for k in range(5))
        offsets = np.searchsorted(row, np.arange(batch.num_rows + 1))
        runs = pa.StructArray.from_arrays([ids.take(pa.array(item)), *(pa.array(x, pa.int64()) for x in places)], ["item_id", "item_start", "doc_start", "n_words"])
        columns = [pa.array(np.concatenate([*x, nothing]), pa.int64()) for x in (counts, hits)]
        yield pa.RecordBatch.from_arrays([*batch.columns[:-1], *columns, pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), runs)], names=[*batch.schema.names[:-1], "n_words", "n_hit", "matches"])


def _slices(bench: DataFrame, item_id: str, item_text: str, max_test_bytes: int) -> Iterator[tuple[list, list]]:
    """The test items in slices whose texts are within the limit, each collected by itself."""
    items = bench.select(F.col(item_id).alias("i"), F.col(item_text).cast("string").alias("t")).where("i is not null and t is not null").distinct()
    size = items.agg(F.coalesce(F.sum(F.octet_length("t")), F.lit(0))).first()[0]
    n = max(1, -(-2 * size // max_test_bytes) if size > max_test_bytes else 1)
    for k in range(n):
        part = items if n == 1 else items.where(F.pmod(F.xxhash64("i", "t"), F.lit(n)) == k)
        rows = part.sort("i", "t").collect()
        if rows or k == n - 1:
            yield [r.i for r in rows], [r.t for r in rows]


def _covered(matches: Column) -> Column:
    """Words inside any of the matches."""
    spans = F.array_sort(F.transform(matches, lambda m: F.struct(m["doc_start"].alias("a"), (m["doc_start"] + m["n_words"]).alias("b"))))
    begin = F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("to"))
    step = lambda acc, s: F.struct((acc["n"] + F.greatest(s["b"] - F.greatest(s["a"], acc["to"]), F.lit(0))).alias("n"), F.greatest(acc["to"], s["b"]).alias("to"))
    return F.aggregate(spans, begin, step, lambda acc: acc["n"])


def contamination(docs: DataFrame, bench: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = 10, max_test_bytes: int = 32 << 20) -> DataFrame:
    """One row per document: ``id_col, n_words, n_hit, items, matches``.

    A window is ``window`` consecutive words of an item, or a shorter item as a whole. ``n_hit`` counts the
    document's words inside any occurrence of a window, ``items`` lists the distinct ids of items with one (unsorted), and
    ``matches`` every verbatim match that can't be made longer: ``item_id, item_start, doc_start, n_words`` (in words).
    Null and empty texts have no words; items with a null id or text are no items, and repeated ones count once. Rows of
    documents are judged one by one, repeated ids and rows too; a null ``id_col`` is passed through. Empty tables
    and very long texts need no care. Other columns are ignored, whatever their names. The result does not depend
    on ``max_test_bytes``.
    """
    spark = docs.sparkSession
    ids_as = to_arrow_type(bench.schema[item_id].dataType)
    kinds = bench.schema[item_id].dataType.simpleString(), docs.schema[id_col].dataType.simpleString()
    found = f"n_words long, n_hit long, matches array<struct<item_id:{kinds[0]},item_start:long,doc_start:long,n_words:long>>"
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    numbered, base, more = None, None, []
    slices = _slices(bench, item_id, item_text, max_test_bytes)
    ahead = next(slices)
    while ahead:
        ids, texts = ahead
        ahead = next(slices, None)
        test = spark.sparkContext.broadcast(TestSide(ids, texts, window))
        scan = partial(_scan, test_side=test, ids_as=ids_as)
        if numbered is None and ahead is None:
            base = map_batches(source, scan, f"id {kinds[1]}, {found}")
            break
        # Rows get numbers once, so that what slices find meets row by row.
        numbered = numbered or cut(source.select("id", F.monotonically_increasing_id().alias("rn"), "text"))
        part = map_batches(numbered, scan, f"id {kinds[1]}, rn long, {found}")
        if base is None:
            base = cut(part)
        else:
            more.append(cut(part.where("n_hit > 0").select("rn", F.col("matches").alias("also"))))
        test.destroy()
    if more:
        drop_cut(numbered)
        rest = more[0]
        for part in more[1:]:
            rest = rest.unionAll(part)
        rest = rest.groupBy("rn").agg(F.flatten(F.collect_list("also")).alias("also"))
        base = base.join(rest, "rn", "left").withColumn("matches", F.when(F.col("also").isNull(), F.col("matches")).otherwise(F.concat("matches", "also")))
        base = base.withColumn("n_hit", F.when(F.col("also").isNull(), F.col("n_hit")).otherwise(_covered(F.col("matches"))))
    return base.select(F.col("id").alias(id_col), "n_words", "n_hit", F.array_distinct(F.col("matches.item_id")).alias("items"), "matches")


def longest_matches(docs: DataFrame, bench: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """Every verbatim match that can't be made longer, a row each: ``id_col, item_id, item_start, doc_start, n_words`` (in words)."""
    return contamination(docs, bench, id_col, **options).select(id_col, F.explode("matches").alias("m")).select(id_col, "m.*")


def op6_suffix_search(spark, sf_dir: str) -> DataFrame:
    docs, bench = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    out = contamination(docs, bench)
    names = F.array_sort(F.transform("items", lambda i: i.cast("string")))
    longest = F.coalesce(F.array_max(F.col("matches.n_words")), F.lit(0).cast("long"))
    return out.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join(names, ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"), longest.alias("longest_match"))


OP6_SQL = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (SELECT item_id, least(10, len(w)) AS n, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS i, w FROM b WHERE len(w) > 0),
win AS (SELECT DISTINCT item_id, n, i AS s, list_slice(w, i, i + n - 1) AS g FROM bw),
dw AS (SELECT doc_id, n, unnest(range(1, len(w) - n + 2)) AS i, w FROM d, (SELECT DISTINCT n FROM win) WHERE len(w) >= n),
dg AS (SELECT doc_id, n, i, list_slice(w, i, i + n - 1) AS g FROM dw),
hit AS (SELECT dg.doc_id, dg.i, dg.n, win.item_id, dg.i - win.s AS diagonal FROM dg JOIN win ON dg.n = win.n AND dg.g = win.g),
islands AS (SELECT doc_id, item_id, n, diagonal, i - row_number() OVER (PARTITION BY doc_id, item_id, diagonal ORDER BY i) AS island FROM hit),
longest AS (SELECT doc_id, max(words)::BIGINT AS longest_match FROM (SELECT doc_id, count(*) + max(n) - 1 AS words FROM islands GROUP BY doc_id, item_id, diagonal, island) GROUP BY doc_id),
covered AS (SELECT doc_id, count(DISTINCT p)::BIGINT AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM hit) GROUP BY doc_id),
items AS (SELECT doc_id, count(*)::BIGINT AS n_items, string_agg(s, ',' ORDER BY s) AS names FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS s FROM hit) GROUP BY doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated,
       coalesce(longest_match, 0)::BIGINT AS longest_match
FROM d LEFT JOIN covered USING (doc_id) LEFT JOIN items USING (doc_id) LEFT JOIN longest USING (doc_id)
"""
