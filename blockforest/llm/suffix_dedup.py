"""Removal of long repeated passages with suffix arrays made by induced sorting.

The job is exact for every repeat of ``width`` bytes anywhere in the corpus, and moves little of it:

1. Every window of ``width`` bytes is filed under its anchor, the smallest hash of a short byte run inside
   it, so equal windows share an anchor. Neighbouring windows with one anchor form a segment; only its place
   and two hashes travel. Anchors that occur once in the corpus can't hold a repeat and end here.
2. Equal segments (128-bit hash) are one: the first in corpus order stays, all others are repeats.
3. Different segments under one anchor repeat each other in part. Their bytes go to shards, whole anchors
   together; an anchor with very many different segments is dealt over several shards.
4. A shard is one string. Its suffix array comes from induced sorting, its longest common prefixes from the
   permuted form; runs of suffixes that agree on ``width`` bytes give the windows that start earlier elsewhere.
5. Windows of anchors dealt over several shards meet once more, one row for each shard and distinct window.
"""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._tables import cut, drop_cut
from ._text import RollingHash, chunks, map_batches, signed, utf8

#: Bytes of an anchor's short run.
ANCHOR_BYTES = 24
#: Bytes of text in one suffix array.
SHARD_BYTES = 1 << 20
#: Different segments of one anchor in a shard.
SEGMENTS_PER_SHARD = 2000
#: Windows of one text that are cut into segments at once (below 2^28).
SLICE_BYTES = 16 << 20


# -- suffix array ---------------------------------------------------------------------------------------


def _types(s: np.ndarray) -> np.ndarray:
    """True where a suffix is smaller than the next one (S-type); the sentinel is S-type."""
    n = len(s)
    out = np.ones(n, bool)
    if n > 1:
        step = np.flatnonzero(s[1:] != s[:-1])  # there is one before the sentinel
        rise = s[step] < s[step + 1]
        out[:-1] = rise[np.searchsorted(step, np.arange(n - 1))]
    return out


def _by_bucket(buckets: np.ndarray) -> np.ndarray:
    """Stable order by bucket number, linear: counting passes over 16 bits each (numpy's stable sort of such numbers)."""
    if buckets.dtype == np.uint16:
        return np.argsort(buckets, kind="stable")
    order = np.argsort(buckets.astype(np.uint16), kind="stable")
    return order[np.argsort((buckets[order] >> 16).astype(np.uint16), kind="stable")]


def _fill(buckets: np.ndarray, place: np.ndarray, step: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(places, order, buckets in order) of suffixes put into their buckets one after another, from each one's pointer on."""
    order = _by_bucket(buckets)
    b = buckets[order]
    first = np.flatnonzero(b[1:] != b[:-1]) + 1
    rank = np.arange(len(b))
    rank[first[0] if len(first) else len(b) :] -= np.repeat(first, np.diff(first, append=len(b)))
    return place[b] + (rank if step > 0 else -rank), order, b


def _sweep(s: np.ndarray, sa: np.ndarray, place: np.ndarray, wanted: np.ndarray, step: int) -> None:
    """One pass over the array: each suffix met puts the one before it, if of the wanted type, into its bucket.

    Suffixes are taken in stretches. A suffix lands behind the one that it comes from; where one lands inside the stretch,
    the stretch ends there, so every place is filled before it is read. Where stretches get short (in runs of one
    character the suffixes follow each other place by place), some places are taken one by one.
    """
    n, at, width = len(sa), 0 if step > 0 else len(sa) - 1, 1024
    while 0 <= at < n:
        if width < 32:
            stop = min(max(at + step * 512, -1), n)
            for p in range(at, stop, step):
                j = sa[p] - 1
                if j >= 0 and wanted[j]:
                    c = s[j]
                    sa[place[c]] = j
                    place[c] += step
            at, width = stop, 256
            continue
        size = min(width, n - at if step > 0 else at + 1)
        met = sa[at : at + size] if step > 0 else sa[at - size + 1 : at + 1][::-1]
        source = np.flatnonzero(met > 0)
        pred = met[source] - 1
        right = wanted[pred]
        source, pred = source[right], pred[right]
        reach = size
        if len(pred):
            where, order, buckets = _fill(s[pred], place, step)
            reach = min(size, int(where.min()) - at if step > 0 else at - int(where.max()))
            if reach < size:
                now = source[order] < reach
                where, order, buckets = where[now], order[now], buckets[now]
            sa[where] = pred[order]
            place[buckets] = where + step  # the last one of each bucket stays
        width = min(2 * width, 1 << 16) if reach == size else 2 * reach
        at += step * reach


def _induce(s: np.ndarray, is_s: np.ndarray, lms: np.ndarray, count: np.ndarray) -> np.ndarray:
    """All suffixes from the leftmost-smaller ones: larger types forward, then smaller types backward."""
    n = len(s)
    end = np.cumsum(count)
    sa = np.full(n, -1, np.int32)
    where, order, _ = _fill(s[lms], end - np.bincount(s[lms], minlength=len(count)), 1)
    sa[where] = lms[order]
    _sweep(s, sa, end - count, ~is_s, 1)
    sa[(sa >= 0) & is_s[sa]] = -1  # these come again, in their final order
    _sweep(s, sa, end - 1, is_s, -1)
    sa[0] = n - 1
    return sa


def suffix_array(s: np.ndarray) -> np.ndarray:
    """Suffix array of integers that end with a 0 found nowhere else, by induced sorting; linear for any alphabet.

    Suffixes are classified; the leftmost-smaller (LMS) substrings are sorted by a first induction and named;
    the string of names is sorted recursively; a second induction from the LMS suffixes gives the array.
    """
    n = len(s)
    if n == 1:
        return np.zeros(1, np.int32)
    s = s.astype(np.uint16 if s.max() < 1 << 16 else np.int32, copy=False)
    is_s = _types(s)
    count = np.bincount(s)
    lms = np.flatnonzero(is_s[1:] & ~is_s[:-1]) + 1
    first = _induce(s, is_s, lms, count)
    marked = np.zeros(n, bool)
    marked[lms] = True
    ordered = first[marked[first]]
    nth = np.full(n, 0, np.int64)
    nth[lms] = np.arange(len(lms))
    stop = np.append(lms[1:], n - 1)  # an LMS substring ends with the next LMS position
    left, right = ordered[:-1], ordered[1:]
    length = stop[nth[ordered]] - ordered
    new = np.ones(len(ordered), bool)
    same = np.flatnonzero(length[1:] == length[:-1])
    depth = 0
    while len(same):  # compare neighbours of equal length, character by character
        a, b = left[same] + depth, right[same] + depth
        equal = s[a] == s[b]
        done = length[same + 1] == depth
        new[same[equal & done] + 1] = False
        same = same[equal & ~done]
        depth += 1
    name = np.cumsum(new) - 1
    reduced = np.empty(len(lms), np.int64)
    reduced[nth[ordered]] = name
    if name[-1] + 1 < len(lms):
        ordered = lms[suffix_array(reduced)]
    return _induce(s, is_s, ordered, count)


def permuted_lcp(s: np.ndarray, sa: np.ndarray) -> np.ndarray:
    """For every position, the characters that its suffix shares with the one before it in the array.

    Only positions whose preceding characters differ are compared; any other has one less than its left
    neighbour.
    """
    n = len(s)
    before = np.full(n, -1, np.int64)
    before[sa[1:]] = sa[:-1]
    at = np.arange(n)
    known = (at == 0) | (before <= 0)
    known[1:] |= (before[1:] <= 0) | (s[at[1:] - 1] != s[before[1:] - 1])
    out = np.zeros(n, np.int64)
    padded = np.concatenate([s.astype(np.uint8), np.zeros(16, np.uint8)])
    words = np.lib.stride_tricks.as_strided(padded.view(np.uint8), (n + 8, 8), (1, 1))
    todo = np.flatnonzero(known & (before >= 0))
    shift = np.zeros(len(todo), np.int64)
    while len(todo):
        a, b = todo + shift, before[todo] + shift
        live = (a < n) & (b < n)
        a, b = np.minimum(a, n), np.minimum(b, n)
        equal = words[a] == words[b]
        whole = equal.all(axis=1) & live
        ends = ~whole
        out[todo[ends]] = np.minimum(shift[ends] + np.where(live[ends], equal[ends].argmin(axis=1), 0), n - np.maximum(todo[ends], before[todo[ends]]))
        todo, shift = todo[whole], shift[whole] + 8
    source = np.maximum.accumulate(np.where(known, at, 0))
    return np.maximum(out[source] - (at - source), 0)


# -- segments -------------------------------------------------------------------------------------------


def _sliding_min(v: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every window of ``width`` values: block-wise prefix and suffix minima."""
    n = len(v)
    full = -(-n // width) * width
    p = np.full(full, np.uint64(0xFFFFFFFFFFFFFFFF))
    p[:n] = v
    blocks = p.reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    back = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[: n - width + 1], ahead[width - 1 : n])


def chunk_segments(data: np.ndarray, offsets: np.ndarray, width: int):
    """(row, start in the row, windows, anchor, segment hash) of the segments of a run of rows.

    A very long text is taken in slices of ``SLICE_BYTES`` windows: a segment across a border is two segments.
    """
    if len(data) <= SLICE_BYTES + width:
        return _slice_segments(data, offsets, width)
    parts = []
    for at in range(0, len(data), SLICE_BYTES):
        stop = min(at + SLICE_BYTES + width - 1, len(data))
        own = np.clip(offsets, at, stop) - at
        row, start, size, anchor, whole = _slice_segments(data[at:stop], own, width)
        parts.append((row, start + np.maximum(at - offsets[row], 0), size, anchor, whole))
    return tuple(np.concatenate(p) for p in zip(*parts, strict=True))


def _slice_segments(data: np.ndarray, offsets: np.ndarray, width: int):
    n = len(data)
    if n < width:
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),) * 2
    reach = width - ANCHOR_BYTES + 1
    at = np.arange(n - ANCHOR_BYTES + 1)
    gram = RollingHash(data, 3).of(at, at + ANCHOR_BYTES)
    bits = np.uint64(28)  # places inside a slice are smaller
    low = _sliding_min((gram >> bits << bits) | at.astype(np.uint64), reach)
    place = (low & np.uint64((1 << 28) - 1)).astype(np.int64)
    windows = n - width + 1
    row = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))[:windows]
    valid = np.arange(windows) + width <= offsets[1:][row]
    change = np.ones(windows, bool)
    change[1:] = (place[1:] != place[:-1]) | (row[1:] != row[:-1]) | (valid[1:] != valid[:-1])
    first = np.flatnonzero(change)
    size = np.diff(np.append(first, windows))
    keep = valid[first]
    first, size = first[keep], size[keep]
    whole = RollingHash(data, 4).of(first, first + size + width - 1)
    return row[first], first - offsets[:-1][row[first]], size, gram[place[first]], whole


def _segments(batches, width: int, anchors_only: bool):
    for batch in batches:
        for first, _, data, offsets in chunks(batch.column(1)):
            row, start, size, anchor, whole = chunk_segments(data, offsets, width)
            if anchors_only:
                yield pa.RecordBatch.from_arrays([pa.array(signed(anchor))], names=["anchor"])
            else:
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(row + first)), pa.array(start, pa.int32()), pa.array(size, pa.int32()), pa.array(signed(anchor)), pa.array(signed(whole))], names=["id", "start", "n", "anchor", "whole"])


def _cut_out(batches, width: int):
    """The bytes of listed segments of each text."""
    for batch in batches:
        data, offsets = utf8(batch.column(1))
        lists = batch.column(2)
        flat, bounds = lists.flatten(), np.diff(lists.offsets.to_numpy())
        row = np.repeat(np.arange(batch.num_rows), bounds)
        start, n = flat.field("start").to_numpy().astype(np.int64), flat.field("n").to_numpy().astype(np.int64)
        begin, stop = offsets[row] + start, offsets[row] + start + n + width - 1
        raw = data.tobytes() if len(row) else b""
        blobs = [raw[a:b] for a, b in zip(begin.tolist(), stop.tolist(), strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(row)), flat.field("start"), flat.field("anchor"), flat.field("part"), flat.field("shared"), pa.array(blobs, pa.binary())], names=["id", "start", "anchor", "part", "shared", "bytes"])


def shard_repeats(ids: np.ndarray, starts: np.ndarray, shared: np.ndarray, blobs: list[bytes], width: int):
    """Repeated windows inside a shard of different segments.

    Returns (segment, first window, windows) of runs that start earlier elsewhere in the shard, and
    (segment, window) of the earliest of each distinct window of segments whose anchor is dealt over shards.
    """
    length = np.array([len(b) for b in blobs], np.int64)
    text = np.frombuffer(b"\xff".join(blobs) + b"\xff", np.uint8)  # no byte of UTF-8
    s = np.empty(len(text) + 1, np.int64)
    s[:-1] = np.where(text == 0xFF, 1, text.astype(np.int64) + 2)
    s[-1] = 0
    sa = suffix_array(s)
    lcp = permuted_lcp(np.where(s > 255, 0, s), sa)[sa] if s.max() <= 255 else None
    begin = np.concatenate([[0], np.cumsum(length + 1)[:-1]])
    seg_of = np.repeat(np.arange(len(blobs)), length + 1)
    inside = np.arange(len(text)) - begin[seg_of]
    starts_window = np.append(inside + width <= length[seg_of], False)
    group = np.cumsum(lcp < width)
    ok = starts_window[sa]
    pos, group = sa[ok], group[ok]
    if not len(pos):
        return np.zeros((0, 3), np.int64), np.zeros((0, 2), np.int64)
    seg = seg_of[pos]
    doc = np.unique(ids, return_inverse=True)[1]
    order_key = (doc[seg].astype(np.int64) << 32) | (starts[seg] + inside[pos])
    head = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
    least = np.minimum.reduceat(order_key, head)
    repeat = order_key != np.repeat(least, np.diff(np.append(head, len(pos))))
    flagged = np.sort(pos[repeat])
    new = np.flatnonzero(np.concatenate([[True], np.diff(flagged) != 1])) if len(flagged) else np.zeros(0, np.int64)
    runs = np.stack([seg_of[flagged[new]], inside[flagged[new]], np.diff(np.append(new, len(flagged)))], axis=1) if len(flagged) else np.zeros((0, 3), np.int64)
    firsts = np.unique(pos[~repeat & shared[seg]])
    return runs, np.stack([seg_of[firsts], inside[firsts]], axis=1)


def _shards(batches, width: int):
    """Rows come sorted by (anchor, part); whole groups of them are gathered up to the size of a shard."""
    ids, starts, shared, blobs, size, last = [], [], [], [], 0, None

    def flush():
        i, a, d = np.array(ids), np.array(starts, np.int64), np.array(shared, bool)
        runs, firsts = shard_repeats(i, a, d, blobs, width)
        text = np.frombuffer(b"".join(blobs), np.uint8)
        base = np.concatenate([[0], np.cumsum([len(b) for b in blobs])[:-1]]).astype(np.int64)
        at = base[firsts[:, 0]] + firsts[:, 1]
        w = [RollingHash(text, k).of(at, at + width) if len(at) else np.zeros(0, np.uint64) for k in (5, 6)]
        seg = np.concatenate([runs[:, 0], firsts[:, 0]])
        return pa.RecordBatch.from_arrays(
            [pa.array(i[seg]), pa.array(a[seg] + np.concatenate([runs[:, 1], firsts[:, 1]]), pa.int32()), pa.array(np.concatenate([runs[:, 2], np.ones(len(firsts), np.int64)]), pa.int32()), pa.array(np.arange(len(seg)) < len(runs)), *(pa.array(signed(np.concatenate([np.zeros(len(runs), np.uint64), x]))) for x in w)],
            names=["id", "start", "n", "repeat", "w1", "w2"],
        )

    for batch in batches:
        rows = batch.to_pydict()
        for row in zip(*(rows[c] for c in ("id", "start", "anchor", "part", "shared", "bytes")), strict=True):
            if size >= SHARD_BYTES and last != row[2:4]:
                yield flush()
                ids, starts, shared, blobs, size = [], [], [], [], 0
            last = row[2:4]
            ids.append(row[0]), starts.append(row[1]), shared.append(row[4]), blobs.append(row[5])
            size += len(row[5])
    if blobs:
        yield flush()


def _keep(batches, width: int):
    """Rows (id, text, ranges of repeated windows) to the bytes that stay."""
    for batch in batches:
        data, offsets = utf8(batch.column(1))
        spans, kept = [], []
        for row, ranges in enumerate(batch.column(2).to_pylist()):
            n, merged = int(offsets[row + 1] - offsets[row]), []
            for r in sorted((r["start"], r["start"] + r["n"] + width - 1) for r in ranges or ()):
                a, b = min(r[0], n), min(r[1], n)
                if merged and a <= merged[-1][1]:
                    merged[-1][1] = max(merged[-1][1], b)
                elif a < b:
                    merged.append([a, b])
            raw = data[offsets[row] : offsets[row + 1]].tobytes()
            at, out = 0, []
            for a, b in merged:
                out.append(raw[at:a])
                at = b
            out.append(raw[at:])
            spans.append([{"start": a, "end": b} for a, b in merged])
            kept.append(b"".join(out))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.diff(offsets), pa.int64()), pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), pa.array(kept, pa.binary())], names=["id", "n_bytes", "removed", "kept"])


def repeated_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 100) -> DataFrame:
    """One row per document: ``id_col, n_bytes, removed array<struct<start,end>>, kept binary`` (UTF-8 bytes).

    A byte is removed if a string of ``width`` bytes that covers it starts earlier too: in a document with a
    smaller id, or in the same one further left. Matches stay inside documents; all are judged on the input.
    Null and empty texts have no bytes. Ids are meant to be unique: rows with equal id and text get equal
    results, rows that share an id but not the text get the ranges of either. Rows with a null id are left
    as they are, and are no earlier copy of others. Other columns are ignored, whatever their names. An empty table
    gives an empty result. Texts of any length are taken whole; a very long one passes through a worker in slices.
    """
    if not 64 <= width <= 4096:
        raise ValueError("width must be 64 to 4096 bytes")
    source = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    long_enough = source.where(F.col("id").isNotNull() & (F.octet_length("text") >= width))
    # Tables that joins meet by a hot key are written first: both sides are then plain exchanges, which adaptive execution splits.
    anchors = map_batches(long_enough, partial(_segments, width=width, anchors_only=True), "anchor long").groupBy("anchor").agg(F.count(F.lit(1)).alias("c")).where("c > 1").select("anchor")
    anchors = cut(anchors)
    segments = map_batches(long_enough, partial(_segments, width=width, anchors_only=False), "id long, start int, n int, anchor long, whole long")
    repeated = cut(segments.join(anchors, "anchor"))
    # Segments by content, the first in corpus order first.
    contents = repeated.groupBy("anchor", "whole").agg(F.min(F.struct("id", "start", "n")).alias("first"))
    contents = cut(contents.select("anchor", "whole", F.col("first.id").alias("id"), F.col("first.start").alias("start"), F.col("first.n").alias("n")))
    later = repeated.join(contents.select("anchor", "whole", F.col("id").alias("fid"), F.col("start").alias("fstart")), ["anchor", "whole"]).where("id <> fid or start <> fstart").select("id", "start", "n")
    # Different segments of one anchor go to shards.
    load = contents.groupBy("anchor").agg(F.ceil(F.count(F.lit(1)) / SEGMENTS_PER_SHARD).alias("parts"), F.count(F.lit(1)).alias("c")).where("c > 1").select("anchor", "parts")
    load = cut(load)
    mixed = contents.join(load, "anchor").select("id", F.struct("start", "n", "anchor", F.pmod("whole", "parts").cast("int").alias("part"), (F.col("parts") > 1).alias("shared")).alias("s"))
    listed = mixed.groupBy("id").agg(F.collect_list("s").alias("list"))
    pieces = map_batches(source.join(listed, "id").select("id", "text", "list"), partial(_cut_out, width=width), "id long, start int, anchor long, part int, shared boolean, bytes binary")
    dealt = pieces.repartition("anchor", "part").sortWithinPartitions("anchor", "part")
    found = cut(map_batches(dealt, partial(_shards, width=width), "id long, start int, n int, repeat boolean, w1 long, w2 long"))
    inside = found.where("repeat").select("id", "start", "n")
    across = found.where("not repeat")
    earliest = across.groupBy("w1", "w2").agg(F.min(F.struct("id", "start")).alias("first"), F.count(F.lit(1)).alias("c")).where("c > 1")
    met = across.join(earliest, ["w1", "w2"]).where("id <> first.id or start <> first.start").select("id", "start", F.lit(1).alias("n"))
    ranges = cut(later.unionAll(inside).unionAll(met).groupBy("id").agg(F.collect_list(F.struct("start", "n")).alias("ranges")))
    for table in (anchors, repeated, contents, load, found):
        drop_cut(table)
    out = source.join(ranges, "id", "left").select("id", "text", "ranges")
    out = map_batches(out, partial(_keep, width=width), "id long, n_bytes long, removed array<struct<start:long,end:long>>, kept binary")
    return out.withColumnRenamed("id", id_col)


def op5_induced_suffix_array(spark, sf_dir: str) -> DataFrame:
    out = repeated_passages(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    removed = F.aggregate("removed", F.lit(0).cast("long"), lambda acc, r: acc + r["end"] - r["start"])
    return out.select("doc_id", "n_bytes", removed.alias("n_removed"), F.size("removed").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))
