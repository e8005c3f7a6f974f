"""Document fingerprints by consistent weighted sampling, in DataFrame functions only.

A document is a set of weighted terms (words with their counts). For each of ``size`` samples and each term
two gamma(2, 1) draws and a uniform one come from a hash of (term, sample) alone. They place the term's
weight on a grid of its own and give a rank; the term of the smallest rank, with its grid level, is the
sample. Two documents agree on a sample with the probability of their generalised Jaccard similarity
(sum of smaller weights over sum of larger weights), and identical documents always agree.

The rank is kept with the sample's identity in one 64-bit number, so a sample is a plain ``min`` that
aggregates in generated code; terms of one document never leave the partition that holds its text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ._tables import cut

#: Samples in a fingerprint: the standard error of a likeness is at most 0.0722.
SIZE = 48
#: Samples that one aggregation makes beside each other; more at once exceed what the JVM compiles well.
SAMPLES_PER_ROW = 8
_CODE_BITS = 16


def _uniform(h: Column, shift: int) -> Column:
    """21 bits of a hash as a number inside (0, 1)."""
    return (F.shiftrightunsigned(h, shift).bitwiseAND((1 << 21) - 1) + 0.5) / float(1 << 21)


def _draws(term: Column, sample: Column, j: int) -> list[Column]:
    """The draws of (term, sample), the same in every document: grid step r, grid offset beta, ln of c. Plain columns, since structs would box each number."""
    h = F.xxhash64(term, sample)
    h2 = F.xxhash64(h)
    r = -F.ln(_uniform(h, 0) * _uniform(h, 21))
    return [h.alias(f"h{j}"), r.alias(f"r{j}"), _uniform(h2, 42).alias(f"beta{j}"), F.ln(-F.ln(_uniform(h2, 0) * _uniform(h2, 21))).alias(f"lnc{j}")]


def _ranked(h: Column, r: Column, beta: Column, lnc: Column, ln_weight: Column) -> Column:
    """Rank and identity of a term's sample as one bigint; the smallest of a document is its sample."""
    level = F.floor(ln_weight / r + beta)
    rank = lnc - r * (level - beta + 1.0)
    # 47 bits of rank (weights below e^1900 can't leave the range), then the identity of (term, level).
    place = ((F.least(F.greatest(rank, F.lit(-2000.0)), F.lit(2000.0)) + 2000.0) * float(1 << 34)).cast("long")
    code = F.xxhash64(h, level).bitwiseAND((1 << _CODE_BITS) - 1)
    return F.when(ln_weight.isNotNull(), F.shiftleft(place, _CODE_BITS).bitwiseOR(code))


def _code(best: Column) -> Column:
    return F.lpad(F.lower(F.hex(best.bitwiseAND((1 << _CODE_BITS) - 1))), _CODE_BITS // 4, "0")


def fingerprints(texts: DataFrame, keys: list[str], bodies: dict[str, str], size: int = SIZE) -> DataFrame:
    """``keys`` and, for each entry name -> text column of ``bodies``, a fingerprint: 4 hex digits a sample.

    ``keys`` must tell all rows apart. If rows are dealt by the first key already, nothing is shuffled. Terms are
    runs of letters and digits of any script, in lower case; a text without one has a null fingerprint here, and
    a row without any is absent. Texts of one row share their draws, so unequal weights cost little more than one text.
    """
    names = list(bodies)
    parts = F.explode(F.array(*[F.struct(F.lit(i).alias("kind"), F.split(F.lower(F.col(bodies[n])), r"[^\p{L}\p{N}]+").alias("words")) for i, n in enumerate(names)])).alias("v")
    words = texts.select(*keys, parts).select(*keys, "v.kind", F.explode("v.words").alias("word")).where("word <> ''")
    weights = [F.ln(F.nullif(F.count_if(F.col("kind") == i), F.lit(0)).cast("double")).alias(f"w{i}") for i in range(len(names))]
    counted = words.select(*keys, "kind", F.xxhash64("word").alias("term")).groupBy(*keys, "term").agg(*weights)
    steps = -(-size // SAMPLES_PER_ROW)
    dealt = counted.select("*", F.explode(F.sequence(F.lit(0), F.lit(steps - 1))).alias("g"))
    drawn = dealt.select(*keys, "g", *[f"w{i}" for i in range(len(names))], *[c for j in range(SAMPLES_PER_ROW) for c in _draws(F.col("term"), F.col("g") * SAMPLES_PER_ROW + j, j)])
    mins = [F.min(_ranked(F.col(f"h{j}"), F.col(f"r{j}"), F.col(f"beta{j}"), F.col(f"lnc{j}"), F.col(f"w{i}"))).alias(f"m{i}_{j}") for i in range(len(names)) for j in range(SAMPLES_PER_ROW)]
    best = drawn.groupBy(*keys, "g").agg(*mins)
    pieces = best.select(*keys, F.struct("g", *[F.concat(*[_code(F.col(f"m{i}_{j}")) for j in range(SAMPLES_PER_ROW)]).alias(f"f{i}") for i in range(len(names))]).alias("piece"))
    whole = pieces.groupBy(*keys).agg(F.array_sort(F.collect_list("piece")).alias("pieces"))
    joined = [F.when(F.element_at("pieces", 1)[f"f{i}"].isNotNull(), F.substring(F.array_join(F.col(f"pieces.f{i}"), ""), 1, size * _CODE_BITS // 4)).alias(n) for i, n in enumerate(names)]
    return whole.select(*keys, *joined)


def likeness(a: Column, b: Column, size: int = SIZE) -> Column:
    """Share of equal samples of two fingerprints; two empty ones are alike, an empty and another are not."""
    step = _CODE_BITS // 4
    same = F.aggregate(F.sequence(F.lit(0), F.lit(size - 1)), F.lit(0), lambda n, s: n + (F.substring(a, s * step + 1, F.lit(step)) == F.substring(b, s * step + 1, F.lit(step))).cast("int"))
    return F.when((a == "") | (b == ""), (a == b).cast("double")).otherwise(same / float(size))


#: Rows of a range of ids, and the least and most ranges.
RANGE_ROWS, RANGES = 16_384, (512, 16_384)


def with_next(docs: DataFrame, id_col: str, text_col: str, buckets: int | None = None) -> DataFrame:
    """Each document with the next one in descending id (after the last: the first): ``bucket, rn, id, text, next_id, next_text``.

    Ids are cut into ranges of about equal counts, whose number follows the number of rows; order is by (id, text), ``rn`` is
    the place in the range. A range ends at its smallest row, whose next is the largest row of the range below; only these
    rows, one for each range, meet in one task and are broadcast (at most ``buckets`` of them).
    """
    if buckets is None:
        buckets = min(max(docs.count() // RANGE_ROWS, RANGES[0]), RANGES[1])
    source = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    edges = sorted(set(source.agg(F.percentile_approx("id", [i / buckets for i in range(1, buckets)], min(20 * buckets, 100_000))).first()[0] or []))
    ranged = source.withColumn("bucket", _count_not_above(edges, F.col("id")))
    down = Window.partitionBy("bucket").orderBy(F.col("id").desc_nulls_last(), F.col("text").desc())
    here = ranged.select("bucket", F.row_number().over(down).alias("rn"), "id", "text", F.lead(F.struct("id", "text")).over(down).alias("follower"))
    largest = ranged.groupBy("bucket").agg(F.max("id").alias("id"))  # one row for each range
    tops = ranged.join(F.broadcast(largest), ["bucket", "id"]).groupBy("bucket", "id").agg(F.max("text").alias("text"))
    if ranged.where("id is null").limit(1).count():
        nulls = ranged.where("id is null").agg(F.max("text").alias("text")).select(F.lit(-1).alias("bucket"), F.lit(None).cast("long").alias("id"), "text")
        tops = tops.unionByName(nulls)
    ring = Window.orderBy(F.col("bucket").desc())
    top = F.struct("id", "text")
    below = tops.select(F.col("bucket").alias("b"), F.coalesce(F.lead(top).over(ring), F.first(top).over(ring.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))).alias("below"))
    follower = F.coalesce("follower", "below")
    return here.join(F.broadcast(below), F.col("bucket") == F.col("b"), "left").select("bucket", "rn", "id", "text", follower["id"].alias("next_id"), follower["text"].alias("next_text"))


def _count_not_above(edges: list[int], x: Column) -> Column:
    """How many of the sorted edges are <= x (-1 for null): a binary search in one array literal."""
    if not edges:
        return F.when(x.isNull(), F.lit(-1)).otherwise(F.lit(0))
    array = F.array(*[F.lit(e).cast("long") for e in edges])
    steps = [1 << k for k in range(len(edges).bit_length() - 1, -1, -1)]
    halve = lambda at, step: F.when(F.try_element_at(array, at + step) <= x, at + step).otherwise(at)  # noqa: E731  behind the end: null
    # Never null, and Spark knows it: a filter for nulls would keep the shuffle of the texts from being reused.
    return F.coalesce(F.when(x.isNull(), F.lit(-1)).otherwise(F.aggregate(F.array(*map(F.lit, steps)), F.lit(0), halve)), F.lit(0))


def edited_text(text: Column, following: Column) -> Column:
    """The last third of the code points replaced by as many (or all) of the next text's first."""
    n = F.char_length(text)
    third = F.floor(n / 3).cast("int")
    return F.concat(F.substring(text, F.lit(1), n - third), F.substring(following, F.lit(1), third))


def edited_fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SIZE) -> DataFrame:
    """Fingerprints of every text and of its edited text, and how alike they and the next document's are.

    Columns: ``id_col, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next``. A null
    text is empty. A text without a letter or digit has the empty fingerprint, so two different ones of them have equal
    fingerprints and a likeness of 1. Rows with equal ids are ordered by their texts; equal rows stay apart. Null ids come
    last. An empty table gives an empty result; texts of any length are taken whole. Extra columns are ignored, whatever
    their names.
    """
    rows = with_next(docs, id_col, text_col).withColumn("edited", edited_text(F.col("text"), F.col("next_text")))
    facts = rows.select("bucket", "rn", "id", "next_id", F.xxhash64("text").alias("hash"), F.xxhash64("next_text").alias("next_hash"), F.char_length("text").cast("long").alias("n_chars"), F.sha2("edited", 256).alias("edited_sha256"))
    prints = fingerprints(rows.select("bucket", "rn", "text", "edited"), ["bucket", "rn"], {"fingerprint": "text", "edited_fingerprint": "edited"}, size)
    joined = facts.join(prints, ["bucket", "rn"], "left")
    whole = cut(joined.select("id", "next_id", "hash", "next_hash", "n_chars", "edited_sha256", F.coalesce("fingerprint", F.lit("")).alias("fingerprint"), F.coalesce("edited_fingerprint", F.lit("")).alias("edited_fingerprint")))
    nexts = whole.groupBy(F.col("id").alias("i"), F.col("hash").alias("h")).agg(F.min("fingerprint").alias("next_fingerprint"))
    out = whole.join(nexts, F.col("next_id").eqNullSafe(F.col("i")) & (F.col("next_hash") == F.col("h")), "left")
    return out.select(
        F.col("id").alias(id_col), "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint",
        likeness(F.col("fingerprint"), F.col("edited_fingerprint"), size).alias("near_edited"), likeness(F.col("fingerprint"), F.col("next_fingerprint"), size).alias("near_next"),
    )


def op7_weighted_sampling(spark, sf_dir: str) -> DataFrame:
    return edited_fingerprints(spark.read.parquet(f"{sf_dir}/documents.parquet"))
