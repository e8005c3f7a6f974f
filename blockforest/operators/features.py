"""Feature extraction and preprocessing, all as column expressions but for one Arrow form."""

from __future__ import annotations

import string

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import portable_hash

ALPHANUMERICS = string.digits + string.ascii_lowercase + string.ascii_uppercase
#: Names of the 63 features: one for each alphanumeric, and the rest.
CHAR_FEATURES = [f"p_{'u' if c.isupper() else ''}{c.lower()}" for c in ALPHANUMERICS] + ["p_other"]


def char_proportions(text: Column, digits: int | None = None) -> list[Column]:
    """63 proportions of code points (case kept); an empty or null text has zeros everywhere."""
    text = F.coalesce(text, F.lit(""))
    n = F.char_length(text)
    counts = [n - F.char_length(F.replace(text, F.lit(c), F.lit(""))) for c in ALPHANUMERICS]
    counts.append(F.char_length(F.regexp_replace(text, "[0-9a-zA-Z]", "")))
    shares = [F.when(n > 0, c / n).otherwise(F.lit(0.0)) for c in counts]
    return [(F.round(s, digits) if digits is not None else s).alias(name) for s, name in zip(shares, CHAR_FEATURES, strict=True)]


def char_vector(text: Column) -> Column:
    """The proportions as one array, in generated code."""
    return F.array(*char_proportions(text))


def _histograms(batches):
    table = np.full(256, 62)
    table[[ord(c) for c in ALPHANUMERICS]] = np.arange(62)
    for batch in batches:
        column = batch.column(1).cast(pa.large_string()).fill_null("")
        offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
        data = np.frombuffer(column.buffers()[2] or b"", np.uint8)
        out = np.zeros((len(column), 63))
        for i in range(len(column)):
            raw = data[offsets[i] : offsets[i + 1]]
            raw = raw[(raw & 0xC0) != 0x80]  # one byte of every code point
            if len(raw):
                out[i] = np.bincount(table[raw], minlength=63) / len(raw)
        lists = pa.ListArray.from_arrays(pa.array(np.arange(len(out) + 1) * 63, pa.int32()), pa.array(out.ravel()))
        yield pa.RecordBatch.from_arrays([batch.column(0), lists, *batch.columns[2:]], names=["row_id", "features", *batch.schema.names[2:]])


def char_histograms(df: DataFrame, id_col: str, text_col: str = "text", also: tuple[str, ...] = ()) -> DataFrame:
    """``row_id, features`` and the columns of ``also``: the same in one pass over the bytes, for long texts."""
    rows = df.select(F.col(id_col).cast("long").alias("row_id"), F.col(text_col).cast("string").alias("text"), *also)
    more = "".join(f", {c} {rows.schema[c].dataType.simpleString()}" for c in also)
    return rows.mapInArrow(_histograms, f"row_id long, features array<double>{more}")


def html_text(html: Column) -> Column:
    """Text of a page: scripts, styles and tags out."""
    return F.regexp_replace(F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " "), "<[^>]*>", " ")


def html_lang(html: Column) -> Column:
    return F.regexp_extract(html, r'<html[^>]*lang="([a-z]+)"', 1)


def split_grouped(df: DataFrame, key: Column, test_in: int = 5, seed: str = "split") -> tuple[DataFrame, DataFrame]:
    """(train, test) by a hash of the content, so equal contents never cross."""
    h = F.pmod(portable_hash(seed, key), F.lit(test_in))
    return df.where(h != 0), df.where(h == 0)


def split_time(df: DataFrame, column: str, cut: str) -> tuple[DataFrame, DataFrame]:
    """(before, from then on)."""
    at = F.lit(cut).cast("timestamp_ntz")
    return df.where(F.col(column) < at), df.where(F.col(column) >= at)


def sample_exact(df: DataFrame, n: int, key: str, seed: str = "sample") -> DataFrame:
    """Exactly n rows (or all): those with the smallest hashes of their key."""
    return df.orderBy(portable_hash(seed, F.col(key)), key).limit(n)


def recode(df: DataFrame, column: str, mapping: dict[str, str]) -> DataFrame:
    """Rare categories to their equivalents."""
    return df.replace(mapping, subset=[column])


def pick_by_month(month: Column, columns: list[Column]) -> Column:
    """The value of the month's own column out of twelve."""
    return F.element_at(F.array(*columns), month.cast("int"))


def fill_missing(df: DataFrame, numeric: list[str], categorical: list[str], sentinel: float = -9999.0, token: str = "missing", check: bool = True) -> DataFrame:
    """NULL and NaN numbers to a value outside the observed range, NULL categories to a token."""
    if check and numeric:
        low = df.agg(F.min(F.least(*[F.nanvl(F.col(c).cast("double"), F.lit(None)) for c in numeric]) if len(numeric) > 1 else F.nanvl(F.col(numeric[0]).cast("double"), F.lit(None)))).first()[0]
        if low is not None and low <= sentinel:
            raise ValueError("the sentinel lies inside the observed range")
    filled = {c: F.coalesce(F.nanvl(F.col(c).cast("double"), F.lit(None)), F.lit(sentinel)) for c in numeric}
    return df.withColumns(filled | {c: F.coalesce(F.col(c), F.lit(token)) for c in categorical})


def one_hot(df: DataFrame, domains: dict[str, list[str]]) -> DataFrame:
    """One 0/1 column for each valid value of each category."""
    return df.withColumns({f"{c}_{''.join(x if x.isalnum() else '_' for x in v).lower()}": F.coalesce(F.col(c) == v, F.lit(False)).cast("int") for c, values in domains.items() for v in values})


def drop_metadata(df: DataFrame, *columns: str) -> DataFrame:
    """Without the columns that name or place an example (ids, links, dates of entry): they are no features."""
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {', '.join(missing)}")
    return df.drop(*columns)


def domain(df: DataFrame, column: str, limit: int = 1000) -> list[str]:
    """Distinct values of a category with few of them."""
    values = [r[0] for r in df.select(column).where(F.col(column).isNotNull()).distinct().limit(limit + 1).collect()]
    if len(values) > limit:
        raise ValueError(f"{column} has over {limit} values")
    return sorted(values)


def to_presence(count: Column) -> Column:
    return (count > 0).cast("int")


def places(domains: dict[str, list[str]]) -> tuple[list[Column], int]:
    """(for each category the place of its value among the 0/1 columns of all, or -1; how many places there are)."""
    out, first = [], 0
    for c, values in domains.items():
        at = F.coalesce(F.array_position(F.array(*map(F.lit, values)), F.col(c)), F.lit(0)).cast("int")
        out.append(F.when(at > 0, at + (first - 1)).otherwise(-1).alias(c))
        first += len(values)
    return out, first


def narrow(df: DataFrame, row_id: str, numbers: list[str], ones: list[Column], width: int, label: str, *also: str) -> DataFrame:
    """``row_id, features, label`` with ``features`` as numbers and ``places`` of ones."""
    features = F.struct(F.array(*[F.col(c).cast("double") for c in numbers]).alias("numbers"), F.array(*ones).alias("ones"), F.lit(width).alias("width"))
    return df.select(F.col(row_id).cast("long").alias("row_id"), features.alias("features"), F.col(label).cast("int").alias("label"), *also)


def compact(df: DataFrame, row_id: str, numbers: list[str], domains: dict[str, list[str]], label: str, *also: str) -> DataFrame:
    """``row_id, features, label`` as ``one_hot`` and ``assemble`` give them, with ``features`` as numbers and the places of ones.

    Rows with many 0/1 columns keep an int for each category instead; training and scoring take them as they are.
    """
    return narrow(df, row_id, numbers, *places(domains), label, *also)


def is_compact(df: DataFrame) -> bool:
    return df.schema["features"].dataType.typeName() == "struct"


def features_of(df: DataFrame) -> Column:
    """The column ``features``: as doubles, or compact as it is."""
    return F.col("features") if is_compact(df) else F.col("features").cast("array<double>").alias("features")


def n_features(df: DataFrame) -> Column:
    return F.size("features.numbers") + F.col("features.width") if is_compact(df) else F.size("features")


def assemble(df: DataFrame, row_id: str, features: list[str], label: str, *also: str) -> DataFrame:
    """``row_id, features, label``."""
    return df.select(F.col(row_id).cast("long").alias("row_id"), F.array(*[F.col(c).cast("double") for c in features]).alias("features"), F.col(label).cast("int").alias("label"), *also)
