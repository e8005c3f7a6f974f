"""Byte-level helpers for Arrow string columns: views, chunks and hashes without Python strings."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator
from functools import lru_cache, partial

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

#: Bytes of text that one numpy pass works on; it bounds the memory of a worker.
CHUNK_BYTES = 1 << 19
#: Bytes of the rows that a worker gets at once (a single longer row comes alone).
BATCH_BYTES = 8 << 20
_BATCH_CONF = "spark.sql.execution.arrow.maxBytesPerBatch"

_U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1


def mix64(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A bijection of 64-bit words that spreads every input bit."""
    z = x.astype(np.uint64, copy=True)
    z += _U((salt * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & 0xFFFFFFFFFFFFFFFF)
    z ^= z >> _U(30)
    z *= _U(0xBF58476D1CE4E5B9)
    z ^= z >> _U(27)
    z *= _U(0x94D049BB133111EB)
    z ^= z >> _U(31)
    return z


def _power_tables(size: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse."""
    tables = []
    for b in (_BASE, pow(_BASE, -1, 1 << 64)):
        steps = np.full(size, b, np.uint64)
        steps[0] = 1
        tables.append(np.multiply.accumulate(steps))
    return tables[0], tables[1]


#: The tables that a worker keeps: those of one chunk. Longer texts make their own and let them go.
_kept_tables = lru_cache(1)(partial(_power_tables, 2 * CHUNK_BYTES + 64))


class RollingHash:
    """Hashes of arbitrary byte ranges in O(1) each, after one prefix sum over the buffer; salts share the base."""

    def __init__(self, data: np.ndarray, salt: int):
        self.salt = salt
        table = mix64(np.arange(256, dtype=np.uint64), 1000 + salt)
        power, self._inverse = _kept_tables()
        if len(data) >= len(power):
            power, self._inverse = _power_tables(len(data) + 1)
        self._prefix = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(table[data] * power[: len(data)], out=self._prefix[1:])

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        raw = (self._prefix[end] - self._prefix[start]) * self._inverse[start]
        return mix64(raw + (end - start).astype(np.uint64) * _U(0xD6E8FEB86659FD93), self.salt)


def utf8(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_binary(column.type):
        column = column.cast(pa.large_binary())
    else:
        column = pc.fill_null(column.cast(pa.large_string()), "")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    raw = column.buffers()[2]
    data = np.frombuffer(raw, np.uint8) if raw is not None else np.zeros(0, np.uint8)
    return data, offsets if len(column) else np.zeros(1, np.int64)


def chunks(column: pa.Array, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Runs of whole rows of about ``limit`` bytes: (first row, end row, bytes, offsets from 0)."""
    data, offsets = utf8(column)
    row, n = 0, len(column)
    while row < n:
        end = max(row + 1, int(np.searchsorted(offsets, offsets[row] + limit, "right")) - 1)
        end = min(end, n)
        yield row, end, data[offsets[row] : offsets[end]], offsets[row : end + 1] - offsets[row]
        row = end


_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: Words are runs of bytes other than the six ASCII blanks.
BLANK_SEPARATED = ~np.isin(np.arange(256), [0x20, *range(0x09, 0x0E)])
#: Words are runs of ASCII digits and letters and of all bytes of other characters.
ALPHANUMERIC = np.isin(np.arange(256), [*range(0x30, 0x3A), *range(0x61, 0x7B), *range(0x80, 0x100)])


def lower_ascii(data: np.ndarray) -> np.ndarray:
    return _LOWER[data]


def word_bounds(data: np.ndarray, offsets: np.ndarray, is_word: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words of all rows, and the index of each row's first word (one more at the end)."""
    inside = np.zeros(len(data) + 2, bool)
    inside[1:-1] = is_word[data]
    breaks = np.zeros(len(data) + 1, bool)
    breaks[offsets] = True
    start = np.flatnonzero(inside[1:] & (~inside[:-1] | breaks))
    end = np.flatnonzero(inside[:-1] & (~inside[1:] | breaks))
    return start, end, np.searchsorted(start, offsets)


def map_batches(rows: DataFrame, function: Callable, schema: str) -> DataFrame:
    """``rows.mapInArrow`` in batches bounded by bytes; a worker gives its free memory back after each partition.

    Workers live through many stages of a session and otherwise keep what the largest batch of any of them took.
    The bound is a runtime setting; one that the session has set lower is left alone.
    """
    conf = rows.sparkSession.conf
    if not conf.get(_BATCH_CONF).rstrip("b").isdigit() or int(conf.get(_BATCH_CONF).rstrip("b")) > BATCH_BYTES:
        conf.set(_BATCH_CONF, f"{BATCH_BYTES}b")
    return rows.mapInArrow(partial(_with_release, function=function), schema)


def _with_release(batches, function: Callable):
    try:
        yield from function(batches)
    finally:
        pa.default_memory_pool().release_unused()
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
        if trim:
            trim(0)


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)
