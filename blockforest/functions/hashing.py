"""Seeded hashes: a portable one that SQL engines share, a fast one, and seeds for workers."""

from __future__ import annotations

import hashlib
from collections import Counter

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def portable_hash(seed: str, value: Column) -> Column:
    """32 bits of md5(seed | value), the same number in every SQL engine."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), value.cast("string"))), 1, 8), 16, 10).cast("long")


def fast_hash(seed: str, value: Column) -> Column:
    """32 bits of xxhash64: the production default."""
    return F.xxhash64(F.lit(seed), value).bitwiseAND(0xFFFFFFFF)


def uniform(seed: str, value: Column, portable: bool = True) -> Column:
    return (portable_hash if portable else fast_hash)(seed, value) / F.lit(4294967296.0)


def derive_seed(*parts) -> int:
    """A seed that depends on its parts alone, so a task that runs again draws the same."""
    return int.from_bytes(hashlib.md5("|".join(map(str, parts)).encode()).digest()[:8], "big")


def portable_sql(seed: str, value: str) -> str:
    """``portable_hash`` in DuckDB."""
    return f"('0x' || substr(md5('{seed}|' || ({value})::VARCHAR), 1, 8))::BIGINT"


def portable_number(seed: str, value: str) -> int:
    """``portable_hash`` in Python."""
    return int(hashlib.md5(f"{seed}|{value}".encode()).hexdigest()[:8], 16)


class PortableRng:
    """Draws that any SQL engine can repeat: draw k of a kind is the portable hash of (kind and seed, key and k).

    It has the methods of numpy's generator that bites and trees use. It is for checks against other engines; training
    at scale draws with numpy.
    """

    def __init__(self, seed: int, *key):
        self._seed, self._key, self._used = seed, ":".join(map(str, key)), Counter()

    def _draws(self, kind: str, n: int) -> np.ndarray:
        first = self._used[kind]
        self._used[kind] += n
        return np.array([portable_number(f"{kind}-{self._seed}", f"{self._key}:{k}") for k in range(first, first + n)], np.int64)

    def choice(self, pool: np.ndarray, size: int, replace: bool = True) -> np.ndarray:
        return pool[self._draws("choice", size) % len(pool)] if replace else pool[np.argsort(self._draws("choice", len(pool)), kind="stable")[:size]]

    def integers(self, low: int, high: int, size: int) -> np.ndarray:
        return low + self._draws("integers", size) % (high - low)

    def random(self, size: int) -> np.ndarray:
        return self._draws("random", size) / 2**32

    def permutation(self, n: int) -> np.ndarray:
        return np.argsort(self._draws("permutation", n), kind="stable")
