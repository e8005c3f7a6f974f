"""License scans: MinHash bands over overlapping windows retrieve templates, exact shingle containment verifies.

Words are cut at everything but ASCII letters and digits and other alphabets. A template of s shingles is looked for in windows
of four cells of half of s, one from each cell of a document on, so every stretch of up to 1.5 s shingles lies whole in some
window, and no window spans two documents. Bands have one coordinate: a window that holds the required share of a template agrees in
each with a probability of at least what the lengths allow (about 1/3), and every template has as many bands as make a miss
rarer than 1 in 400,000. Windows without any shingle of a template can't agree and are not hashed. Every retrieved (window, template)
is then verified on the template's whole shingle set.
"""

from __future__ import annotations

import math
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._text import ALPHANUMERIC, RollingHash, chunks, lower_ascii, map_batches, mix64, word_bounds

#: Statements of common licenses, by name; a further form of a license has a suffix.
TEMPLATES = {
    "agpl-3.0": "licensed under the GNU Affero General Public License, version 3",
    "agpl-3.0-text": "it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License",
    "all-rights-reserved": "All rights reserved",
    "apache-2.0": "Licensed under the Apache License, Version 2.0",
    "apache-2.0-short": "Licensed under the Apache 2.0 License",
    "bsd-2-clause-name": "Licensed under the BSD 2-Clause License",
    "bsd-3-clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "bsd-3-clause-name": "Licensed under the BSD 3-Clause License",
    "cc-by-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License",
    "cc-by-4.0-short": "Licensed under CC BY 4.0",
    "cc-by-nc-4.0": "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License",
    "cc-by-nc-4.0-short": "Licensed under CC BY-NC 4.0",
    "cc-by-nc-nd-4.0": "This work is licensed under a Creative Commons Attribution-NonCommercial-NoDerivatives 4.0 International License",
    "cc-by-nc-nd-4.0-short": "Licensed under CC BY-NC-ND 4.0",
    "cc-by-nc-sa-4.0": "This work is licensed under a Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License",
    "cc-by-nc-sa-4.0-short": "Licensed under CC BY-NC-SA 4.0",
    "cc-by-nd-4.0": "This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License",
    "cc-by-nd-4.0-short": "Licensed under CC BY-ND 4.0",
    "cc-by-sa-4.0": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License",
    "cc-by-sa-4.0-short": "Licensed under CC BY-SA 4.0",
    "cc0-1.0": "Licensed under CC0 1.0",
    "cc0-1.0-text": "has waived all copyright and related or neighboring rights to this work",
    "epl-2.0": "made available under the terms of the Eclipse Public License 2.0",
    "gpl-2.0": "licensed under the GNU General Public License, version 2",
    "gpl-2.0-text": "it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License",
    "gpl-3.0": "licensed under the GNU General Public License, version 3",
    "gpl-3.0-text": "it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License",
    "isc-text": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted",
    "lgpl-2.1": "licensed under the GNU Lesser General Public License, version 2.1",
    "lgpl-2.1-text": "terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License",
    "lgpl-3.0": "licensed under the GNU Lesser General Public License, version 3",
    "lgpl-3.0-text": "terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License",
    "mit": "Released under the MIT License",
    "mit-name": "Licensed under the MIT License",
    "mit-text": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files",
    "mpl-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0",
    "mpl-2.0-name": "Licensed under the Mozilla Public License, version 2.0",
    "unlicense": "This is free and unencumbered software released into the public domain",
}
#: Words of a shingle, least number of bands, and the share of a template's shingles that must be there, in percent.
SHINGLE, BANDS, CONTAINED = 3, 32, 80
#: A window is so many cells; a template in a window is missed by all bands at most once in so many times.
CELLS, MISS = 4, 400_000
#: Windows that one numpy pass works on.
_WINDOWS = 1 << 14


def _shingles(words: np.ndarray, k: int) -> np.ndarray:
    if len(words) < k:
        return np.zeros(0, np.uint64)
    acc = np.zeros(len(words) - k + 1, np.uint64)
    for i in range(k):
        acc = mix64(acc + words[i : len(words) - k + 1 + i], i)
    return acc


def bands_needed(n: int, cell: int, percent: int) -> int:
    """Bands for n shingles, of which ``percent`` are in a window that is full of other ones besides."""
    held = max(1, -(-n * percent // 100))
    agree = held / (n + max(0, CELLS * cell - held))
    return max(BANDS, math.ceil(math.log(MISS) / -math.log1p(-agree))) if agree < 1 else BANDS


class Templates:
    """Shingle sets of the templates, grouped by cell length, with their band coordinates."""

    def __init__(self, texts: dict[str, str], percent: int = CONTAINED):
        self.names = sorted(texts)
        self.percent, self.sets, self.by_cell, self.bands = percent, [], {}, []
        for i, name in enumerate(self.names):
            for _, _, data, offsets in chunks(pa.array([texts[name]])):
                data = lower_ascii(data)
                start, end, _ = word_bounds(data, offsets, ALPHANUMERIC)
                words = RollingHash(data, 2).of(start, end)
            sh = _shingles(words, SHINGLE)
            if not len(sh):
                raise ValueError(f"template {name} has fewer than {SHINGLE} words")
            s, cell = np.unique(sh), -(-len(sh) // 2)
            self.sets.append(s)
            self.by_cell.setdefault(cell, []).append(i)
            self.bands.append(np.array([mix64(s, 60 + b).min() for b in range(bands_needed(len(s), cell, percent))], np.uint64))
        self.known = [set(s.tolist()) for s in self.sets]
        self.openers = {cell: np.unique(np.concatenate([self.sets[i] for i in members])) for cell, members in self.by_cell.items()}
        self.all = np.unique(np.concatenate([*self.sets, np.zeros(0, np.uint64)]))


def _windows(at: np.ndarray, first: np.ndarray, cell: int) -> np.ndarray:
    """Starts of the windows that hold one of the shingles ``at``; ``first``: the first shingle of its document."""
    own = (at - first) // cell
    back = np.minimum(own[:, None], np.arange(CELLS))
    return np.unique(first[:, None] + (own[:, None] - back) * cell)


def matches(words: np.ndarray, bound: np.ndarray, templates: Templates) -> set[tuple[int, int]]:
    """(row, template) of a run of rows: retrieved by bands, verified by containment."""
    found: dict[tuple[int, int], set[int]] = {}
    sh = _shingles(words, SHINGLE)
    hits = np.flatnonzero(np.isin(sh, templates.all))
    row = np.searchsorted(bound, hits, "right") - 1
    inside = hits + SHINGLE <= bound[row + 1]  # a shingle never spans two documents
    hits, row = hits[inside], row[inside]
    if not len(hits):
        return set()
    for cell, members in templates.by_cell.items():
        here = np.isin(sh[hits], templates.openers[cell])
        starts = _windows(hits[here], bound[row[here]], cell)
        for a in range(0, len(starts), _WINDOWS):
            start = starts[a : a + _WINDOWS]
            owner = np.searchsorted(bound, start, "right") - 1
            at = start[:, None] + np.arange(CELLS * cell)
            real = at + SHINGLE <= bound[owner + 1][:, None]
            values = sh[np.where(real, at, start[:, None])]  # behind the document's end: the first shingle again
            candidates = {i: np.zeros(len(start), bool) for i in members}
            for b in range(max(len(templates.bands[i]) for i in members)):
                low = mix64(values, 60 + b).min(axis=1)
                for i in members:
                    if b < len(templates.bands[i]):
                        candidates[i] |= low == templates.bands[i][b]
            for i, windows in candidates.items():
                for w in np.flatnonzero(windows).tolist():
                    have = templates.known[i].intersection(values[w].tolist())
                    if 100 * len(have) >= templates.percent * len(templates.sets[i]):
                        key = (int(owner[w]), i)
                        found[key] = have | found.get(key, set())
    return _nearest(found, templates)


def _nearest(found: dict[tuple[int, int], set[int]], templates: Templates) -> set[tuple[int, int]]:
    """Without the templates that only share the words of a closer one: version 2 in a statement of version 3."""
    share = {(r, i): len(have) / len(templates.sets[i]) for (r, i), have in found.items()}
    rows: dict[int, list[int]] = {}
    for r, i in found:
        rows.setdefault(r, []).append(i)
    return {(r, i) for (r, i), have in found.items() if not any(share[r, j] > share[r, i] and have <= templates.known[j] for j in rows[r])}


def _scan(batches, templates: Templates):
    for batch in batches:
        names = []
        for first, end, data, offsets in chunks(batch.column(1)):
            data = lower_ascii(data)
            start, stop, bound = word_bounds(data, offsets, ALPHANUMERIC)
            per: dict[int, list[str]] = {}
            for r, i in matches(RollingHash(data, 2).of(start, stop), bound, templates):
                per.setdefault(r, []).append(templates.names[i])
            names.extend(sorted(per.get(r, [])) for r in range(end - first))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, pa.list_(pa.string()))], names=["id", "licenses"])


def find_licenses(docs: DataFrame, templates: dict[str, str] | None = None, id_col: str = "doc_id", text_col: str = "text", percent: int = CONTAINED) -> DataFrame:
    """``id_col, licenses array<string>``: templates of which a stretch of text holds ``percent`` of the shingles.

    A template whose shingles there all belong to another template that is held to a larger share is left out. The names are
    sorted. Null and empty texts have none; ids are passed through, null ones too; repeated rows get equal results. An empty
    table gives an empty result; texts of any length are scanned whole. Extra columns are ignored, whatever their names.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    known = Templates(TEMPLATES if templates is None else templates, percent)
    return map_batches(rows, partial(_scan, templates=known), f"id {kind}, licenses array<string>").withColumnRenamed("id", id_col)


def op3_license_bands(spark, sf_dir: str) -> DataFrame:
    out = find_licenses(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", F.size("licenses").cast("long").alias("n_licenses"), F.array_join("licenses", ",").alias("licenses"))
