import re

import numpy as np

from blockforest.llm.licenses import TEMPLATES, Templates, find_licenses, op3_license_bands


def words(t):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate({c: c + 32 for c in range(65, 91)}))


def shingles(w):
    return {tuple(w[i : i + 3]) for i in range(len(w) - 2)}


def whole(text):
    """Templates that stand in the text word for word."""
    t = " " + " ".join(words(text)) + " "
    return sorted(n for n, x in TEMPLATES.items() if " " + " ".join(words(x)) + " " in t)


def test_against_word_search(spark, sf):
    got = {r.doc_id: [x for x in r.licenses.split(",") if x] for r in op3_license_bands(spark, sf).collect()}
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    assert len(got) == len(texts) and sum(map(len, got.values())) > 20
    for i, t in texts.items():
        assert set(whole(t)) <= set(got[i])
        for name in got[i]:  # nothing without four fifths of the template's shingles in the text
            s = shingles(words(TEMPLATES[name]))
            assert 100 * len(s & shingles(words(t))) >= 80 * len(s)


def test_edges(spark):
    bsd = TEMPLATES["bsd-3-clause"]
    rows = [(1, None), (2, ""), (3, "x " * 5001 + bsd.upper() + " y" * 5000), (4, bsd.replace("source", "SRC code")), (5, "Released under the"), (None, "released UNDER the mit license"), (6, "Released under the MIT License. " * 3), (6, "Released under the MIT License. " * 3), (7, "Released under"), (8, "the MIT License")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'a' as licenses", "2 as id").coalesce(1)
    got = [(r.doc_id, r.licenses) for r in find_licenses(df).collect()]
    assert got == [(1, []), (2, []), (3, ["bsd-3-clause"]), (4, ["bsd-3-clause"]), (5, []), (None, ["mit"]), (6, ["mit"]), (6, ["mit"]), (7, []), (8, [])]
    assert find_licenses(df.limit(0)).count() == 0


def test_every_statement_of_the_documents_has_a_template(spark, sf):
    statements = {"This work is licensed under the GNU General Public License, version 3.": "gpl-3.0", "All rights reserved.": "all-rights-reserved", "Licensed under CC BY-NC 4.0.": "cc-by-nc-4.0-short", "Released under the MIT License.": "mit", "Licensed under the Apache License, Version 2.0.": "apache-2.0"}
    got = {r.doc_id: r.licenses.split(",") for r in op3_license_bands(spark, sf).collect()}
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    for statement, name in statements.items():
        holders = {i for i, t in texts.items() if statement in t}
        assert holders and holders == {i for i, names in got.items() if name in names}


def test_each_template_names_itself_alone(spark):
    df = spark.createDataFrame(sorted(TEMPLATES.items()), "doc_id string, text string").coalesce(1)
    assert {r.doc_id: r.licenses for r in find_licenses(df).collect()} == {n: [n] for n in TEMPLATES}


def test_bands_miss_less_than_once_in_400_000():
    known = Templates(TEMPLATES)
    for cell, members in known.by_cell.items():
        for i in members:
            n = len(known.sets[i])
            held = -(-4 * n // 5)
            agree = held / (n + 4 * cell - held)  # the rest of the window is foreign
            assert (1 - min(agree, 1)) ** len(known.bands[i]) <= 1 / 400_000, known.names[i]


def test_statements_between_foreign_words_are_all_found(spark):
    # four fifths of a template's shingles, at every offset, with documents of other lengths before it
    rng = np.random.default_rng(5)
    other = lambda n: " ".join(f"w{x}" for x in rng.integers(0, 10**9, n))
    rows, want = [], {}
    for name in ("mit", "gpl-3.0", "mpl-2.0"):
        w = words(TEMPLATES[name])
        n = len(shingles(words(TEMPLATES[name])))
        text = " ".join(w[: len(w) - (n - -(-4 * n // 5))])
        for k in range(1500):
            want[len(rows)] = name
            rows.append((len(rows), f"{other(k % 37)} {text} {other(40)}"))
    df = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)
    missed = [r.doc_id for r in find_licenses(df).collect() if want[r.doc_id] not in r.licenses]
    assert missed == []
