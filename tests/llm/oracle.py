"""Run a query's SQL in DuckDB over the same tables and compare the rows."""

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(sf_dir, sql):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    cur = con.execute(sql)
    names = [c[0] for c in cur.description]
    return names, cur.fetchall()


def rows_by_name(df):
    names = sorted(df.columns)
    return names, sorted((tuple(r[n] for n in names) for r in df.collect()), key=repr)


def assert_same(df, sf_dir, sql):
    names, rows = duck(sf_dir, sql)
    order = sorted(range(len(names)), key=names.__getitem__)
    expected = sorted((tuple(r[i] for i in order) for r in rows), key=repr)
    got_names, got = rows_by_name(df)
    assert got_names == sorted(names)
    assert len(got) == len(expected)
    for a, b in zip(got, expected, strict=True):
        assert a == b
