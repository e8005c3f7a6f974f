import pytest
from pyspark.sql import functions as F

from blockforest.plans import methods, registry, relational

duckdb = pytest.importorskip("duckdb")
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: A share of the queries keeps this quick; the driver holds all of them against DuckDB.
SOME = [*list(relational.Q)[::6], *list(methods.Q)[::6], "udtf_thresholds", "udtf_tree_nodes", "udf_scalar", "stump_forest_importance", "udf_stops", "stream_sessions", "stream_running_errors", "stream_lazy_scores", "stream_committee", "stream_label_arrivals", "committee_union", "committee_tallies", "stump_forest_trees", "stump_importance_oob", "bite_rejection"]


@pytest.mark.parametrize("name", SOME)
def test_against_duckdb(spark, tiny, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{tiny}/{t}.parquet')")
    cur = con.execute(registry.ORACLES[name])
    names = [c[0] for c in cur.description]
    want = sorted((tuple(v for _, v in sorted(zip(names, r, strict=True))) for r in cur.fetchall()), key=repr)
    df = registry.QUERIES[name](spark, tiny)
    assert sorted(df.columns) == sorted(names)
    got = sorted((tuple(r[c] for c in sorted(names)) for r in df.collect()), key=repr)
    assert got == want


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 10
    assert set(e.oracle_sql()) <= set(e.queries())


def test_pushdown_and_broadcast(spark, sf):
    plan = registry.QUERIES["scan_project_filter"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_discount)" in plan and "l_comment" not in plan
    star = registry.QUERIES["join_inner_star"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in star


def test_letter_shares_are_of_whole_texts(spark, tmp_path):
    rows = [(1, "x" * 600 + "e" * 200, "en"), (2, "", "de"), (3, "e" * 400 + "x" * 400, "de")]
    spark.createDataFrame(rows, "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.feature: r["mean"] for r in registry.QUERIES["entropy_by_feature"](spark, str(tmp_path)).collect()}
    assert got == {"e": 0.25, "h": 0.0, "n": 0.0, "t": 0.0, "u": 0.0}
    assert registry.QUERIES["best_split_root"](spark, str(tmp_path)).count() == 1


def test_experiments_read_whole_texts(spark, tiny, monkeypatch):
    from blockforest.plans import workloads

    asked = []

    class Seen(Exception):
        pass

    def seen(*args, **options):
        asked.append(options)
        raise Seen

    monkeypatch.setattr(workloads, "weblang", seen)
    names = [n for n in registry.QUERIES if n.startswith(("w9_", "w10_", "w13_bite_sizes", "w14_lazy_real", "w16_", "w17_", "w18_", "skewed_blocks")) and not n.endswith("_birds")]
    for name in names:
        with pytest.raises(Seen):
            registry.QUERIES[name](spark, tiny)
    assert len(names) == 8 and all("variant" not in o and o["flip"] == 0.1 for o in asked)


def test_flipped_labels(spark, tiny):
    from blockforest.plans.workloads import weblang

    label = lambda flip: {r.row_id: (r.label, r.features) for d in weblang(spark, tiny, flip=flip) for r in d.collect()}
    plain, flipped = label(0.0), label(0.1)
    assert plain.keys() == flipped.keys() and all(plain[i][1] == flipped[i][1] for i in plain)
    assert 0.04 < sum(plain[i][0] != flipped[i][0] for i in plain) / len(plain) < 0.18


def test_simulations_are_whole(spark, tiny, monkeypatch):
    from blockforest.functions.stopping import Rule
    from blockforest.plans import workloads

    asked = []
    monkeypatch.setattr(workloads, "simulate", lambda s, n, rules, seed: asked.append((n, rules)) or s.createDataFrame([], "rule string, m int, alpha double, relative_error double, disagreement double"))
    for name in ("w6_simulation_levels", "w7_simulation_errors"):
        registry.QUERIES[name](spark, tiny)
    for n, rules in asked:
        assert n == 1_000_000 and set(rules) == {Rule(r, 10_000, a) for r in ("g1_fpc", "g1", "g2_fpc", "g2", "bayes") for a in (0.05, 0.01, 1e-3, 1e-4)}
    assert len(asked) == 2 and {"w13_bite_sizes_birds", "w14_lazy_real_birds"} <= set(registry.QUERIES)


def test_simulated_tables_come_from_the_driver(spark):
    from blockforest.functions.stopping import Rule
    from blockforest.operators.simulate import simulate

    rows = simulate(spark, 2000, [Rule("bayes", 200, 0.01), Rule("g1_fpc", 200, 0.01)]).collect()
    assert sorted(r.rule for r in rows) == ["bayes", "g1_fpc"] and all(r.points == 2000 and r.eval_fraction < 0.5 for r in rows)


def test_unpivot_takes_all_line_items(spark, tiny):
    lines = spark.read.parquet(f"{tiny}/lineitem.parquet").count()
    assert registry.QUERIES["agg_unpivot"](spark, tiny).count() == 3 * lines


def test_updates_keep_one_row_for_each_key(spark, tiny, tmp_path):
    from blockforest.streaming import streams

    events = spark.read.parquet(f"{tiny}/events.parquet").orderBy("ts")
    events.where("event_id % 2 = 0").coalesce(1).write.parquet(f"{tmp_path}/a")
    events.where("event_id % 2 = 1").coalesce(1).write.parquet(f"{tmp_path}/b")
    for part in ("a", "b"):
        next((tmp_path / part).glob("*.parquet")).rename(tmp_path / f"events_{part}.parquet")
    got = {r.user_id: (r.seen, r.errors) for r in streams.QUERIES["stream_running_errors"](spark, str(tmp_path)).collect()}
    rows = streams.QUERIES["stream_running_errors"](spark, str(tmp_path)).count()
    want = {r.user_id: (r.seen, r.errors) for r in events.groupBy("user_id").agg(F.count(F.lit(1)).alias("seen"), F.count_if(F.col("event_type") == "error").alias("errors")).collect()}
    assert got == want and rows == len(want)


@pytest.mark.parametrize("name", ["stream_lazy_scores", "stream_committee", "stream_dedup", "stream_label_arrivals"])
def test_streams_of_tables_in_folders(spark, tiny, tmp_path, name):
    """Large tables are folders of parts: no part may be passed over."""
    for table in ("documents", "events"):
        spark.read.parquet(f"{tiny}/{table}.parquet").repartition(2).write.parquet(f"{tmp_path}/{table}.parquet")
    want = duckdb.sql(registry.ORACLES[name].replace("documents", f"read_parquet('{tiny}/documents.parquet')").replace("FROM events", f"FROM read_parquet('{tiny}/events.parquet')").replace("JOIN events", f"JOIN read_parquet('{tiny}/events.parquet')"))
    df = registry.QUERIES[name](spark, str(tmp_path)).select(*want.columns)
    got, rows = sorted(map(tuple, df.collect()), key=repr), sorted(want.fetchall(), key=repr)
    assert got == rows and (rows or name == "stream_label_arrivals")


def test_shares_at_a_half_are_rounded_as_in_sql(spark, tmp_path):
    """41 of 640 letters are 0.064062 in DuckDB and 0.064063 in Spark's decimals, where they would be one with 146 of 2279."""
    text = lambda c, n: "".join(x * c for x in methods.LETTERS).ljust(n, "x")
    rows = [(i, text(41, 640) if i % 2 else text(146, 2279), "en" if i % 2 else "de") for i in range(200)]
    file = f"{tmp_path}/documents.parquet"
    spark.createDataFrame(rows, "doc_id long, text string, lang string").withColumn("source", F.lit("")).withColumn("n_chars", F.length("text").cast("long")).coalesce(2).write.parquet(file)
    want = duckdb.sql(registry.ORACLES["stream_lazy_scores"].replace("documents", f"read_parquet('{file}/*.parquet')"))
    got = registry.QUERIES["stream_lazy_scores"](spark, str(tmp_path)).select(*want.columns)
    expected = sorted(want.fetchall())
    assert sorted(map(tuple, got.collect())) == expected and {r[1] for r in expected} == {0, 1}


@pytest.mark.parametrize("name", ["cte_recursive", "fpc_table", "min_votes_table", "model_size_nodes", *[n for n in methods.Q if n.startswith("thresholds_") and n != "thresholds_stored"]])
def test_tables_of_methods_read_a_given_table(spark, tiny, name):
    df = registry.QUERIES[name](spark, tiny)
    want = "documents" if name == "model_size_nodes" else "orders" if name == "cte_recursive" else "events"
    assert want in registry.ORACLES[name]
    if name != "model_size_nodes":  # its forest reads documents while it is trained
        assert any(f.endswith(f"{want}.parquet") for f in df.inputFiles()) or "Scan parquet" in df._jdf.queryExecution().executedPlan().toString()
    test_against_duckdb(spark, tiny, name)


def test_readers_and_sinks(spark, tmp_path):
    from blockforest.sources import tables

    df = spark.createDataFrame([(1, "a"), (2, "b")], "block int, v string")
    for fmt in ("csv", "json", "orc", "parquet"):
        tables.write(df, f"{tmp_path}/{fmt}", fmt)
        assert sorted(map(tuple, tables.read(spark, fmt, f"{tmp_path}/{fmt}", "block int, v string").collect())) == [(1, "a"), (2, "b")]
    tables.write_blocks(df, f"{tmp_path}/blocks")
    assert tables.block_storage(spark, f"{tmp_path}/blocks").count() == 2
    assert tables.read_stream(spark, "parquet", f"{tmp_path}/parquet", "block int, v string").isStreaming
    assert tables.read_stream(spark, "rate").isStreaming


def test_late_rows_are_counted(spark, tmp_path):
    import os

    from blockforest.streaming import streams

    def put(name, at, times):
        rows = ", ".join(f"({i}, timestamp_ntz'2024-01-01 {t}', 1L, 'click', 0D, '')" for i, t in enumerate(times))
        spark.sql(f"SELECT cast(col1 AS long) AS event_id, col2 AS ts, col3 AS user_id, col4 AS event_type, col5 AS value, col6 AS props FROM VALUES {rows}").coalesce(1).write.parquet(f"{tmp_path}/{name}")
        file = tmp_path / f"events_{name}.parquet"
        next((tmp_path / name).glob("*.parquet")).rename(file)
        os.utime(file, (at, at))

    put("a", 1_700_000_000, ["10:00:00", "12:00:00"])
    put("b", 1_700_000_100, ["15:00:00"])
    put("c", 1_700_000_200, ["10:30:00", "14:30:00"])
    counted = streams.tumbling(streams.events_stream(spark, str(tmp_path)), "1 hour")
    query = counted.writeStream.format("memory").queryName("late").outputMode("append").option("checkpointLocation", f"{tmp_path}/ck").trigger(availableNow=True).start()
    query.awaitTermination()
    assert streams.late_rows(query) == 1


def test_metrics_grow(spark, tmp_path):
    from blockforest.plans.workloads import metric_rows
    from blockforest.sources.tables import append_metrics

    for k in range(2):
        append_metrics(metric_rows(spark, [("w", "accuracy", 0.5 + k, {"m": k}), ("v", "ms", 1, {})]), f"{tmp_path}/metrics")
    got = spark.read.parquet(f"{tmp_path}/metrics")
    assert got.count() == 4 and got.where("workload = 'w'").agg(F.sum("value")).first()[0] == 2.0
