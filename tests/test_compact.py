import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from blockforest.operators import compact
from blockforest.operators import features as fx
from blockforest.operators.ensemble import fit_local_ensemble
from blockforest.operators.schemas import ForestParams
from blockforest.operators.train import train_mega_forest, tune_bite_size
from blockforest.plans import workloads


@pytest.mark.parametrize("sampler", ["importance", "bagging", "rejection", "full"])
def test_trees_do_not_depend_on_how_a_block_is_kept(monkeypatch, sampler):
    rng = np.random.default_rng(0)
    n = 700
    numbers = np.stack([rng.integers(0, 50, n) * 1.0, np.round(rng.random(n) * 1e5, 2), rng.random(n) / 3, np.where(rng.random(n) < 0.1, np.nan, 0.1)], axis=1)
    ones = np.stack([rng.integers(-1, 5, n), rng.integers(5, 8, n)], axis=1).astype(np.int16)
    y = ((numbers[:, 1] > 4e4) ^ (ones[:, 0] == 2)).astype(np.int64)
    ids = rng.permutation(n)

    def trees(piece):
        monkeypatch.setattr(compact, "PIECE", piece)
        held = compact.Rows()
        for a in range(0, n, 90):
            held.add(ids[a : a + 90], numbers[a : a + 90], ones[a : a + 90], 8, y[a : a + 90])
        x, labels = held.done()
        assert isinstance(x, compact.Rows) == (piece < n)
        every = x[np.arange(n)] if piece < n else x
        np.testing.assert_array_equal(every, compact.dense(numbers, ones, 8)[np.argsort(ids)])
        return [(t.feature.tolist(), t.threshold.tolist(), t.leaf_class.tolist(), facts["oob_error"]) for _, _, t, facts in fit_local_ensemble(x, labels, ForestParams(n_trees=4, bite_size=80, sampler=sampler))]

    assert trees(200) == trees(10_000)


def test_compact_rows_equal_one_hot_ones(spark, tiny):
    df = workloads.star(spark, tiny)
    domains = {"p_brand": fx.domain(df, "p_brand"), "n_name": fx.domain(df, "n_name")[1:]}  # one nation has no column
    df = df.withColumn("label", (F.col("l_quantity") > 20).cast("int"))
    hot = fx.one_hot(df, domains)
    wide = fx.assemble(hot, "row_id", ["l_quantity", "l_tax", *[c for c in hot.columns if c.startswith(("p_brand_", "n_name_"))]], "label")
    narrow = fx.compact(df, "row_id", ["l_quantity", "l_tax"], domains, "label")
    a, b = (d.orderBy("row_id").toArrow().combine_chunks() for d in (wide, narrow))
    one = lambda t: t["features"].chunk(0) if isinstance(t["features"], pa.ChunkedArray) else t["features"]
    np.testing.assert_array_equal(compact.dense(*compact.parts_of(one(a))), compact.dense(*compact.parts_of(one(b))))
    p = ForestParams(n_trees=2, bite_size=60, n_blocks=3)
    key = lambda f: sorted((r.tree_id, tuple(r.feature), tuple(r.threshold)) for r in f.trees.collect())
    assert key(train_mega_forest(wide, p)) == key(train_mega_forest(narrow, p))
    assert sorted(map(tuple, tune_bite_size(wide, [20, 40], p, wide).drop("fit_ms").collect())) == sorted(map(tuple, tune_bite_size(narrow, [20, 40], p, narrow).drop("fit_ms").collect()))


def test_line_items_travel_narrow(spark, tiny):
    """Experiments on line items neither persist nor shuffle a double for every 0/1 column."""
    train, test = workloads.high_value_lines(spark, tiny, 0.1)
    assert fx.is_compact(train) and workloads._kept(train) is train and not train.is_cached
    r = train.first().features
    assert len(r.numbers) == 11 and len(r.ones) == 4 and r.width > 40 and train.schema == test.schema
    plan = train._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and plan.count("Scan parquet") == 1


def _random_tree(rng, d, n, classes=2):
    """A full-grown tree on noise, so that most of its ends are beyond the first 64."""
    from blockforest.operators.tree import fit_tree

    x, y = d[:n], rng.integers(0, classes, n)
    return fit_tree(x, y, classes, rng, min_leaf=2)


@pytest.mark.parametrize("classes", [2, 5])
def test_bits_and_parts_give_every_row_its_leaf(classes):
    rng = np.random.default_rng(3)
    n = 40_000  # more than a strip
    numbers = np.stack([rng.integers(0, 40, n) * 1.0, np.round(rng.normal(0, 1e4, n), 2), rng.random(n), np.where(rng.random(n) < 0.1, np.nan, rng.integers(0, 3, n))], axis=1)
    ones = np.stack([rng.integers(-1, 5, n), rng.integers(5, 9, n)], axis=1).astype(np.int16)
    x = compact.dense(numbers, ones, 10)  # no row has the last place
    whole = compact._Piece(numbers, ones)
    joined = compact._Piece.joined([compact._Piece(numbers[a : a + 9000], ones[a : a + 9000]) for a in range(0, n, 9000)])
    assert [c.kind for c in whole.columns] == ["code", "hundredths", "plain", "code"] == [c.kind for c in joined.columns]
    np.testing.assert_array_equal(joined.plain()[0], numbers)
    np.testing.assert_array_equal(joined.plain()[1], ones)
    for size in (1, 30, 3000):
        tree = _random_tree(rng, x, size, classes)
        assert (len(compact.Walk(tree).ends) == 64) == (size == 3000)
        for piece in (whole, joined):
            np.testing.assert_array_equal(piece.predict(tree), tree.predict(x))
    tree.counts, tree.threshold[tree.feature == 4] = None, -0.5  # below 0 and 1: all rows go right
    np.testing.assert_array_equal(whole.predict(tree), tree.predict(x))


def test_every_bite_size_has_a_task_of_its_own(spark, tiny, monkeypatch):
    """A union of parts of one partition each is a single partition in Spark 4.1: sizes were fitted one after another."""
    from blockforest.operators import train

    seen = []
    merge = train.store.merge_ensembles
    monkeypatch.setattr(train.store, "merge_ensembles", lambda trees, params: seen.append(trees.rdd.getNumPartitions()) or merge(trees, params))
    rows, test = workloads.high_value_lines(spark, tiny)
    key = "spark.sql.unionOutputPartitioning"
    before = spark.conf.get(key, None)
    got = train.tune_bite_size(rows, [20, 40, 80], ForestParams(n_trees=3, n_blocks=2), test).collect()
    assert seen == [3] and len(got) == 3 and spark.conf.get(key, None) == before


def test_bite_sizes_are_the_forests_of_one_block(spark, tiny):
    """A size's accuracy and nodes are those of a forest with that bite on that block."""
    from blockforest.operators.blocks import assign_blocks
    from blockforest.operators.scoring import predict_full

    rows, test = workloads.high_value_lines(spark, tiny)
    p = ForestParams(n_trees=4, n_blocks=2, bite_size=60)
    r = tune_bite_size(rows, [60], p, test).first()
    forest = train_mega_forest(assign_blocks(rows, 2, seed=p.seed).where("block = 0"), p)
    share = predict_full(forest, test).join(test.select("row_id", "label"), "row_id").agg(F.avg((F.col("prediction") == F.col("label")).cast("double"))).first()[0]
    assert r.nodes == forest.trees.agg(F.sum("n_nodes")).first()[0] and abs(r.accuracy - share) < 1e-12


@pytest.mark.parametrize("piece", [300, 10_000])
def test_packed_rows_come_back(spark, tiny, monkeypatch, piece):
    monkeypatch.setattr(compact, "PIECE", piece)
    rows, _ = workloads.high_value_lines(spark, tiny)
    table = rows.select("row_id", "features", "label").limit(2000).toArrow()
    batches = table.to_batches(max_chunksize=170)
    held, plain = compact.Rows(), compact.Rows()
    for part in (batches[:5], batches[5:]):  # two tasks put rows together
        for batch in compact.pack_rows(iter(part)):
            held.add_packed(memoryview(batch.column(0)[0].as_buffer()))
    for b in batches:
        plain.add(b.column(0).to_numpy(), *compact.parts_of(b.column(1)), b.column(2).to_numpy())
    (x, y), (want, labels) = held.done(), plain.done()
    every = np.arange(table.num_rows)
    assert isinstance(x, compact.Rows) == (piece == 300)
    np.testing.assert_array_equal(x[every], want[every])
    np.testing.assert_array_equal(y, labels)
