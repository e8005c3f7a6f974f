import numpy as np
import pytest
from pyspark.sql import functions as F

from blockforest.functions import measures
from blockforest.functions.stopping import Rule
from blockforest.operators import committee, model, sampling, scoring, train
from blockforest.operators import features as fx
from blockforest.operators.blocks import assign_blocks, partition_by_block
from blockforest.operators.ensemble import fit_local_ensemble
from blockforest.operators.schemas import ForestParams
from blockforest.operators.simulate import draw_points
from blockforest.operators.tree import best_split, entropy, fit_tree, n_attributes


def toy(n=600, d=6, seed=0):
    rng = np.random.default_rng(seed)
    x = rng.random((n, d)).round(2)
    return x, ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.4)).astype(int)


@pytest.fixture(scope="module")
def rows(spark):
    x, y = toy()
    return spark.createDataFrame([(i, a.tolist(), int(b)) for i, (a, b) in enumerate(zip(x, y, strict=True))], "row_id long, features array<double>, label int").cache()


PARAMS = ForestParams(n_trees=6, bite_size=60, n_blocks=4, n_parts=3)


@pytest.fixture(scope="module")
def forest(rows):
    return train.train_mega_forest(rows, PARAMS)


def test_attribute_counts_and_entropy():
    assert [n_attributes(d) for d in (1, 63, 64, 1143)] == [1, 6, 7, 11]
    assert entropy(np.array([5, 5])) == 1 and entropy(np.array([7, 0])) == 0


def test_split_is_the_best_of_all():
    rng = np.random.default_rng(1)
    for _ in range(60):
        x, y = rng.integers(0, 6, (20, 3)).astype(float), rng.integers(0, 3, 20)
        got = best_split(x, y, 3)
        best = -1.0
        for c in range(3):
            for v in np.unique(x[:, c])[:-1]:
                a = x[:, c] <= v
                h = lambda m: entropy(np.bincount(y[m], minlength=3))  # noqa: B023, E731
                best = max(best, entropy(np.bincount(y, minlength=3)) - (a.mean() * h(a) + (~a).mean() * h(~a)))
        assert abs(got[2] - best) < 1e-12
    assert best_split(np.ones((5, 2)), np.array([0, 1, 0, 1, 0]), 2) is None


def test_trees():
    x, y = toy()
    t = fit_tree(x, y, 2, np.random.default_rng(0), min_leaf=1, n_attr=6)
    assert (t.predict(x) == y).all()
    assert fit_tree(x, y, 2, np.random.default_rng(0), max_depth=2).depth <= 2
    assert len(fit_tree(x, np.ones(len(y), int), 2, np.random.default_rng(0)).feature) == 1
    same = fit_tree(np.ones((30, 2)), np.arange(30) % 2, 2, np.random.default_rng(0))
    assert len(same.feature) == 1 and same.leaf_class[0] == 0


def test_bites():
    rng = np.random.default_rng(0)
    bite, fell = sampling.draw_bite(np.arange(10), np.arange(10, 20), 7, rng)
    assert (bite >= 10).sum() == 4 and not fell
    assert sampling.draw_bite(np.arange(10), np.zeros(0, int), 6, rng)[1]
    assert sampling.accept_probability(0.6) == 1 and abs(sampling.accept_probability(0.2) - 0.25) < 1e-12
    wrong = np.zeros(1000, bool)
    wrong[:100] = True
    bite, _ = sampling.draw_bite_rejection(wrong, 0.1, 4000, rng)
    assert abs(wrong[bite].mean() - 0.5) < 0.04  # half right, half wrong
    votes = np.zeros((5, 2), int)
    sampling.update_oob(votes, np.array([0, 1, 1, 0, 1]), np.array([0, 0, 2]))
    assert votes.tolist() == [[0, 0], [0, 1], [0, 0], [1, 0], [0, 1]]
    right, wrong = sampling.split_pools(votes, np.array([0, 1, 1, 1, 1]))
    assert right.tolist() == [0, 1, 2, 4] and wrong.tolist() == [0, 2, 3]
    assert sampling.split_pools(votes, np.array([0, 1, 1, 1, 1]), "wrong")[0].tolist() == [1, 4]
    assert abs(sampling.oob_error(votes, np.array([0, 1, 1, 1, 1])) - 1 / 3) < 1e-12


def test_prefixes_do_not_depend_on_what_follows():
    x, y = toy()
    short = [t.threshold.tolist() for _, _, t, _ in fit_local_ensemble(x, y, ForestParams(n_trees=3, bite_size=50), 1)]
    long = [t.threshold.tolist() for _, _, t, _ in fit_local_ensemble(x, y, ForestParams(n_trees=6, bite_size=50), 1)]
    assert long[:3] == short


def test_training_is_the_same_however_rows_arrive(rows, forest):
    key = lambda f: sorted((r.tree_id, r.ens_part, tuple(r.feature), tuple(r.threshold)) for r in f.trees.collect())
    again = train.train_mega_forest(rows.orderBy(F.rand(5)).repartition(3), PARAMS)
    assert key(again) == key(forest) and len(key(forest)) == 24
    facts = measures.plan_facts(train.train_blocks(assign_blocks(rows, 4), PARAMS))
    assert facts["exchanges"] == 1
    per = partition_by_block(assign_blocks(rows, 4), 4).select(F.spark_partition_id().alias("p"), "block").distinct().collect()
    assert all(r.p == r.block for r in per) and len(per) == 4


def test_restrict_equals_a_smaller_training(rows, forest):
    from dataclasses import replace

    small = train.train_blocks(assign_blocks(rows, 4).where("block < 2"), replace(PARAMS, n_trees=3))
    key = lambda df: sorted((r.tree_id, tuple(r.threshold)) for r in df.collect())
    assert key(forest.restrict(2, 3).trees) == key(small)


def test_full_lazy_and_committee_agree(rows, forest):
    full = {r.row_id: r.prediction for r in scoring.predict_full(forest, rows).collect()}
    sure = scoring.predict_lazy(forest, rows, rule="certain").collect()
    assert {r.row_id: r.prediction for r in sure} == full and max(r.votes_used for r in sure) <= 24
    never = {r.row_id: (r.prediction, r.votes_used) for r in scoring.predict_lazy(forest, rows, rule="full").collect()}
    assert {k: p for k, (p, _) in never.items()} == full and {v for _, v in never.values()} == {24}
    for order in ("offset", "random", "batch"):
        lazy = scoring.predict_lazy(forest, rows, alpha=0.05, order=order).collect()
        assert np.mean([full[r.row_id] != r.prediction for r in lazy]) <= 0.05
    voted = committee.committee_predict(forest, rows, rule="certain")
    got = voted.collect()
    assert {r.row_id: r.prediction for r in got} == full and len(got) == len(full)
    near = committee.committee_predict(forest, rows, rule="certain", strategy="broadcast_rows")
    assert {r.row_id: r.prediction for r in near.collect()} == full
    half = committee.committee_predict(forest, rows, alpha=0.05, rule="g1_fpc").collect()
    assert sorted(r.row_id for r in half) == sorted(full)
    accuracy = np.mean([full[r.row_id] == r.label for r in rows.select("row_id", "label").collect()])
    assert accuracy > 0.85


def test_union_save_and_resume(rows, forest, tmp_path):
    both = forest.union(forest)
    assert both.trees.select("tree_id").distinct().count() == 48
    path = str(tmp_path / "model")
    back = forest.save(path)
    assert back.trees.count() == 24 and back.params.n_blocks == 4
    waves = str(tmp_path / "waves")
    train.train_in_waves(assign_blocks(rows, 4), PARAMS, waves, wave=3)
    again = train.train_in_waves(assign_blocks(rows, 4), PARAMS, waves, wave=1)
    assert again.trees.count() == 24
    with pytest.raises(ValueError):
        model.pack(forest, max_mb=1e-6)


def test_lazy_votes_in_dataframes_equal_the_loop(spark):
    rng = np.random.default_rng(4)
    votes = (rng.random((40, 30)) < rng.random((40, 1))).astype(int)
    df = spark.createDataFrame([(i, p + 1, int(votes[i, p])) for i in range(40) for p in range(30)], "row_id long, pos int, vote int")
    for name in ("g1_fpc", "g2", "chebyshev", "certain", "bayes"):
        rule = Rule(name, 30, 0.05)
        leads = rule.leads()
        got = {r.row_id: (r.prediction, r.votes_used) for r in scoring.lazy_from_votes(df, rule).collect()}
        for i in range(40):
            ones, used = 0, 30
            for n in range(1, 31):
                ones += votes[i, n - 1]
                if max(ones, n - ones) >= leads[n] or n == 30:
                    used = n
                    break
            assert got[i] == (int(2 * ones > used), used)


def test_simulation_keeps_its_level():
    for name in ("g1_fpc", "g1", "g2_fpc", "g2", "bayes"):
        p, used, lazy, full = draw_points(np.random.default_rng(1), 20_000, Rule(name, 500, 0.01))
        assert (lazy != full).mean() <= 0.012 and used.mean() / 500 < 0.2
    _, used, _, _ = draw_points(np.random.default_rng(1), 4000, Rule("g1_fpc", 10_000, 0.01))
    assert used.mean() / 10_000 < 0.03  # the saving that the method promises


def test_features(spark):
    df = spark.createDataFrame([(1, "aA1 é"), (2, ""), (3, None)], "id long, text string")
    native = {r.id: r.v for r in df.select("id", fx.char_vector(F.col("text")).alias("v")).collect()}
    arrow = {r.row_id: r.features for r in fx.char_histograms(df, "id").collect()}
    assert native == arrow and native[1][62] == 0.4 and sum(native[2]) == 0 == sum(native[3])
    gaps = spark.createDataFrame([(1.0, "x"), (float("nan"), None), (None, "y")], "a double, b string")
    assert [tuple(r) for r in fx.fill_missing(gaps, ["a"], ["b"]).collect()] == [(1.0, "x"), (-9999.0, "missing"), (-9999.0, "y")]
    with pytest.raises(ValueError):
        fx.fill_missing(gaps, ["a"], [], sentinel=5.0)


def count_fits(monkeypatch, folder):
    """Every fitting of a block leaves a file."""
    fit = train._fit_blocks

    def counted(batches, **options):
        import uuid
        from pathlib import Path

        for out in fit(batches, **options):
            for _ in set(out.column("block").to_pylist()):
                Path(f"{folder}/{uuid.uuid4().hex}").touch()
            yield out

    monkeypatch.setattr(train, "_fit_blocks", counted)
    return lambda: len(list(folder.iterdir()))


def test_blocks_are_fitted_once(rows, monkeypatch, tmp_path):
    fits = count_fits(monkeypatch, tmp_path)
    f = train.train_mega_forest(rows, PARAMS)
    assert fits() == 4
    scoring.predict_full(f, rows).count(), scoring.predict_lazy(f, rows).count()
    committee.committee_predict(f, rows).count()
    scoring.accuracy_grid(f, rows, [(2, 3), (4, 6)]).collect()
    assert fits() == 4
    grown, seen = train.train_until_plateau(rows, PARAMS, rows, tolerance=-1.0)
    assert [q for q, _ in seen] == [1, 2, 4] and fits() == 8
    key = lambda trees: sorted((r.tree_id, tuple(r.threshold)) for r in trees.collect())
    assert key(grown.trees) == key(f.trees) and grown.params.n_blocks == 4


def test_waves_and_serial_equal_one_training(rows, forest, tmp_path):
    key = lambda trees: sorted((r.tree_id, tuple(r.threshold)) for r in trees.collect())
    assert key(train.train_in_waves(rows, PARAMS, str(tmp_path / "m"), wave=3).trees) == key(forest.trees)
    assert key(train.train_serial(rows, PARAMS).trees) == key(forest.trees.where("block = 0"))


def test_a_committee_moves_rows_and_trees_once(rows, forest):
    first = committee.committee_pass(forest, rows, groups=3)
    assert measures.plan_facts(first)["exchanges"] == 1
    tallies = committee.partition_tallies(forest, rows.select("row_id", "features"), groups=5)
    assert measures.plan_facts(tallies)["exchanges"] == 1 and measures.plan_facts(tallies)["broadcasts"] == 0
    one, many = ({(r.ens_part, r.row_id, r.vote): r.n for r in committee.partition_tallies(forest, rows.select("row_id", "features"), groups=g).collect()} for g in (1, 7))
    assert one == many and sum(one.values()) == 24 * 600
    assert measures.shuffled_bytes(rows.groupBy("label").count()) > 0
    few = committee.tallies_by_broadcast(forest, rows.select("row_id", "features"), max_mb=1e-6)
    assert few.count() == len(one)


def test_keyed_places_are_permutations():
    for size in (1, 2, 5, 64, 1000):
        keys = np.array([0, 7, 1 << 61])
        places = np.array([scoring.keyed_place(keys, s, size) for s in range(size)])
        assert (np.sort(places, axis=0) == np.arange(size)[:, None]).all()
    assert len({tuple(scoring.keyed_place(np.arange(200), s, 5)[k] for s in range(5)) for k in range(200)}) > 60


def always_one(x, y, n_classes, rng, **options):
    return fit_tree(x, np.ones(len(y), int), n_classes, rng)


def test_own_learners_and_stored_parameters(spark, rows, tmp_path):
    from dataclasses import replace

    f = train.train_mega_forest(rows, replace(PARAMS, learner=always_one, n_blocks=2), str(tmp_path / "own"))
    assert {r.prediction for r in scoring.predict_full(f, rows).collect()} == {1}
    kept = replace(PARAMS, n_attr=3, resample=True, max_depth=4)
    back = train.train_mega_forest(rows, kept, str(tmp_path / "kept")).params
    assert back == kept
    assert f.union(f).params.n_blocks == 4 and f.restrict(1, 2).params.n_trees == 2


def test_resampled_attributes_find_a_cut():
    x = np.zeros((40, 12))
    x[:, 3] = np.arange(40)
    y = (np.arange(40) > 17).astype(int)
    fit = lambda again: [len(fit_tree(x, y, 2, np.random.default_rng(k), n_attr=2, resample=again).feature) > 1 for k in range(30)]
    assert all(fit(True)) and not all(fit(False))


def test_bite_sizes_meet_the_validation_rows_where_they_are(rows):
    got = train.tune_bite_size(rows, [20, 200], PARAMS, rows).orderBy("bite_size").collect()
    assert [r.bite_size for r in got] == [20, 200] and got[0].nodes < got[1].nodes and got[1].accuracy > 0.8


def test_disagreement_stays_below_the_level_at_any_size():
    from blockforest.operators.simulate import draw_points

    for m in (100, 1000, 5000):
        for alpha in (0.05, 0.01):
            for name in ("g1_fpc", "g2", "bayes"):
                _, _, lazy, full = draw_points(np.random.default_rng(m), 20_000, Rule(name, m, alpha))
                assert (lazy != full).mean() <= alpha * 1.15 + 0.001


def test_bayes_over_several_classes():
    rng = np.random.default_rng(3)
    tallies = rng.multinomial(12, [0.5, 0.3, 0.2], 40)
    exact, drawn = (Rule("bayes", 20, 0.05, multi=m).stops_tallies(tallies, 12) for m in ("exact", "sampled"))
    assert (exact == drawn).mean() > 0.85 and 0 < exact.sum() < 40
    pairs = Rule("bayes", 20, 0.05).stops_tallies(tallies, 12)
    assert (pairs == exact).mean() > 0.7
    with pytest.raises(ValueError):
        Rule("bayes", 20, multi="else")


def test_map_only_union_has_the_same_trees(rows, forest):
    here = model.merge_ensembles(train.train_blocks(assign_blocks(rows, 4), PARAMS), PARAMS, mode="map")
    key = lambda trees: sorted((r.tree_id, r.ens_part, tuple(r.threshold)) for r in trees.collect())
    assert key(here.trees) == key(forest.trees)
