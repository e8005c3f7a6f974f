"""The experiments on the given tables; every one returns rows of ``workload, metric, value, params``."""

from __future__ import annotations

import time
from dataclasses import replace
from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import measures
from ..functions.hashing import portable_hash, portable_sql
from ..functions.stopping import Rule, bayes_final_prob, bayes_final_prob_primes, bayes_leads
from ..operators import committee as committees
from ..operators import features as fx
from ..operators.blocks import assign_blocks
from ..operators.schemas import METRIC, ForestParams
from ..operators.scoring import accuracy_grid, predict_full, predict_lazy
from ..operators.simulate import simulate
from ..operators.train import train_blocks, train_mega_forest, train_serial, train_until_plateau, tune_bite_size
from ..sources.tables import load, written

#: Levels of disagreement that the simulations compare.
LEVELS = (0.05, 0.01, 1e-3, 1e-4)
FIVE_RULES = ("g1_fpc", "g1", "g2_fpc", "g2", "bayes")


def metric_rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(w, m, None if v is None else float(v), {k: str(x) for k, x in p.items()}) for w, m, v, p in rows], METRIC)


_HELD: list[DataFrame] = []
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def _kept(df: DataFrame) -> DataFrame:
    """Persisted until the experiment that asked for it is over; compact rows are in a table as it is."""
    if "features" in df.columns and fx.is_compact(df):
        return df
    _HELD.append(df.persist())
    return df


def experiment(run):
    """An experiment whose result is made of plain numbers: what it persisted is given back at its end.

    Its shuffle files go with the query that wrote them, and don't pile up from step to step.
    """

    @wraps(run)
    def inner(*args, **kw):
        before = len(_HELD)
        conf = args[0].conf
        clean = conf.get(_CLEANUP, None)
        conf.set(_CLEANUP, "true")
        try:
            return run(*args, **kw)
        finally:
            conf.unset(_CLEANUP) if clean is None else conf.set(_CLEANUP, clean)
            while len(_HELD) > before:
                _HELD.pop().unpersist()

    return inner


# -- learning sets ----------------------------------------------------------------------------------------


def weblang(spark: SparkSession, sf_dir: str, table: str = "documents", classes: str = "binary", flip: float = 0.0) -> tuple[DataFrame, DataFrame]:
    """(train, test): 63 character proportions, English or not (or the language); equal texts stay on one side.

    A share of the labels of two classes may be flipped, chosen by hash.
    """
    if flip and classes != "binary":
        raise ValueError("only labels of two classes can be flipped")
    if table == "documents":
        df = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("row_id"), "text", "lang")
    else:
        df = load(spark, sf_dir, "pages").select(F.col("page_id").alias("row_id"), fx.html_text(F.col("html")).alias("text"), fx.html_lang(F.col("html")).alias("lang"))
    label = (F.col("lang") == "en").cast("int") if classes == "binary" else (F.array_position(F.array(*map(F.lit, ("de", "en", "es", "fr"))), F.col("lang")) - 1).cast("int")
    if flip:
        label = F.when(portable_hash("flip", F.col("row_id")) < flip * 2**32, 1 - label).otherwise(label)
    train, test = fx.split_grouped(df, F.md5("text"))
    shape = lambda d: fx.char_histograms(d.withColumn("label", label), "row_id", also=("label",))
    return shape(train), shape(test)


def labelled_documents(spark: SparkSession, sf_dir: str, target: str = "quality") -> tuple[DataFrame, DataFrame]:
    docs, labels = load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")
    df = docs.join(labels, "doc_id").select("doc_id", "text", F.col(target).cast("int").alias("label"))
    train, test = fx.split_grouped(df, F.md5("text"))
    shape = lambda d: fx.char_histograms(d, "doc_id", also=("label",))
    return shape(train), shape(test)


def embeddings(spark: SparkSession, sf_dir: str, classes: str = "binary") -> tuple[DataFrame, DataFrame]:
    label = (F.col("label") < 3).cast("int") if classes == "binary" else F.col("label")
    df = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), F.col("embedding").cast("array<double>").alias("features"), label.alias("label"))
    return fx.split_grouped(df, F.col("row_id"))


STAR_NUMERIC = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "p_size", "p_retailprice", "o_totalprice", "c_acctbal", "s_acctbal", "ship_month", "order_month"]


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items with their order, part, supplier and customer; dimensions are joined by size, as Spark sees fit."""
    t = {n: load(spark, sf_dir, n) for n in ("lineitem", "orders", "part", "supplier", "customer", "nation")}
    orders = t["orders"].join(t["customer"].join(t["nation"], F.col("c_nationkey") == F.col("n_nationkey")), F.col("o_custkey") == F.col("c_custkey"))  # before line items, which are more
    joined = t["lineitem"].join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(t["part"], F.col("l_partkey") == F.col("p_partkey")).join(t["supplier"], F.col("l_suppkey") == F.col("s_suppkey"))
    key = F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    return joined.select("*", key.alias("row_id"), F.month("l_shipdate").alias("ship_month"), F.month("o_orderdate").alias("order_month"))


def high_value_lines(spark: SparkSession, sf_dir: str, flip: float = 0.0) -> tuple[DataFrame, DataFrame]:
    """(train, test) by time: is a line's value high? A share of the labels may be flipped, chosen by hash."""
    df = star(spark, sf_dir)
    homes = {"p_brand": "part", "c_mktsegment": "customer", "o_orderpriority": "orders", "n_name": "nation"}
    domains = {c: fx.domain(load(spark, sf_dir, table), c) for c, table in homes.items()}  # of the dimensions, not of their join
    label = (F.col("l_quantity") * F.col("l_extendedprice") * (1 - F.col("l_discount")) > 1.6e6).cast("int")
    if flip:
        label = F.when(portable_hash("flip", F.col("row_id")) < flip * 2**32, 1 - label).otherwise(label)
    # Joined once, and written as plain columns; rows of 0/1 columns would be ten times as large wherever they lie.
    # Categories are looked up here, not by every step that reads the table.
    places, width = fx.places(domains)
    lines = written(df.select("row_id", *STAR_NUMERIC, *places, label.alias("label"), "l_shipdate"), "lines")
    rows = fx.narrow(lines, "row_id", STAR_NUMERIC, [F.col(c) for c in domains], width, "label", "l_shipdate")
    train, test = fx.split_time(rows, "l_shipdate", "2001-01-01 00:00:00")
    return train.drop("l_shipdate"), test.drop("l_shipdate")


def error_days(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(train, test): did a user's day have an error event? From the day's other events."""
    e = load(spark, sf_dir, "events").withColumn("day", F.to_date("ts")).withColumn("k", F.get_json_object("props", "$.k").cast("double"))
    other = F.col("event_type") != "error"
    kinds = [k for k in fx.domain(e, "event_type") if k != "error"]
    per = e.groupBy("user_id", "day").agg(
        F.count_if(~other).alias("errors"), *[F.count_if(F.col("event_type") == k).alias(f"n_{k}") for k in kinds], F.sum(F.when(other, F.col("value"))).alias("value"), F.avg(F.when(other, F.col("k"))).alias("k"),
        *[F.count_if(other & F.hour("ts").between(6 * h, 6 * h + 5)).alias(f"h_{h}") for h in range(4)],
    )
    names = [*[f"n_{k}" for k in kinds], "value", "k", *[f"h_{h}" for h in range(4)]]
    per = fx.fill_missing(per.withColumn("label", fx.to_presence(F.col("errors"))).withColumn("row_id", F.xxhash64("user_id", "day")), ["value", "k"], [], check=False)
    rows = fx.assemble(per, "row_id", names, "label", F.col("day").cast("timestamp_ntz").alias("day"))
    days = load(spark, sf_dir, "events").agg(F.percentile_approx(F.unix_seconds(F.col("ts").cast("timestamp")), 0.8, 10000)).first()[0]
    cut = time.strftime("%Y-%m-%d 00:00:00", time.gmtime(days))
    train, test = fx.split_time(rows, "day", cut)
    return train.drop("day"), test.drop("day")


def learning_set(spark: SparkSession, sf_dir: str, name: str, **options) -> tuple[DataFrame, DataFrame]:
    makers = {"weblang": weblang, "birds": high_value_lines, "error_days": error_days, "embeddings": embeddings, "labels": labelled_documents}
    return makers[name](spark, sf_dir, **options)


# -- experiments -------------------------------------------------------------------------------------------


def _share(pred: DataFrame, truth: DataFrame) -> float:
    return measures.accuracy(pred, truth).first()[0]


@experiment
def fit_and_score(spark, sf_dir, workload="weblang", params=ForestParams(n_trees=10, bite_size=100, n_blocks=4), **options) -> DataFrame:
    """One mega-forest: data facts, accuracy, size, and what the scan and shuffle of training look like."""
    train, test = learning_set(spark, sf_dir, workload, **options)
    train, test = _kept(train), _kept(test)
    began = time.perf_counter()
    blocked = assign_blocks(train, params.n_blocks, seed=params.seed)
    facts = measures.plan_facts(train_blocks(blocked, params))
    forest = train_mega_forest(blocked, params)
    n = forest.trees.count()
    seconds = time.perf_counter() - began
    rows = [(workload, f"{r.part}_{k}", r[k], {}) for r in measures.dataset_summary(train, test).collect() for k in ("rows", "features", "positive_share")]
    size = forest.size().first()
    rows += [(workload, "trees", n, {}), (workload, "train_seconds", seconds, {}), (workload, "accuracy", _share(predict_full(forest, test), test), {}), (workload, "model_bytes", size.bytes, {}), (workload, "exchanges", facts["exchanges"], {})]
    return metric_rows(spark, rows)


@experiment
def accuracy_time(spark, sf_dir, workload="weblang", local_sizes=(1, 5, 10, 25), serial_sizes=(25, 50, 100), samplers=("importance", "bagging"), params=ForestParams(n_trees=25, bite_size=100, n_blocks=8), seed: int = 42, **options) -> DataFrame:
    """Accuracy and training time by ensemble size: mega-forest, bagged forest, serial baseline.

    A line is one training at its largest size; smaller sizes are prefixes. The time of a prefix is the slowest
    block's fitting time, which is what a cluster with a worker for each block waits for.
    """
    train, test = (_kept(d) for d in learning_set(spark, sf_dir, workload, **options))
    rows = []
    for sampler in samplers:
        p = replace(params, sampler=sampler, n_trees=max(local_sizes), seed=seed)
        began = time.perf_counter()
        forest = train_mega_forest(train, p)
        rows.append((workload, "wall_seconds", time.perf_counter() - began, {"line": sampler, "trees": p.n_trees * p.n_blocks}))
        grid = {(r.blocks, r.local_size): r for r in accuracy_grid(forest, test, [(p.n_blocks, k) for k in local_sizes]).collect()}
        for k in local_sizes:
            ms = forest.trees.where(F.col("iter") < k).groupBy("block").agg(F.sum("fit_ms").alias("ms")).agg(F.max("ms")).first()[0]
            rows += [(workload, "accuracy", grid[(p.n_blocks, k)].accuracy, {"line": sampler, "trees": k * p.n_blocks}), (workload, "seconds", ms / 1000, {"line": sampler, "trees": k * p.n_blocks})]
    p = replace(params, n_trees=max(serial_sizes), seed=seed)
    serial = train_serial(train, p)
    grid = {r.local_size: r for r in accuracy_grid(serial, test, [(1, k) for k in serial_sizes]).collect()}
    for k in serial_sizes:
        ms = serial.trees.where(F.col("iter") < k).agg(F.sum("fit_ms")).first()[0]
        rows += [(workload, "accuracy", grid[k].accuracy, {"line": "serial", "trees": k}), (workload, "seconds", ms / 1000, {"line": "serial", "trees": k})]
    # the time at which each line is as accurate as the serial one at its best
    points: dict[tuple, dict] = {}
    for _, m, v, at in rows:
        points.setdefault((at["line"], at["trees"]), {})[m] = v
    lines = spark.createDataFrame([(line, float(v["accuracy"]), float(v["seconds"])) for (line, _), v in points.items() if "accuracy" in v], "line string, accuracy double, seconds double")
    best = max(v["accuracy"] for (line, _), v in points.items() if line == "serial")
    rows += [(workload, "seconds_to_serial_accuracy", r.seconds, {"line": r.line}) for r in measures.time_to_accuracy(lines, F.lit(best)).collect()]
    return metric_rows(spark, rows)


def accuracy_blocks(spark, sf_dir, workload="weblang", qs=(1, 2, 4, 8), local_sizes=(5, 25), params=ForestParams(n_trees=25, bite_size=100, n_blocks=8), **options) -> DataFrame:
    """Accuracy by number of blocks and trees in each, from one forest and one scan of the test rows."""
    train, test = learning_set(spark, sf_dir, workload, **options)
    p = replace(params, n_trees=max(local_sizes))
    forest = train_mega_forest(train, p)
    grid = accuracy_grid(forest, test, [(q, k) for q in qs for k in local_sizes])
    return grid.select(F.lit(workload).alias("workload"), F.lit("accuracy").alias("metric"), F.col("accuracy").alias("value"), F.create_map(F.lit("blocks"), F.col("blocks").cast("string"), F.lit("local_size"), F.col("local_size").cast("string")).alias("params"))


def bite_sizes(spark, sf_dir, workload="weblang", sizes=(50, 100, 200, 400), params=ForestParams(n_trees=25, n_blocks=2), **options) -> DataFrame:
    """Accuracy by bite size on one block."""
    train, test = learning_set(spark, sf_dir, workload, **options)
    out = tune_bite_size(train, list(sizes), params, test)
    return out.select(F.lit(workload).alias("workload"), F.lit("accuracy").alias("metric"), F.col("accuracy").alias("value"), F.create_map(F.lit("bite_size"), F.col("bite_size").cast("string"), F.lit("nodes"), F.col("nodes").cast("string")).alias("params"))


@experiment
def lazy_real(spark, sf_dir, workload="weblang", ms=(50, 100, 200), alphas=(0.05, 0.01, 1e-3), rule="g1_fpc", params=ForestParams(n_trees=25, bite_size=100, n_blocks=8), **options) -> DataFrame:
    """Evaluation fraction, relative error, disagreement of lazy votes on trained forests, by size and level."""
    train, test = (_kept(d) for d in learning_set(spark, sf_dir, workload, **options))
    forest = train_mega_forest(train, params)
    rows = []
    for m in ms:
        part = forest.restrict(local_size=max(1, m // params.n_blocks))
        size = params.n_blocks * max(1, m // params.n_blocks)
        full = _kept(predict_full(part, test).select("row_id", F.col("prediction").alias("full_prediction")).join(test.select("row_id", "label"), "row_id"))
        for alpha in alphas:
            lazy = predict_lazy(part, test, rule, alpha).join(full, "row_id")
            r = lazy.agg(F.avg("votes_used").alias("v"), F.avg((F.col("prediction") == F.col("label")).cast("double")).alias("l"), F.avg((F.col("full_prediction") == F.col("label")).cast("double")).alias("f"), F.avg((F.col("prediction") != F.col("full_prediction")).cast("double")).alias("d")).first()
            at = {"m": size, "alpha": alpha}
            rows += [(workload, "eval_fraction", r.v / size, at), (workload, "relative_error", 1 - r.l / r.f, at), (workload, "disagreement", r.d, at), (workload, "savings", size / r.v, at)]
    return metric_rows(spark, rows)


@experiment
def stop_points(spark, sf_dir, workload="weblang", alpha=0.01, params=ForestParams(n_trees=25, bite_size=100, n_blocks=8), **options) -> DataFrame:
    """Histogram of the votes that rows need, and the shares that need few or all."""
    train, test = learning_set(spark, sf_dir, workload, **options)
    forest = train_mega_forest(train, params)
    pred = _kept(predict_lazy(forest, test, alpha=alpha))
    m = params.n_trees * params.n_blocks
    rows = [(workload, "stop_bin", r.n, {"low": r.low}) for r in measures.stop_histogram(pred).collect()]
    s = measures.share_within(pred, 100, m).first()
    return metric_rows(spark, [*rows, (workload, "share_within_100", s.share_within, {}), (workload, "share_all", s.share_all, {})])


def shallow(spark, sf_dir, max_depth=6, **kw) -> DataFrame:
    """Lazy votes of depth-limited trees, as for ensembles too large for full-grown ones."""
    return lazy_real(spark, sf_dir, ms=(200,), params=ForestParams(n_trees=25, bite_size=100, n_blocks=8, max_depth=max_depth), **kw)


@experiment
def committee(spark, sf_dir, workload="weblang", p=4, alpha=0.01, params=ForestParams(n_trees=25, bite_size=100, n_blocks=8), **options) -> DataFrame:
    """Coverage, undecided rate and agreement with the full vote of committee evaluation."""
    train, test = (_kept(d) for d in learning_set(spark, sf_dir, workload, **options))
    params = replace(params, n_parts=p)
    forest = train_mega_forest(train, params)
    pred = _kept(committees.committee_predict(forest, test, alpha=alpha))
    stats = committees.committee_stats(pred).first()
    differ = measures.disagreement(pred, predict_full(forest, test)).first()[0]
    rows = [("committee", "rows", stats.rows, {"p": p}), ("committee", "test_rows", test.count(), {"p": p}), ("committee", "undecided_rate", stats.undecided_rate, {"p": p}), ("committee", "disagreement", differ, {"p": p}), ("committee", "accuracy", _share(pred, test), {"p": p})]
    return metric_rows(spark, rows)


def sim(spark, rules=FIVE_RULES, ms=(100, 500, 1000, 5000, 10_000), alphas=(1e-4,), n_points=1_000_000, seed=42) -> DataFrame:
    """Simulated votes: evaluation fraction and errors by rule, size and level."""
    return simulate(spark, n_points, [Rule(r, m, a) for r in rules for m in ms for a in alphas], seed)


def threshold_times(spark, ms=(100, 1000, 10_000, 100_000, 200_000, 1_000_000), bayes_ms=(100, 1000, 10_000, 100_000), log_ms=(100, 1000, 10_000), prime_ms=(30, 100)) -> DataFrame:
    """Milliseconds to build a table of thresholds, by rule and size: Gaussian, Bayesian from vote to vote, in log space, by primes."""
    def timed(f):
        began = time.perf_counter()
        f()
        return 1000 * (time.perf_counter() - began)

    rows = [("threshold_time", "ms", timed(Rule("g1_fpc", m).leads), {"rule": "gaussian", "m": m}) for m in ms]
    rows += [("threshold_time", "ms", timed(lambda m=m: bayes_leads(m, 0.01)), {"rule": "bayes", "m": m}) for m in bayes_ms]
    rows += [("threshold_time", "ms", timed(lambda m=m: bayes_leads(m, 0.01, bayes_final_prob)), {"rule": "bayes_log", "m": m}) for m in log_ms]
    rows += [("threshold_time", "ms", timed(lambda m=m: bayes_leads(m, 0.01, bayes_final_prob_primes)), {"rule": "bayes_primes", "m": m}) for m in prime_ms]
    return metric_rows(spark, rows)


def clean_birds(spark, sf_dir) -> DataFrame:
    """The preprocessing chain on line items with injected gaps: limit, recode, monthly value, tokens, sentinels, 0/1."""
    key = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    df = star(spark, sf_dir).where("l_quantity <= 45")
    gap = lambda c, s: F.when(portable_hash(s, F.concat_ws("|", *key)) < 0.05 * 2**32, F.lit(None)).otherwise(F.col(c))
    df = df.withColumn("l_tax", gap("l_tax", "tax")).withColumn("c_mktsegment", gap("c_mktsegment", "segment"))
    df = fx.recode(df, "o_orderpriority", {"4-NOT SPECIFIED": "5-LOW"})
    monthly = df.groupBy("n_name").pivot("ship_month", list(range(1, 13))).agg(F.avg("l_extendedprice")).select(F.col("n_name").alias("nm"), *[F.col(str(i)).alias(f"m{i}") for i in range(1, 13)])
    df = df.join(F.broadcast(monthly), F.col("n_name") == F.col("nm")).withColumn("month_price", fx.pick_by_month(F.col("ship_month"), [F.col(f"m{i}") for i in range(1, 13)]))
    df = fx.fill_missing(df, ["l_tax"], ["c_mktsegment"])
    df = fx.one_hot(df, {"o_orderpriority": [p for p in fx.domain(load(spark, sf_dir, "orders"), "o_orderpriority") if p != "4-NOT SPECIFIED"]})
    return df.select(*key, "l_quantity", "l_tax", "c_mktsegment", F.round("month_price", 6).alias("month_price"), *[c for c in df.columns if c.startswith("o_orderpriority_")])


_KEY = "concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey)"
CLEAN_BIRDS_SQL = f"""
WITH s AS (SELECT l.*, {_KEY} AS k, CASE o_orderpriority WHEN '4-NOT SPECIFIED' THEN '5-LOW' ELSE o_orderpriority END AS priority, c_mktsegment AS segment, n_name, month(l_shipdate) AS m
  FROM lineitem l JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE l_quantity <= 45),
p AS (SELECT n_name, m, avg(l_extendedprice) AS price FROM s GROUP BY n_name, m)
SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, CASE WHEN {portable_sql('tax', 'k')} < 0.05 * 4294967296 THEN -9999.0::DOUBLE ELSE l_tax END AS l_tax,
  CASE WHEN {portable_sql('segment', 'k')} < 0.05 * 4294967296 THEN 'missing' ELSE segment END AS c_mktsegment, round(price, 6) AS month_price,
  (priority = '1-URGENT')::INT AS o_orderpriority_1_urgent, (priority = '2-HIGH')::INT AS o_orderpriority_2_high, (priority = '3-MEDIUM')::INT AS o_orderpriority_3_medium, (priority = '5-LOW')::INT AS o_orderpriority_5_low
FROM s JOIN p USING (n_name, m)"""


@experiment
def majority_and_single(spark, sf_dir, workload="weblang", **options) -> DataFrame:
    """Floors: the commonest class, a stump, one tree."""
    train, test = (_kept(d) for d in learning_set(spark, sf_dir, workload, **options))
    rows = []
    for learner in ("majority", "stump", "tree"):
        p = ForestParams(n_trees=1, bite_size=200, n_blocks=1, sampler="bagging", learner=learner)
        rows.append((workload, "accuracy", _share(predict_full(train_mega_forest(train, p), test), test), {"learner": learner}))
    return metric_rows(spark, rows)


@experiment
def mllib_forest(spark, sf_dir, workload="weblang", trees=20, **options) -> DataFrame:
    """The multi-pass, all-data forest that Spark ships, for time and accuracy beside ours."""
    from pyspark.ml.classification import RandomForestClassifier
    from pyspark.ml.functions import array_to_vector

    train, test = (d.select("row_id", array_to_vector("features").alias("features"), "label") for d in learning_set(spark, sf_dir, workload, **options))
    began = time.perf_counter()
    model = RandomForestClassifier(numTrees=trees, maxDepth=10, seed=1).fit(train)
    seconds = time.perf_counter() - began
    share = model.transform(test).agg(F.avg((F.col("prediction") == F.col("label")).cast("double"))).first()[0]
    return metric_rows(spark, [(workload, "accuracy", share, {"line": "all-data forest", "trees": trees}), (workload, "seconds", seconds, {"line": "all-data forest", "trees": trees})])


@experiment
def draw_orders(spark, sf_dir, workload="weblang", params=ForestParams(n_trees=25, bite_size=100, n_blocks=8), **options) -> DataFrame:
    """Votes and seconds with a fresh order for every row, one offset for each row, one for a batch."""
    train, test = (_kept(d) for d in learning_set(spark, sf_dir, workload, **options))
    forest = train_mega_forest(train, params)
    rows = []
    predict_lazy(forest, test).agg(F.avg("votes_used")).first()  # rows and workers are there before the clock starts
    for order in ("random", "offset", "batch"):
        began = time.perf_counter()
        votes = predict_lazy(forest, test, order=order).agg(F.avg("votes_used")).first()[0]
        rows += [("draw_order", "votes", votes, {"order": order}), ("draw_order", "seconds", time.perf_counter() - began, {"order": order})]
    return metric_rows(spark, rows)


@experiment
def skewed_blocks(spark, sf_dir, params=ForestParams(n_trees=10, bite_size=100, n_blocks=4)) -> DataFrame:
    """Blocks sorted by label against random ones: why rows are dealt at random."""
    train, test = (_kept(d) for d in weblang(spark, sf_dir, flip=0.1))
    rows = []
    for mode in ("random", "sorted"):
        blocked = assign_blocks(train, params.n_blocks, mode=mode, by="label")
        rows.append(("skewed_blocks", "accuracy", _share(predict_full(train_mega_forest(blocked, params), test), test), {"mode": mode}))
    return metric_rows(spark, rows)


@experiment
def multiclass_bayes(spark, sf_dir, params, alpha=0.01) -> DataFrame:
    """The Bayesian rule over four classes: leader against runner-up, and by draws from the posterior."""
    train, test = (_kept(d) for d in weblang(spark, sf_dir, classes="multi"))
    forest = train_mega_forest(train, params)
    rows = []
    for multi in ("pairwise", "sampled"):
        lazy = predict_lazy(forest, test, "bayes", alpha, multi=multi, also_full=True)
        r = lazy.agg(F.avg("votes_used").alias("v"), F.avg((F.col("prediction") != F.col("full_prediction")).cast("double")).alias("d")).first()
        rows += [("multiclass_bayes", "votes", r.v, {"multi": multi}), ("multiclass_bayes", "disagreement", r.d, {"multi": multi})]
    return metric_rows(spark, rows)


@experiment
def plateau(spark, sf_dir, params=ForestParams(n_trees=10, bite_size=100, n_blocks=16)) -> DataFrame:
    """Blocks are doubled until the accuracy moves no more."""
    train, test = (_kept(d) for d in weblang(spark, sf_dir, flip=0.1))
    _, seen = train_until_plateau(train, params, test)
    return metric_rows(spark, [("plateau", "accuracy", share, {"blocks": q}) for q, share in seen])
