"""The methods as queries, each with a DuckDB twin: features, blocks, bites, splits, thresholds, lazy votes, measures.

The Spark side calls the library's operators; the twin computes the same by SQL alone. Where a method draws at random it
draws by a portable hash (``PortableRng``), so that both engines take the same rows.
"""

from __future__ import annotations

import re
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import measures
from ..functions.hashing import PortableRng, portable_hash, portable_sql
from ..functions.stopping import Rule, correction_column, lead_column, stored_thresholds, thresholds_sql
from ..operators import blocks, committee, sampling, scoring, splits, tree
from ..operators import features as fx
from ..operators.model import MegaForest
from ..operators.schemas import TREE, ForestParams
from ..operators.train import matrix, train_in_waves, train_mega_forest, train_serial, train_until_plateau, tune_bite_size
from ..sources.tables import block_storage, load, shared_path, views, write_blocks

Q: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {}
#: Voters and level of the votes made by hash.
M, ALPHA = 64, 0.01


def add(name: str, spark, duck: str) -> None:
    if isinstance(spark, str):
        text = spark
        spark = lambda s, d: views(s, d, text).sql(text)
    Q[name] = (spark, duck)


def duck(template: str) -> str:
    """DuckDB's text: {h[seed|expression]} is the portable hash, {r[a;b]} the numbers from a to b."""
    text = re.sub(r"\{h\[([^|\]]+)\|([^\]]+)\]\}", lambda m: portable_sql(m[1], m[2]), template)
    return re.sub(r"\{r\[([^;\]]+);([^\]]+)\]\}", r"unnest(range(\1, (\2) + 1))", text)


# -- features and preprocessing ---------------------------------------------------------------------------

_SHARES = ", ".join(f"round((length(text) - length(replace(text, '{c}', ''))) / length(text)::DOUBLE, 8) AS {n}" for c, n in zip(fx.ALPHANUMERICS, fx.CHAR_FEATURES, strict=False))
_SHARES += ", round(length(regexp_replace(text, '[0-9a-zA-Z]', '', 'g')) / length(text)::DOUBLE, 8) AS p_other"
add("char_proportions_docs", lambda s, d: load(s, d, "documents").select("doc_id", *fx.char_proportions(F.col("text"), 8)), f"SELECT doc_id, {_SHARES} FROM documents")
add("char_proportions_pages", lambda s, d: load(s, d, "pages").select("page_id", F.regexp_replace("html", "<[^>]*>", " ").alias("text")).select("page_id", *fx.char_proportions(F.col("text"), 8)), f"SELECT page_id, {_SHARES} FROM (SELECT page_id, regexp_replace(html, '<[^>]*>', ' ', 'g') AS text FROM pages)")
add("char_histogram_arrow", lambda s, d: fx.char_histograms(load(s, d, "documents"), "doc_id").select(F.col("row_id").alias("doc_id"), *[F.round(F.col("features")[i], 8).alias(n) for i, n in enumerate(fx.CHAR_FEATURES)]), f"SELECT doc_id, {_SHARES} FROM documents")
add("html_lang_label", lambda s, d: load(s, d, "pages").select("page_id", fx.html_lang(F.col("html")).alias("lang")).withColumn("label", (F.col("lang") == "en").cast("int")), """SELECT page_id, regexp_extract(html, '<html[^>]*lang="([a-z]+)"', 1) AS lang, (regexp_extract(html, '<html[^>]*lang="([a-z]+)"', 1) = 'en')::INT AS label FROM pages""")
add("html_text_pages", lambda s, d: load(s, d, "pages").select("page_id", F.md5(fx.html_text(F.col("html"))).alias("text_md5"), F.length(fx.html_text(F.col("html"))).alias("n")), "SELECT page_id, md5(t) AS text_md5, length(t)::INT AS n FROM (SELECT page_id, regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g') AS t FROM pages)")
_SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
add("one_hot_customers", lambda s, d: fx.one_hot(load(s, d, "customer"), {"c_mktsegment": _SEGMENTS}).select("c_custkey", *[f"c_mktsegment_{x.lower()}" for x in _SEGMENTS]), "SELECT c_custkey, " + ", ".join(f"(c_mktsegment = '{x}')::INT AS c_mktsegment_{x.lower()}" for x in _SEGMENTS) + " FROM customer")


def _gaps(s, d):
    df = load(s, d, "orders").select("o_orderkey", F.when(portable_hash("gn", F.col("o_orderkey")) % 20 == 0, F.lit(None)).otherwise(F.col("o_totalprice")).alias("price"), F.when(portable_hash("gc", F.col("o_orderkey")) % 20 == 0, F.lit(None)).otherwise(F.col("o_orderpriority")).alias("priority"))
    return fx.fill_missing(df, ["price"], ["priority"])


add("fill_missing_inject", _gaps, f"SELECT o_orderkey, CASE WHEN {portable_sql('gn', 'o_orderkey')} % 20 = 0 THEN -9999.0::DOUBLE ELSE o_totalprice END AS price, CASE WHEN {portable_sql('gc', 'o_orderkey')} % 20 = 0 THEN 'missing' ELSE o_orderpriority END AS priority FROM orders")
add("recode_rare", lambda s, d: fx.recode(load(s, d, "orders"), "o_orderstatus", {"P": "O"}).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n")), "SELECT CASE o_orderstatus WHEN 'P' THEN 'O' ELSE o_orderstatus END AS o_orderstatus, count(*) AS n FROM orders GROUP BY 1")


def _by_month(s, d):
    o = load(s, d, "orders").withColumn("m", F.month("o_orderdate"))
    wide = o.groupBy("o_orderpriority").pivot("m", list(range(1, 13))).agg(F.count(F.lit(1))).na.fill(0)
    wide = wide.select(F.col("o_orderpriority").alias("p"), *[F.col(str(i)).alias(f"m{i}") for i in range(1, 13)])
    return o.join(F.broadcast(wide), F.col("o_orderpriority") == F.col("p")).select("o_orderkey", fx.pick_by_month(F.col("m"), [F.col(f"m{i}") for i in range(1, 13)]).alias("n"))


add("pick_by_month", _by_month, "SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderpriority, month(o_orderdate)) AS n FROM orders")
add("to_presence_events", lambda s, d: load(s, d, "events").groupBy("user_id", F.to_date("ts").alias("day")).agg(fx.to_presence(F.count_if(F.col("event_type") == "error")).alias("label")), "SELECT user_id, ts::DATE AS day, (count(*) FILTER (WHERE event_type = 'error') > 0)::INT AS label FROM events GROUP BY 1, 2")


def _sides(s, d):
    train, test = fx.split_grouped(load(s, d, "documents"), F.md5("text"))
    return train.select("doc_id", F.lit("train").alias("part")).unionAll(test.select("doc_id", F.lit("test").alias("part")))


add("split_by_content", _sides, f"SELECT doc_id, CASE WHEN {portable_sql('split', 'md5(text)')} % 5 = 0 THEN 'test' ELSE 'train' END AS part FROM documents")


def _times(s, d):
    a, b = fx.split_time(load(s, d, "lineitem"), "l_shipdate", "2001-01-01 00:00:00")
    return a.agg(F.count(F.lit(1)).alias("n")).select(F.lit("train").alias("part"), "n").unionAll(b.agg(F.count(F.lit(1)).alias("n")).select(F.lit("test").alias("part"), "n"))


add("split_time", _times, "SELECT CASE WHEN l_shipdate < TIMESTAMP '2001-01-01' THEN 'train' ELSE 'test' END AS part, count(*) AS n FROM lineitem GROUP BY 1")
add("filter_effort", lambda s, d: load(s, d, "lineitem").where("l_quantity <= 45").agg(F.count(F.lit(1)).alias("n"), F.max("l_quantity").alias("top")), "SELECT count(*) AS n, max(l_quantity) AS top FROM lineitem WHERE l_quantity <= 45")
add("sample_exact", lambda s, d: fx.sample_exact(load(s, d, "documents").select("doc_id"), 40, "doc_id"), f"SELECT doc_id FROM documents ORDER BY {portable_sql('sample', 'doc_id')}, doc_id LIMIT 40")
_LABELLED = "(SELECT doc_id AS row_id, (lang = 'en')::INT AS label FROM documents)"


def labelled(s, d):
    return load(s, d, "documents").select(F.col("doc_id").alias("row_id"), (F.col("lang") == "en").cast("int").alias("label"))


def _summary(s, d):
    rows = labelled(s, d).withColumn("features", F.array(F.lit(1.0)))
    train, test = fx.split_grouped(rows, F.col("row_id"))
    return measures.dataset_summary(train, test).withColumn("positive_share", F.round("positive_share", 8))


add("dataset_summary", _summary, f"SELECT CASE WHEN {portable_sql('split', 'row_id')} % 5 = 0 THEN 'test' ELSE 'train' END AS part, count(*) AS rows, 1 AS features, round(avg(label), 8) AS positive_share FROM {_LABELLED} GROUP BY 1")

# -- blocks ------------------------------------------------------------------------------------------------

add("assign_blocks", lambda s, d: blocks.assign_blocks(labelled(s, d), 8).select("row_id", "block"), f"SELECT row_id, ({portable_sql('block-42', 'row_id')} % 8)::INT AS block FROM {_LABELLED}")
add("assign_blocks_stratified", lambda s, d: blocks.assign_blocks(labelled(s, d), 8, stratify="label").select("row_id", "block"), f"SELECT row_id, ((row_number() OVER (PARTITION BY label ORDER BY {portable_sql('block-42', 'row_id')}, row_id) - 1) % 8)::INT AS block FROM {_LABELLED}")
add("assign_blocks_sorted", lambda s, d: blocks.assign_blocks(labelled(s, d), 8, mode="sorted", by="label").select("row_id", "block"), f"SELECT row_id, (ntile(8) OVER (ORDER BY label, row_id) - 1)::INT AS block FROM {_LABELLED}")
add("block_balance", lambda s, d: blocks.block_balance(blocks.assign_blocks(labelled(s, d), 8)), f"""
WITH b AS (SELECT ({portable_sql('block-42', 'row_id')} % 8)::INT AS block, label FROM {_LABELLED}), c AS (SELECT block, label, count(*) AS n FROM b GROUP BY 1, 2),
f AS (SELECT *, sum(n) OVER (PARTITION BY block)::DOUBLE AS size, sum(n) OVER (PARTITION BY label)::DOUBLE AS cls, sum(n) OVER ()::DOUBLE AS total FROM c)
SELECT block, max(size)::BIGINT AS rows, round(max(abs(n / size - cls / total)), 8) AS max_deviation, round(sum((n - size * cls / total) * (n - size * cls / total) / (size * cls / total)), 6) AS chi_square FROM f GROUP BY block""")
add("replicate_keys", lambda s, d: committee.replicate(labelled(s, d).select("row_id"), 4).groupBy("ens_part").agg(F.count(F.lit(1)).alias("n")), f"SELECT p::INT AS ens_part, count(*) AS n FROM {_LABELLED}, range(4) t(p) GROUP BY 1")

# -- votes by hash -------------------------------------------------------------------------------------------

_VOTES = f"(SELECT doc_id AS row_id, t::INT AS tree_id, (({portable_sql('v', 'concat(t::VARCHAR, chr(58), doc_id::VARCHAR)')}) < {portable_sql('p', 'doc_id')})::INT AS vote FROM documents, range({M}) r(t))"
_PLACE = f"(({portable_sql('permute', 'tree_id')} % 1000003) * 64 + tree_id)"


def hash_votes(s, d, m: int = M) -> DataFrame:
    """Votes of m members on the ids of documents: a member says 1 if its hash is below the document's share."""
    docs = load(s, d, "documents").select(F.col("doc_id").alias("row_id"), F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("tree_id"))
    return docs.select("row_id", "tree_id", (portable_hash("v", F.concat_ws(":", F.col("tree_id").cast("string"), F.col("row_id").cast("string"))) < portable_hash("p", F.col("row_id"))).cast("int").alias("vote"))


def truth(s, d) -> DataFrame:
    return load(s, d, "documents").select(F.col("doc_id").alias("row_id"), (portable_hash("p", F.col("doc_id")) >= 2**31).cast("int").alias("label"))


_TRUTH = f"(SELECT doc_id AS row_id, ({portable_sql('p', 'doc_id')} >= 2147483648)::INT AS label FROM documents)"


def ordered(s, d) -> DataFrame:
    """Votes with positions: every row starts at its own place on the ring of members."""
    return scoring.offset_order(hash_votes(s, d), M, portable_hash("offset", F.col("row_id")), F.col("tree_id").cast("long"))


_ORDERED = f"(SELECT row_id, tree_id, vote, (((tree_id - {portable_sql('offset', 'row_id')}) % {M}) + {M}) % {M} + 1 AS pos FROM {_VOTES})"


def _lazy_sql(rule: Rule) -> str:
    """First position at which the leader has enough votes, or the last one."""
    return f"""SELECT row_id, CASE WHEN ones > pos - ones THEN 1 ELSE 0 END AS prediction, pos::INT AS votes_used, stop AS stopped_early FROM (
  SELECT *, row_number() OVER (PARTITION BY row_id ORDER BY (NOT stop)::INT, CASE WHEN stop THEN pos ELSE -pos END) AS rn FROM (
    SELECT r.row_id, r.pos, r.ones, coalesce(greatest(r.ones, r.pos - r.ones) >= t.min_lead, false) AND r.pos < {rule.m} AS stop
    FROM (SELECT row_id, pos, sum(vote) OVER (PARTITION BY row_id ORDER BY pos)::BIGINT AS ones FROM {_ORDERED}) r
    LEFT JOIN ({thresholds_sql(rule)}) t ON r.pos = t.n)) WHERE rn = 1"""


def met(s, d, m: int) -> DataFrame:
    """``n, met``: the numbers of votes from 1 to m that events stand for (by their ids), and how many events have each."""
    return load(s, d, "events").groupBy((F.pmod("event_id", F.lit(m)) + 1).cast("int").alias("n")).agg(F.count(F.lit(1)).alias("met"))


def _met_sql(m: int) -> str:
    return f"(SELECT (event_id % {m} + 1)::INT AS n, count(*) AS met FROM events GROUP BY 1)"


_LAZY_RULES = {name: Rule(name, M, ALPHA) for name in ("g1_fpc", "g1", "g2_fpc", "g2", "chebyshev", "chernoff", "certain", "full", "bayes")}
for _name, _rule in _LAZY_RULES.items():
    add(f"lazy_{_name}", lambda s, d, r=_rule: scoring.lazy_from_votes(ordered(s, d), r), _lazy_sql(_rule))
for _name, _m, _alpha in (("g1_fpc", 1000, 0.01), ("g1", 1000, 0.01), ("g2_fpc", 1000, 1e-3), ("g2", 1000, 1e-4), ("chebyshev", 500, 0.01), ("chernoff", 500, 0.01), ("certain", 101, 0.01), ("bayes", 50, 0.01)):
    add(f"thresholds_{_name}", lambda s, d, r=Rule(_name, _m, _alpha): met(s, d, r.m).select("n", lead_column(r, F.col("n")).alias("min_lead"), "met"), f"SELECT n, min_lead, met FROM ({thresholds_sql(Rule(_name, _m, _alpha))}) t JOIN {_met_sql(_m)} e USING (n)")
_LEVELS = (0.05, 0.01, 0.005, 0.001, 0.0001)
add("thresholds_stored", lambda s, d: stored_thresholds(s, Rule("g1_fpc", 300, 0.001), shared_path(s, "thresholds")), thresholds_sql(Rule("g1_fpc", 300, 0.001)))
add("min_votes_table", lambda s, d: met(s, d, 5).join(s.createDataFrame([(i, a, Rule("g1_fpc", 1000, a).least) for i, a in enumerate(_LEVELS, 1)], "n int, alpha double, votes int"), "n").select("alpha", "votes", "met"), f"SELECT a::DOUBLE AS alpha, v::INT AS votes, met FROM (VALUES (1, 0.05, 15), (2, 0.01, 15), (3, 0.005, 30), (4, 0.001, 30), (5, 0.0001, 45)) t(n, a, v) JOIN {_met_sql(5)} e USING (n)")
add("fpc_table", lambda s, d: met(s, d, 200).select("n", F.round(correction_column(F.col("n"), 200), 10).alias("factor"), "met"), f"SELECT n, round(CASE WHEN n > 10 THEN sqrt((200.0::DOUBLE - n) / 199.0::DOUBLE) ELSE 1.0::DOUBLE END, 10) AS factor, met FROM {_met_sql(200)} e")
add("vote_tally", lambda s, d: scoring.tally_votes(hash_votes(s, d)), f"SELECT row_id, vote, count(*) AS n FROM {_VOTES} GROUP BY 1, 2")
_MAJORITY = f"(SELECT row_id, CASE WHEN 2 * sum(vote) > count(*) THEN 1 ELSE 0 END AS prediction, count(*)::INT AS votes_used FROM {_VOTES} GROUP BY row_id)"


def full_votes(s, d) -> DataFrame:
    return scoring.majority(scoring.tally_votes(hash_votes(s, d)))


add("majority", full_votes, f"SELECT row_id, prediction FROM {_MAJORITY}")
add("lazy_offset_order", lambda s, d: ordered(s, d).select("row_id", "tree_id", F.col("pos")), f"SELECT row_id, tree_id, pos FROM {_ORDERED}")
_THREE = f"(SELECT row_id, pos, CASE WHEN {portable_sql('c3', 'concat(tree_id::VARCHAR, chr(58), row_id::VARCHAR)')} % 3 = 0 THEN 2 ELSE vote END AS vote FROM {_ORDERED})"


def _multi(s, d):
    third = portable_hash("c3", F.concat_ws(":", F.col("tree_id").cast("string"), F.col("row_id").cast("string"))) % 3 == 0
    votes = ordered(s, d).withColumn("vote", F.when(third, 2).otherwise(F.col("vote")))
    return scoring.lazy_from_votes(votes, Rule("g1_fpc", M, ALPHA), 3)


_Z2 = Rule("g1_fpc", M, ALPHA).square()
add("lazy_multiclass", _multi, f"""
WITH r AS (SELECT row_id, pos, sum((vote = 0)::INT) OVER w AS a, sum((vote = 1)::INT) OVER w AS b, sum((vote = 2)::INT) OVER w AS c FROM {_THREE} WINDOW w AS (PARTITION BY row_id ORDER BY pos)),
q AS (SELECT row_id, pos, greatest(a, b, c) AS top, a + b + c - greatest(a, b, c) - least(a, b, c) AS second, CASE WHEN a >= b AND a >= c THEN 0 WHEN b >= c THEN 1 ELSE 2 END AS leader FROM r),
k AS (SELECT *, {_Z2!r}::DOUBLE * (CASE WHEN pos > {0.05 * M} THEN ({M}.0::DOUBLE - pos) / {M - 1}.0 ELSE 1.0 END) / (top + second)::DOUBLE AS cc FROM q),
t AS (SELECT *, pos >= 15 AND pos < {M} AND top >= floor((top + second)::DOUBLE * (0.5::DOUBLE + 0.5::DOUBLE * sqrt(cc / (1.0 + cc)))) + 1 AS stop FROM k)
SELECT row_id, leader AS prediction, pos::INT AS votes_used, stop AS stopped_early FROM (SELECT *, row_number() OVER (PARTITION BY row_id ORDER BY (NOT stop)::INT, CASE WHEN stop THEN pos ELSE -pos END) AS rn FROM t) WHERE rn = 1""")

# -- measures over votes ---------------------------------------------------------------------------------------

_LAZY = f"({_lazy_sql(_LAZY_RULES['g1_fpc'])})"


def lazy(s, d):
    return scoring.lazy_from_votes(ordered(s, d), _LAZY_RULES["g1_fpc"])


add("accuracy", lambda s, d: measures.accuracy(full_votes(s, d), truth(s, d)).select(F.round("accuracy", 8).alias("accuracy")), f"SELECT round(avg((prediction = label)::INT), 8) AS accuracy FROM {_MAJORITY} JOIN {_TRUTH} USING (row_id)")
add("eval_fraction", lambda s, d: measures.eval_fraction(lazy(s, d), M).select(F.round("eval_fraction", 8).alias("eval_fraction"), F.round("savings", 8).alias("savings")), f"SELECT round(avg(votes_used) / {M}, 8) AS eval_fraction, round({M} / avg(votes_used), 8) AS savings FROM {_LAZY}")
add("relative_error", lambda s, d: measures.relative_error(lazy(s, d), full_votes(s, d), truth(s, d)).select(F.round("relative_error", 8).alias("relative_error")), f"SELECT round(1 - avg((l.prediction = label)::INT) / avg((f.prediction = label)::INT), 8) AS relative_error FROM {_LAZY} l JOIN {_MAJORITY} f USING (row_id) JOIN {_TRUTH} t USING (row_id)")
add("disagreement", lambda s, d: measures.disagreement(lazy(s, d), full_votes(s, d)).select(F.round("disagreement", 8).alias("disagreement")), f"SELECT round(avg((l.prediction <> f.prediction)::INT), 8) AS disagreement FROM {_LAZY} l JOIN {_MAJORITY} f USING (row_id)")
add("stop_histogram", lambda s, d: measures.stop_histogram(lazy(s, d)), f"SELECT bin, (2 ** bin)::BIGINT AS low, count(*) AS n FROM (SELECT floor(log2(votes_used) + 1e-12)::INT AS bin FROM {_LAZY}) GROUP BY bin")
add("share_within", lambda s, d: measures.share_within(lazy(s, d), 32, M).select(F.round("share_within", 8).alias("share_within"), F.round("share_all", 8).alias("share_all")), f"SELECT round(avg((votes_used <= 32)::INT), 8) AS share_within, round(avg((votes_used >= {M})::INT), 8) AS share_all FROM {_LAZY}")
add("confusion", lambda s, d: measures.confusion(lazy(s, d), truth(s, d), [0, 1]).withColumn("recall", F.round("recall", 8)), f'SELECT label, count(*) FILTER (WHERE prediction = 0) AS "0", count(*) FILTER (WHERE prediction = 1) AS "1", round(avg((prediction = label)::INT), 8) AS recall FROM {_LAZY} JOIN {_TRUTH} USING (row_id) GROUP BY label')

# -- simulated members ------------------------------------------------------------------------------------------


def _simulated(s, d) -> DataFrame:
    """32 simulated members on the ids of documents: the full vote, the true class, and the first 15 votes for class 1."""
    votes = load(s, d, "documents").select(F.col("doc_id").alias("row_id"), F.explode(F.sequence(F.lit(1), F.lit(32))).alias("tree_id"))
    share = portable_hash("sp", F.col("row_id"))
    votes = votes.select("row_id", "tree_id", (portable_hash("sv", F.concat_ws(":", F.col("tree_id").cast("string"), F.col("row_id").cast("string"))) < share).cast("int").alias("vote"))
    first = scoring.tally_votes(votes.where("tree_id <= 15")).where("vote = 1").select("row_id", F.col("n").alias("first15"))
    full = scoring.majority(scoring.tally_votes(votes)).withColumnRenamed("prediction", "full_class")
    return full.join(first, "row_id", "left").select("row_id", "full_class", (share >= 2**31).cast("int").alias("label"), F.coalesce("first15", F.lit(0)).alias("first15"))


add("simulate_small", _simulated, duck("""
WITH x AS (SELECT doc_id AS id, {r[1;32]} AS i FROM documents),
v AS (SELECT id, i, ({h[sv|concat(i, ':', id)]} < {h[sp|id]})::INT AS one FROM x)
SELECT id AS row_id, (2 * sum(one) > 32)::INT AS full_class, ({h[sp|id]} >= 2147483648)::INT AS label, sum(CASE WHEN i <= 15 THEN one ELSE 0 END)::BIGINT AS first15 FROM v GROUP BY id"""))

# -- bites and out-of-bag votes: the samplers of training on whole blocks, with draws that SQL can repeat --------------------

_SAMPLED = "kind string, block int, i int, row_id bigint, a double, b double"


def _sample_block(table: pa.Table) -> pa.Table:
    """Five uniform bites of a block, the out-of-bag votes of five made-up trees, the pools, and a steered bite of either kind."""
    table = table.sort_by("row_id").combine_chunks()
    ids, y, block = table["row_id"].to_numpy(), table["label"].to_numpy(), table["block"][0].as_py()
    everything, votes, rows = np.arange(len(ids)), np.zeros((len(ids), 2), np.int64), []
    put = lambda kind, i, where, a, b: rows.append((kind, i, where, a, b))
    for i in range(5):
        bite, _ = sampling.draw_bite(everything, everything[:0], 20, PortableRng(42, block, i))
        sampling.update_oob(votes, table[f"said{i}"].to_numpy(), bite)
        which, copies = np.unique(bite, return_counts=True)
        put("uniform", i, ids[which], copies, copies)
    right, wrong = sampling.split_pools(votes, y)
    error = sampling.oob_error(votes, y)
    voted = votes.sum(axis=1) > 0
    put("votes", 0, ids[voted], votes[voted, 0], votes[voted, 1])
    put("split", 0, ids, np.isin(everything, right), np.isin(everything, wrong))
    put("error", 0, np.zeros(1, int), np.array([error]), np.array([sampling.accept_probability(error)]))
    bite, _ = sampling.draw_bite(right, wrong, 20, PortableRng(42, block, "importance"))
    put("importance", 0, ids[bite], np.arange(20) < 10, np.isin(bite, wrong))
    is_wrong = np.isin(everything, wrong)
    bite, _ = sampling.draw_bite_rejection(is_wrong, error, 20, PortableRng(42, block, "rejection"))
    put("rejection", 0, ids[bite], is_wrong[bite], is_wrong[bite])
    flat = lambda k: np.concatenate([np.asarray(r[k], float if k > 2 else np.int64) for r in rows])
    n = [len(r[2]) for r in rows]
    return pa.table({"kind": np.repeat([r[0] for r in rows], n).tolist(), "block": pa.array([block] * sum(n), pa.int32()), "i": pa.array(np.repeat([r[1] for r in rows], n), pa.int32()), "row_id": flat(2), "a": flat(3), "b": flat(4)})


def sampled(s, d, kind: str) -> DataFrame:
    said = lambda i: F.when(portable_hash("stub", F.concat_ws(":", F.lit(str(i)), F.col("row_id").cast("string"))) % 10 < 7, F.col("label")).otherwise(1 - F.col("label")).alias(f"said{i}")
    rows = blocks.assign_blocks(labelled(s, d), 4).select("row_id", "label", "block", *[said(i) for i in range(5)])
    return rows.groupBy("block").applyInArrow(_sample_block, _SAMPLED).where(F.col("kind") == kind).drop("kind")


_POOLS = """
WITH b AS (SELECT doc_id AS row_id, (lang = 'en')::INT AS label, ({h[block-42|doc_id]} % 4)::INT AS block FROM documents),
ranked AS (SELECT block, row_id, row_number() OVER (PARTITION BY block ORDER BY row_id) - 1 AS rk, count(*) OVER (PARTITION BY block) AS size FROM b),
trees AS (SELECT DISTINCT block, i FROM b, range(5) t(i)),
drawn AS (SELECT block, i, row_id, count(*) AS copies FROM (SELECT block, i, s, {h[choice-42|concat(block, ':', i, ':', s)]} AS draw FROM trees, range(20) t(s)) JOIN ranked USING (block) WHERE rk = draw % size GROUP BY 1, 2, 3),
votes AS (SELECT b.block, i, b.row_id, b.label, CASE WHEN {h[stub|concat(i, ':', b.row_id)]} % 10 < 7 THEN b.label ELSE 1 - b.label END AS vote FROM b JOIN trees USING (block)),
tally AS (SELECT v.block, v.row_id, v.label, sum(1 - vote) AS v0, sum(vote) AS v1 FROM votes v LEFT JOIN drawn d ON v.block = d.block AND v.i = d.i AND v.row_id = d.row_id WHERE d.row_id IS NULL GROUP BY 1, 2, 3),
split AS (SELECT b.block, b.row_id, b.label, v0 IS NULL OR (v1 > v0)::INT = b.label AS is_right, v0 IS NULL OR (v1 > v0)::INT <> b.label AS is_wrong FROM b LEFT JOIN tally USING (block, row_id)),
err AS (SELECT block, avg(((v1 > v0)::INT <> label)::INT) AS e FROM tally GROUP BY block)
"""
_STEERED = _POOLS + """, pools AS (SELECT block, row_id, is_wrong, 1 AS pool, row_number() OVER (PARTITION BY block ORDER BY row_id) - 1 AS rk, count(*) OVER (PARTITION BY block) AS size FROM split WHERE is_wrong
UNION ALL SELECT block, row_id, is_wrong, 0, row_number() OVER (PARTITION BY block ORDER BY row_id) - 1, count(*) OVER (PARTITION BY block) FROM split WHERE is_right),
chosen AS (SELECT p.block, s, p.pool, p.row_id, p.is_wrong FROM (SELECT DISTINCT block FROM b) q, range(20) t(s) JOIN pools p ON p.block = q.block AND p.pool = (s < 10)::INT AND p.rk = {h[choice-42|concat(q.block, ':importance:', s)]} % p.size)
"""
add("bite_uniform", lambda s, d: sampled(s, d, "uniform").select("block", "i", "row_id", F.col("a").cast("long").alias("copies")), duck(_POOLS + "SELECT block, i::INT AS i, row_id, copies FROM drawn"))
add("oob_votes", lambda s, d: sampled(s, d, "votes").select("block", "row_id", F.col("a").cast("long").alias("v0"), F.col("b").cast("long").alias("v1")), duck(_POOLS + "SELECT block, row_id, v0::BIGINT AS v0, v1::BIGINT AS v1 FROM tally"))
add("oob_split", lambda s, d: sampled(s, d, "split").select("block", "row_id", (F.col("a") == 1).alias("is_right"), (F.col("b") == 1).alias("is_wrong")), duck(_POOLS + "SELECT block, row_id, is_right, is_wrong FROM split"))
add("oob_error", lambda s, d: sampled(s, d, "error").select("block", F.round("a", 8).alias("error")), duck(_POOLS + "SELECT block, round(e, 8) AS error FROM err"))
add("accept_probability", lambda s, d: sampled(s, d, "error").select("block", F.round("b", 8).alias("p")), duck(_POOLS + "SELECT block, round(CASE WHEN e >= 0.5 THEN 1 ELSE e / (1 - e) END, 8) AS p FROM err"))
add("bite_importance", lambda s, d: sampled(s, d, "importance").groupBy("block", F.col("a").cast("int").alias("pool"), "row_id").agg(F.count(F.lit(1)).alias("copies")), duck(_STEERED + "SELECT block, pool, row_id, count(*) AS copies FROM chosen GROUP BY 1, 2, 3"))
add("bite_composition", lambda s, d: sampled(s, d, "importance").groupBy("block").agg(F.round(F.avg("b"), 8).alias("wrong_share")), duck(_STEERED + "SELECT block, round(avg(is_wrong::INT), 8) AS wrong_share FROM chosen GROUP BY block"))
add("bite_rejection", lambda s, d: sampled(s, d, "rejection").groupBy("block", "row_id").agg(F.count(F.lit(1)).alias("copies")), duck(_POOLS + """, odds AS (SELECT block, CASE WHEN e >= 0.5 THEN 1 ELSE e / (1 - e) END AS p FROM err),
shots AS (SELECT block, p, s, {h[integers-42|concat(block, ':rejection:', s)]} AS draw, {h[random-42|concat(block, ':rejection:', s)]} / 4294967296.0::DOUBLE AS u FROM odds, range(400) t(s)),
taken AS (SELECT block, split.row_id, row_number() OVER (PARTITION BY block ORDER BY s) AS nth FROM shots JOIN ranked USING (block) JOIN split USING (block, row_id) WHERE rk = draw % size AND (is_wrong OR u < p))
SELECT block, row_id, count(*) AS copies FROM taken WHERE nth <= 20 GROUP BY 1, 2"""))

# -- splits and trees: shares of five letters in whole texts ------------------------------------------------------------

LETTERS = "ehntu"


def letter_features(docs: DataFrame) -> DataFrame:
    """``row_id, features, label``: shares of five letters, rounded; a null or empty text has share 0.

    Three of ten labels are flipped, by hash, so that members differ. Shares are rounded as DuckDB does it, to the nearest
    millionth of the double; Spark's six digits come from its decimal form, and 41 / 640 would go up here and down there.
    """
    n = F.char_length("text")
    share = lambda c: F.when(n > 0, F.round((n - F.char_length(F.replace(F.col("text"), F.lit(c), F.lit("")))) / n * 1e6) / 1e6).otherwise(F.lit(0.0))
    return docs.select(F.col("doc_id").alias("row_id"), F.array(*[share(c) for c in LETTERS]).alias("features"), F.when(portable_hash("flip", F.col("doc_id")) % 10 < 3, F.col("lang") != "en").otherwise(F.col("lang") == "en").cast("int").alias("label"))


def letter_rows(s, d) -> DataFrame:
    """The same of the documents, with ``block``."""
    return blocks.assign_blocks(letter_features(load(s, d, "documents")), 4)


def letter_name(feature: str = "feature"):
    return F.element_at(F.array(*[F.lit(c) for c in LETTERS]), F.col(feature) + 1)


_LONG = "WITH x AS (" + " UNION ALL ".join(f"SELECT doc_id AS row_id, ({{h[block-42|doc_id]}} % 4)::INT AS block, ((lang = 'en') <> ({{h[flip|doc_id]}} % 10 < 3))::INT AS label, '{c}' AS feature, {k} AS f, CASE WHEN length(text) > 0 THEN round((length(text) - length(replace(text, '{c}', '')))::DOUBLE / length(text), 6) ELSE 0::DOUBLE END AS value FROM documents" for k, c in enumerate(LETTERS)) + ")"


def _ent(a: str, b: str) -> str:
    part = lambda q: f"(CASE WHEN {q} > 0 THEN -({q}::DOUBLE / ({a} + {b})) * log2({q}::DOUBLE / ({a} + {b})) ELSE 0 END)"
    return f"({part(a)} + {part(b)})"


_GAIN = f"round({_ent('tp', '(tn - tp)')} - (n_low * {_ent('lp', '(n_low - lp)')} + (tn - n_low) * {_ent('(tp - lp)', '(tn - n_low - tp + lp)')}) / tn, 10)"


def _splits(group: str) -> str:
    """Best cut of every group: cumulative class counts by value, gain at each change of value."""
    key = f"{group}, " if group else ""
    part = f"PARTITION BY {key}f"
    return duck(_LONG + f""", c AS (SELECT {key}f, feature, value, sum(label) AS p, count(*) AS n FROM x GROUP BY {key}f, feature, value),
r AS (SELECT {key}f, feature, value, lead(value) OVER w AS nxt, sum(p) OVER w AS lp, sum(n) OVER w AS n_low, sum(p) OVER ({part}) AS tp, sum(n) OVER ({part}) AS tn FROM c WINDOW w AS ({part} ORDER BY value)),
g AS (SELECT {key}f, feature, (value + nxt) / 2 AS threshold, {_GAIN} AS gain FROM r WHERE nxt IS NOT NULL)
SELECT {key}feature, round(threshold, 8) AS threshold, gain FROM (SELECT *, row_number() OVER ({f'PARTITION BY {group} ' if group else ''}ORDER BY gain DESC, f, threshold) AS rn FROM g) t WHERE rn = 1""")


def _split_of_block(table: pa.Table) -> pa.Table:
    x, y = matrix(table["features"].combine_chunks()), table["label"].to_numpy().astype(np.int64)
    column, threshold, gain = tree.best_split(x, y, 2)
    return pa.table({"block": table["block"][:1].cast(pa.int32()), "feature": pa.array([column], pa.int32()), "threshold": [threshold], "gain": [gain]})


def _cut_columns() -> list:
    return [letter_name().alias("feature"), F.round("threshold", 8).alias("threshold"), F.round("gain", 10).alias("gain")]


add("best_split_root", lambda s, d: splits.best_splits(letter_rows(s, d)).select(*_cut_columns()), _splits(""))
add("best_split_by_block", lambda s, d: splits.best_splits(letter_rows(s, d), group=("block",)).select("block", *_cut_columns()), _splits("block"))
add("best_split_per_block", lambda s, d: letter_rows(s, d).groupBy("block").applyInArrow(_split_of_block, "block int, feature int, threshold double, gain double").select("block", *_cut_columns()), _splits("block"))


def _entropy_by_feature(s, d) -> DataFrame:
    long = letter_rows(s, d).select("label", F.posexplode("features").alias("feature", "value"))
    counts = long.groupBy("feature").agg(*splits.class_counts(2), F.round(F.avg("value"), 8).alias("mean"))
    return counts.select(letter_name().alias("feature"), F.round(splits.entropy_column([F.col("n0"), F.col("n1")]), 8).alias("entropy"), "mean")


add("entropy_by_feature", _entropy_by_feature, duck(_LONG + f" SELECT feature, round({_ent('sum(label)', '(count(*) - sum(label))')}, 8) AS entropy, round(avg(value), 8) AS mean FROM x GROUP BY feature"))
_NODES = "nodes(tree_id, node, feature, threshold, lft, rgt, cls) AS (VALUES (0, 0, -1, 0.0E0, -1, -1, 1), (1, 0, 0, 0.12E0, 1, 2, 0), (1, 1, -1, 0.0E0, -1, -1, 0), (1, 2, -1, 0.0E0, -1, -1, 1), (2, 0, 1, 0.03E0, 1, 2, 0), (2, 1, 0, 0.10E0, 3, 4, 0), (2, 2, -1, 0.0E0, -1, -1, 1), (2, 3, -1, 0.0E0, -1, -1, 0), (2, 4, 2, 0.08E0, 5, 6, 0), (2, 5, -1, 0.0E0, -1, -1, 1), (2, 6, -1, 0.0E0, -1, -1, 0))"


def hand_written(s) -> MegaForest:
    """The three trees of ``_NODES`` as a forest: a leaf, a stump, one of depth 3."""
    trees = [(0, [-1], [0.0], [-1], [-1], [1], 0), (1, [0, -1, -1], [0.12, 0.0, 0.0], [1, -1, -1], [2, -1, -1], [0, 0, 1], 1), (2, [1, 0, -1, -1, 2, -1, -1], [0.03, 0.10, 0.0, 0.0, 0.08, 0.0, 0.0], [1, 3, -1, -1, 5, -1, -1], [2, 4, -1, -1, 6, -1, -1], [0, 0, 1, 0, 0, 1, 0], 3)]
    rows = [(0, i, 0, i, 0, f, t, a, b, c, [], 0, depth, len(f), None, False, 0) for i, f, t, a, b, c, depth in trees]
    return MegaForest(s.createDataFrame(rows, TREE), ForestParams(n_trees=3, n_blocks=1, n_parts=1))


_WIDE = "f AS (SELECT doc_id AS row_id, " + ", ".join(f"CASE WHEN length(text) > 0 THEN round((length(text) - length(replace(text, '{c}', '')))::DOUBLE / length(text), 6) ELSE 0::DOUBLE END AS x{i}" for i, c in enumerate(LETTERS)) + " FROM documents)"
_WALK = "CASE n.feature " + " ".join(f"WHEN {i} THEN x{i}" for i in range(len(LETTERS))) + " END"
add("predict_nodes", lambda s, d: scoring.votes_by_tree(hand_written(s), letter_rows(s, d)), f"WITH RECURSIVE {_NODES}, {_WIDE}, walk(row_id, tree_id, node) AS (SELECT row_id, tree_id, 0 FROM f, (SELECT DISTINCT tree_id FROM nodes) t UNION ALL SELECT w.row_id, w.tree_id, CASE WHEN {_WALK} <= n.threshold THEN n.lft ELSE n.rgt END FROM walk w JOIN nodes n ON w.tree_id = n.tree_id AND w.node = n.node JOIN f ON w.row_id = f.row_id WHERE n.feature >= 0) SELECT w.row_id, w.tree_id::BIGINT AS tree_id, n.cls AS vote FROM walk w JOIN nodes n ON w.tree_id = n.tree_id AND w.node = n.node WHERE n.feature < 0")
add("tree_nodes_table", lambda s, d: hand_written(s).nodes().select("tree_id", "node", "feature", "threshold", F.col("left").alias("lft"), F.col("right").alias("rgt"), F.col("leaf_class").alias("cls")), f"WITH {_NODES} SELECT tree_id::BIGINT AS tree_id, node, feature, threshold::DOUBLE AS threshold, lft, rgt, cls FROM nodes")

# -- whole forests of stumps: blocks, bites, exact splits, votes, committees; training as it is, with portable draws ---------------

STUMPS = ForestParams(n_trees=5, bite_size=60, n_blocks=4, n_parts=4, sampler="bagging", learner="stump", draws="portable")
STEERED = ForestParams(n_trees=3, bite_size=20, n_blocks=4, n_parts=4, sampler="importance", learner="stump", draws="portable", n_attr=5)


def stump_sets(s, d) -> tuple[DataFrame, DataFrame]:
    return fx.split_grouped(letter_rows(s, d), F.col("row_id"))


def stump_forest(s, d, params: ForestParams = STUMPS) -> tuple[MegaForest, DataFrame]:
    """(forest, test rows)."""
    train, test = stump_sets(s, d)
    return train_mega_forest(train, params), test


def _stump_rows(forest: MegaForest) -> DataFrame:
    leaf = lambda side: F.element_at("leaf_class", F.element_at(side, 1) + 1)
    root = forest.trees.withColumn("f", F.element_at("feature", 1))
    return root.select("block", "iter", letter_name("f").alias("feature"), F.round(F.element_at("threshold", 1), 8).alias("threshold"), leaf("left").alias("lcls"), leaf("right").alias("rcls"))


_STUMPS = _LONG + f""", train AS (SELECT * FROM x WHERE {{h[split|row_id]}} % 5 <> 0), test AS (SELECT * FROM x WHERE {{h[split|row_id]}} % 5 = 0),
ranked AS (SELECT block, row_id, row_number() OVER (PARTITION BY block ORDER BY row_id) - 1 AS rk, count(*) OVER (PARTITION BY block) AS size FROM (SELECT DISTINCT block, row_id FROM train)),
trees AS (SELECT DISTINCT block, i FROM ranked, range(5) t(i)),
slots AS (SELECT block, i, s, {{h[choice-42|concat(block, ':', i, ':', s)]}} AS draw FROM trees, range(60) t(s)),
bite AS (SELECT block, i, row_id FROM slots JOIN ranked USING (block) WHERE rk = draw % size),
tried AS (SELECT block, i, f FROM (SELECT block, i, f, row_number() OVER (PARTITION BY block, i ORDER BY {{h[permutation-42|concat(block, ':', i, ':', f)]}}, f) AS rn FROM trees, range(5) t(f)) WHERE rn <= 3),
c AS (SELECT bite.block, bite.i, train.f, train.feature, value, sum(label) AS p, count(*) AS n FROM bite JOIN train ON bite.row_id = train.row_id JOIN tried ON tried.block = bite.block AND tried.i = bite.i AND tried.f = train.f GROUP BY ALL),
r AS (SELECT block, i, f, feature, value, lead(value) OVER w AS nxt, sum(p) OVER w AS lp, sum(n) OVER w AS n_low, sum(p) OVER t AS tp, sum(n) OVER t AS tn FROM c WINDOW w AS (PARTITION BY block, i, f ORDER BY value), t AS (PARTITION BY block, i, f)),
g AS (SELECT *, (value + nxt) / 2 AS threshold, {_GAIN} AS gain FROM r WHERE nxt IS NOT NULL),
stump AS (SELECT block, i, f, feature, threshold, (2 * lp > n_low)::INT AS lcls, (2 * (tp - lp) > tn - n_low)::INT AS rcls FROM (SELECT *, row_number() OVER (PARTITION BY block, i ORDER BY gain DESC, f, threshold) AS rn FROM g) WHERE rn = 1),
vote AS (SELECT test.row_id, test.label, stump.block * 1000000 + stump.i AS tree_id, {{h[part-42|concat(stump.block, ':', stump.i)]}} % 4 AS part, CASE WHEN value <= threshold THEN lcls ELSE rcls END AS vote FROM test JOIN stump ON test.f = stump.f),
full_vote AS (SELECT row_id, label, sum(vote) AS ones, count(*) AS m, (2 * sum(vote) > count(*))::INT AS prediction FROM vote GROUP BY 1, 2)
"""
add("stump_forest_trees", lambda s, d: _stump_rows(stump_forest(s, d)[0]), duck(_STUMPS + 'SELECT block, i::INT AS "iter", feature, round(threshold, 8) AS threshold, lcls, rcls FROM stump'))
add("model_size_nodes", lambda s, d: stump_forest(s, d)[0].size().withColumn("mean_nodes", F.round("mean_nodes", 8)), duck(_STUMPS + ", nodes AS (SELECT block, i, unnest([0, 1, 1]) AS depth FROM stump) SELECT count(DISTINCT (block, i)) AS trees, count(*) AS nodes, (count(*) * 32)::BIGINT AS bytes, round(count(*)::DOUBLE / count(DISTINCT (block, i)), 8) AS mean_nodes, max(depth) AS max_depth FROM nodes"))
add("stump_forest_bagging", lambda s, d: scoring.predict_full(*stump_forest(s, d)).select("row_id", "prediction", "votes_used", F.round("leader_share", 8).alias("leader_share")), duck(_STUMPS + "SELECT row_id, prediction, m::INT AS votes_used, round(greatest(ones, m - ones)::DOUBLE / m, 8) AS leader_share FROM full_vote"))


def _stump_lazy(s, d) -> DataFrame:
    return scoring.predict_lazy(*stump_forest(s, d), rule="certain", portable=True).select("row_id", "prediction", "votes_used", "stopped_early")


#: From the votes of all members: those of a ring from a row's own place on, until more than half of 20 agree.
STUMP_LAZY_SQL = duck(_STUMPS + """, place AS (SELECT tree_id, row_number() OVER (ORDER BY {h[permute|tree_id]}, tree_id) - 1 AS nth FROM (SELECT DISTINCT tree_id FROM vote)),
ring AS (SELECT row_id, vote, (nth - {h[offset-7|row_id]} % 20 + 20) % 20 + 1 AS pos FROM vote JOIN place USING (tree_id)),
run AS (SELECT row_id, pos, sum(vote) OVER (PARTITION BY row_id ORDER BY pos) AS ones FROM ring),
stops AS (SELECT row_id, min(CASE WHEN pos = 20 OR greatest(ones, pos - ones) > 10 THEN pos END) AS used FROM run GROUP BY row_id)
SELECT row_id, (2 * ones > used)::INT AS prediction, used::INT AS votes_used, used < 20 AS stopped_early FROM stops JOIN run USING (row_id) WHERE pos = used""")
add("stump_forest_lazy", _stump_lazy, STUMP_LAZY_SQL)


def _stump_accuracy(s, d) -> DataFrame:
    forest, test = stump_forest(s, d)
    return measures.accuracy(scoring.predict_full(forest, test), test).select(F.round("accuracy", 8).alias("accuracy"))


add("stump_forest_metrics", _stump_accuracy, duck(_STUMPS + "SELECT round(avg((prediction = label)::INT), 8) AS accuracy FROM full_vote"))
add("stump_forest_grid", lambda s, d: scoring.accuracy_grid(*stump_forest(s, d), [(q, k) for q in (1, 2, 4) for k in (1, 3, 5)]).withColumn("accuracy", F.round("accuracy", 8)), duck(_STUMPS + """, cell AS (SELECT q, k, row_id, label, sum(vote) AS ones, count(*) AS m FROM vote, (VALUES (1), (2), (4)) a(q), (VALUES (1), (3), (5)) b(k) WHERE tree_id // 1000000 < q AND tree_id % 1000000 < k GROUP BY ALL)
SELECT q AS blocks, k AS local_size, max(m)::BIGINT AS trees, round(avg(((2 * ones > m)::INT = label)::INT), 8) AS accuracy FROM cell GROUP BY q, k"""))
add("stump_forest_union", lambda s, d: scoring.predict_full((lambda f, t: f.restrict(2).union(MegaForest(f.trees.where("block >= 2"), f.params)))(*stump_forest(s, d)), stump_sets(s, d)[1]).select("row_id", "prediction", "votes_used"), duck(_STUMPS + "SELECT row_id, prediction, m::INT AS votes_used FROM full_vote"))

# -- committees of the stump forest: one part of four judges, the others are asked for undecided rows --------------------------

_JUDGE = Rule("g1_fpc", 20, 0.01, 3)
_JUDGED = _STUMPS + f""", place AS (SELECT tree_id, part, row_number() OVER (PARTITION BY part ORDER BY {{h[permute|tree_id]}}, tree_id) - 1 AS nth, count(*) OVER (PARTITION BY part) AS size FROM (SELECT DISTINCT tree_id, part FROM vote)),
ring AS (SELECT row_id, vote, (nth - {{h[offset-3|row_id]}} % size + size) % size + 1 AS pos, size FROM vote JOIN place USING (tree_id) WHERE vote.part = {{h[committee-3|row_id]}} % 4),
run AS (SELECT row_id, pos, size, sum(vote) OVER (PARTITION BY row_id ORDER BY pos) AS ones FROM ring),
tested AS (SELECT run.*, coalesce(greatest(ones, pos - ones) >= min_lead, false) AS stop FROM run LEFT JOIN ({thresholds_sql(_JUDGE)}) t ON t.n = pos),
judged AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY row_id ORDER BY stop DESC, CASE WHEN stop THEN pos ELSE -pos END) AS rn FROM tested) WHERE rn = 1)
"""


def _first_pass(s, d) -> tuple[MegaForest, DataFrame]:
    forest, test = stump_forest(s, d)
    return forest, committee.committee_pass(forest, test, "g1_fpc", 0.01, min_votes=3, portable=True)


def _undecided(s, d, ask) -> DataFrame:
    forest, first = _first_pass(s, d)
    return ask(forest, first.where("not stopped_early"))


def _committee(s, d, **options) -> DataFrame:
    return committee.committee_predict(*stump_forest(s, d), "g1_fpc", 0.01, min_votes=3, portable=True, **options).select("row_id", "prediction", "votes_used", "stage")


_UNION = _JUDGED + "SELECT f.row_id, CASE WHEN stop THEN (2 * j.ones > pos)::INT ELSE f.prediction END AS prediction, CASE WHEN stop THEN pos ELSE m END::INT AS votes_used, CASE WHEN stop THEN 'committee' ELSE 'full' END AS stage FROM full_vote f LEFT JOIN judged j USING (row_id)"
COMMITTEE_SQL = duck(_UNION)
add("committee_decided", lambda s, d: _first_pass(s, d)[1].where("stopped_early").select("row_id", "prediction", "votes_used"), duck(_JUDGED + "SELECT row_id, (2 * ones > pos)::INT AS prediction, pos::INT AS votes_used FROM judged WHERE stop"))
add("committee_tallies", lambda s, d: _undecided(s, d, committee.partition_tallies).where("n > 0"), duck(_JUDGED + "SELECT part::INT AS ens_part, row_id, vote, count(*) AS n FROM vote WHERE row_id NOT IN (SELECT row_id FROM judged WHERE stop) GROUP BY ALL"))
add("committee_tallies_broadcast", lambda s, d: _undecided(s, d, committee.tallies_by_broadcast).groupBy("row_id", "vote").agg(F.sum("n").alias("n")).where("n > 0"), duck(_JUDGED + "SELECT row_id, vote, count(*) AS n FROM vote WHERE row_id NOT IN (SELECT row_id FROM judged WHERE stop) GROUP BY ALL"))
add("committee_union", _committee, COMMITTEE_SQL)
add("committee_stats", lambda s, d: committee.committee_stats(_committee(s, d)).select("rows", "undecided", F.round("undecided_rate", 8).alias("undecided_rate"), F.round("mean_votes", 8).alias("mean_votes")), duck(f"SELECT count(*) AS rows, count(*) FILTER (WHERE stage = 'full') AS undecided, round(avg((stage = 'full')::INT), 8) AS undecided_rate, round(avg(votes_used), 8) AS mean_votes FROM ({_UNION})"))

# -- stumps on importance bites: three rounds, each bite drawn from the out-of-bag pools of the stumps before it ---------

_ROUNDS = 3


def _round(k: int) -> str:
    """Bite k (10 draws from either pool, the wrong one first; an empty pool falls back to the other), its stump, the votes after it."""
    pred = "(v1 > v0)::INT"
    return f""",
split{k} AS (SELECT *, v0 + v1 = 0 OR {pred} = label AS is_right, v0 + v1 = 0 OR {pred} <> label AS is_wrong FROM state{k - 1}),
full{k} AS (SELECT *, bool_or(is_right) OVER (PARTITION BY block) AS any_right, bool_or(is_wrong) OVER (PARTITION BY block) AS any_wrong FROM split{k}),
member{k} AS (SELECT *, (pool = 0 AND (is_right OR NOT any_right) OR pool = 1 AND (is_wrong OR NOT any_wrong))::INT AS inside FROM full{k}, range(2) t(pool)),
rank{k} AS (SELECT *, sum(inside) OVER (PARTITION BY block, pool ORDER BY row_id) - 1 AS rk, sum(inside) OVER (PARTITION BY block, pool) AS size FROM member{k}),
slot{k} AS (SELECT block, pool, {{h[choice-42|concat(block, ':{k - 1}:', s + 10 * (1 - pool))]}} AS draw FROM (SELECT DISTINCT block FROM state0), range(2) t(pool), range(10) u(s)),
hits{k} AS (SELECT block, row_id, count(*) AS copies FROM slot{k} JOIN rank{k} USING (block, pool) WHERE inside = 1 AND rk = draw % size GROUP BY 1, 2),
bite{k} AS (SELECT a.block, a.row_id, a.label, a.v0, a.v1, coalesce(copies, 0) AS copies FROM state{k - 1} a LEFT JOIN hits{k} h ON a.block = h.block AND a.row_id = h.row_id),
count{k} AS (SELECT b.block, f, feature, value, sum(copies * b.label) AS p, sum(copies) AS n FROM bite{k} b JOIN train ON b.row_id = train.row_id WHERE copies > 0 GROUP BY ALL),
run{k} AS (SELECT block, f, feature, value, lead(value) OVER w AS nxt, sum(p) OVER w AS lp, sum(n) OVER w AS n_low, sum(p) OVER t AS tp, sum(n) OVER t AS tn FROM count{k} WINDOW w AS (PARTITION BY block, f ORDER BY value), t AS (PARTITION BY block, f)),
gain{k} AS (SELECT *, (value + nxt) / 2 AS threshold, {_GAIN} AS gain FROM run{k} WHERE nxt IS NOT NULL),
stump{k} AS (SELECT block, f, feature, threshold, (2 * lp > n_low)::INT AS lcls, (2 * (tp - lp) > tn - n_low)::INT AS rcls FROM (SELECT *, row_number() OVER (PARTITION BY block ORDER BY gain DESC, f, threshold) AS rn FROM gain{k}) q WHERE rn = 1),
said{k} AS (SELECT b.*, CASE WHEN value <= threshold THEN lcls ELSE rcls END AS vote FROM bite{k} b JOIN stump{k} s ON b.block = s.block JOIN train ON train.row_id = b.row_id AND train.f = s.f),
state{k} AS (SELECT block, row_id, label, v0 + (copies = 0 AND vote = 0)::INT AS v0, v1 + (copies = 0 AND vote = 1)::INT AS v1 FROM said{k})"""


_CHAIN = _LONG + """, train AS (SELECT * FROM x WHERE {h[split|row_id]} % 5 <> 0), test AS (SELECT * FROM x WHERE {h[split|row_id]} % 5 = 0),
state0 AS (SELECT DISTINCT block, row_id, label, 0 AS v0, 0 AS v1 FROM train)""" + "".join(_round(k) for k in range(1, _ROUNDS + 1))
_CHAIN += ", stump AS (" + " UNION ALL ".join(f"SELECT block, {k - 1} AS i, f, feature, threshold, lcls, rcls FROM stump{k}" for k in range(1, _ROUNDS + 1)) + ")"
_ERRORS = " UNION ALL ".join(f'SELECT block, {k - 1} AS "iter", round(avg(((v1 > v0)::INT <> label)::INT), 8) AS oob_error FROM state{k} WHERE v0 + v1 > 0 GROUP BY block' for k in range(1, _ROUNDS + 1))
add("stump_forest_importance", lambda s, d: _stump_rows(stump_forest(s, d, STEERED)[0]), duck(_CHAIN + ' SELECT block, i AS "iter", feature, round(threshold, 8) AS threshold, lcls, rcls FROM stump'))
add("stump_importance_votes", lambda s, d: scoring.predict_full(*stump_forest(s, d, STEERED)).select("row_id", "prediction", "votes_used"), duck(_CHAIN + " SELECT row_id, (2 * sum(vote) > count(*))::INT AS prediction, count(*)::INT AS votes_used FROM (SELECT row_id, CASE WHEN value <= threshold THEN lcls ELSE rcls END AS vote FROM test JOIN stump USING (f)) GROUP BY row_id"))
add("stump_importance_oob", lambda s, d: stump_forest(s, d, STEERED)[0].trees.select("block", "iter", F.round("oob_error", 8).alias("oob_error")), duck(_CHAIN + " " + _ERRORS))

add("forest_prune", lambda s, d: stump_forest(s, d, STEERED)[0].prune(5).trees.select("block", "iter"), duck(_CHAIN + ' SELECT block, "iter" FROM (' + _ERRORS.replace("round(", "(").replace(", 8)", ")") + ') ORDER BY oob_error, block * 1000000 + "iter" LIMIT 5'))

# -- the experiments in small, on forests of stumps: serial, waves, plateau, bite sizes, floors, lazy measures ------------------


def _waves(s, d) -> DataFrame:
    return _stump_rows(train_in_waves(stump_sets(s, d)[0], STUMPS, shared_path(s, "forests"), wave=3))


def _plateau(s, d) -> DataFrame:
    train, test = stump_sets(s, d)
    _, seen = train_until_plateau(train.drop("block"), STUMPS, test, tolerance=-1.0)
    return s.createDataFrame([(q, round(share, 8)) for q, share in seen], "blocks int, accuracy double")


_TREE_ROWS = 'SELECT block, i::INT AS "iter", feature, round(threshold, 8) AS threshold, lcls, rcls FROM stump'
add("stump_forest_serial", lambda s, d: _stump_rows(train_serial(stump_sets(s, d)[0], STUMPS)), duck(_STUMPS + _TREE_ROWS + " WHERE block = 0"))
add("stump_forest_waves", _waves, duck(_STUMPS + _TREE_ROWS))
add("stump_forest_plateau", _plateau, duck(_STUMPS + """, cell AS (SELECT q, row_id, label, sum(vote) AS ones, count(*) AS m FROM vote, (VALUES (1), (2), (4)) a(q) WHERE tree_id // 1000000 < q GROUP BY ALL)
SELECT q AS blocks, round(avg(((2 * ones > m)::INT = label)::INT), 8) AS accuracy FROM cell GROUP BY q"""))
#: The first block at two bite sizes: block numbers of the draws are the sizes' places in the list.
_SIZES = (20, 60)
_BY_SIZE = _STUMPS.replace("(SELECT DISTINCT block, row_id FROM train)", "(SELECT DISTINCT q AS block, row_id FROM train, range(2) z(q) WHERE block = 0)").replace("FROM trees, range(60) t(s))", f"FROM trees, range({max(_SIZES)}) t(s) WHERE s < CASE block WHEN 0 THEN {_SIZES[0]} ELSE {_SIZES[1]} END)")
assert _BY_SIZE.count("z(q)") == 1 and _BY_SIZE.count("CASE block") == 1


def _bite_sizes(s, d) -> DataFrame:
    train, test = stump_sets(s, d)
    return tune_bite_size(train, list(_SIZES), STUMPS, test).select("bite_size", F.round("accuracy", 8).alias("accuracy"), "nodes")


add("stump_bite_sizes", _bite_sizes, duck(_BY_SIZE + f""", cell AS (SELECT tree_id // 1000000 AS block, row_id, label, sum(vote) AS ones, count(*) AS m FROM vote GROUP BY ALL)
SELECT CASE block WHEN 0 THEN {_SIZES[0]} ELSE {_SIZES[1]} END::INT AS bite_size, round(avg(((2 * ones > m)::INT = label)::INT), 8) AS accuracy, (3 * max(m))::BIGINT AS nodes FROM cell GROUP BY block"""))
_FLOOR = ForestParams(n_trees=1, bite_size=41, n_blocks=1, n_parts=1, sampler="bagging", learner="majority", draws="portable")


def _floor(s, d) -> DataFrame:
    train, test = stump_sets(s, d)
    pred = scoring.predict_full(train_mega_forest(train.drop("block"), _FLOOR), test)
    return measures.accuracy(pred, test).select(F.round("accuracy", 8).alias("accuracy"))


add("floor_majority", _floor, duck(_LONG + """, train AS (SELECT row_id, label, row_number() OVER (ORDER BY row_id) - 1 AS rk, count(*) OVER () AS size FROM (SELECT DISTINCT row_id, label FROM x WHERE {h[split|row_id]} % 5 <> 0)),
bite AS (SELECT label FROM (SELECT {h[choice-42|concat('0:0:', s)]} AS draw FROM range(41) t(s)) JOIN train ON rk = draw % size)
SELECT round(avg((label = (SELECT (2 * sum(label) > count(*))::INT FROM bite))::INT), 8) AS accuracy FROM (SELECT DISTINCT row_id, label FROM x WHERE {h[split|row_id]} % 5 = 0)"""))
_LEVELS_OF_STUMPS = (0.2, 0.05, 0.01)


def _lazy_measures(s, d) -> DataFrame:
    """Evaluation fraction, relative error and disagreement by level."""
    forest, test = stump_forest(s, d)
    full, out = scoring.predict_full(forest, test), None
    for alpha in _LEVELS_OF_STUMPS:
        lazy = scoring.predict_lazy(forest, test, "g1_fpc", alpha, min_votes=3, portable=True)
        parts = [measures.eval_fraction(lazy, 20), measures.relative_error(lazy, full, test), measures.disagreement(lazy, full)]
        values = [F.lit(v).cast("double").alias(c) for part in parts for c, v in part.first().asDict().items()]
        one = s.range(1).select(F.lit(alpha).alias("alpha"), *values).select("alpha", *[F.round(c, 8).alias(c) for c in ("eval_fraction", "savings", "relative_error", "disagreement")])
        out = one if out is None else out.unionAll(one)
    return out


_RING = _STUMPS + """, place AS (SELECT tree_id, row_number() OVER (ORDER BY {h[permute|tree_id]}, tree_id) - 1 AS nth FROM (SELECT DISTINCT tree_id FROM vote)),
ring AS (SELECT row_id, vote, (nth - {h[offset-7|row_id]} % 20 + 20) % 20 + 1 AS pos FROM vote JOIN place USING (tree_id)),
run AS (SELECT row_id, pos, sum(vote) OVER (PARTITION BY row_id ORDER BY pos) AS ones FROM ring)
"""


def _stops_sql(alpha: float) -> str:
    rule = Rule("g1_fpc", 20, alpha, 3)
    return f"SELECT {alpha!r}::DOUBLE AS alpha, row_id, (2 * ones > pos)::INT AS prediction, pos::INT AS votes_used FROM run JOIN (SELECT row_id, min(CASE WHEN pos = 20 OR greatest(ones, pos - ones) >= min_lead THEN pos END) AS used FROM run LEFT JOIN ({thresholds_sql(rule)}) t ON t.n = pos GROUP BY row_id) USING (row_id) WHERE pos = used"


add("stump_lazy_measures", _lazy_measures, duck(_RING + ", lazy AS (" + " UNION ALL ".join(map(_stops_sql, _LEVELS_OF_STUMPS)) + """)
SELECT alpha, round(avg(votes_used) / 20, 8) AS eval_fraction, round(20 / avg(votes_used), 8) AS savings, round(1 - avg((l.prediction = label)::INT) / avg((f.prediction = label)::INT), 8) AS relative_error, round(avg((l.prediction <> f.prediction)::INT), 8) AS disagreement
FROM lazy l JOIN full_vote f USING (row_id) GROUP BY alpha"""))
add("stump_stop_points", lambda s, d: measures.stop_histogram(scoring.predict_lazy(*stump_forest(s, d), "g1_fpc", 0.05, min_votes=3, portable=True)), duck(_RING + ", lazy AS (" + _stops_sql(0.05) + ") SELECT floor(log2(votes_used) + 1e-12)::INT AS bin, (2 ** floor(log2(votes_used) + 1e-12))::BIGINT AS low, count(*) AS n FROM lazy GROUP BY ALL"))

# -- what is left: metadata, storage, times -------------------------------------------------------------------------

add("drop_metadata", lambda s, d: fx.drop_metadata(load(s, d, "documents"), "text", "source"), "SELECT doc_id, lang, n_chars FROM documents")


def _storage(s, d) -> DataFrame:
    path = shared_path(s, "blocks")
    write_blocks(blocks.assign_blocks(labelled(s, d), 8), path)
    return block_storage(s, path).select("block", "rows", (F.col("files") > 0).alias("on_disk"), (F.col("bytes") > 0).alias("measured"))


add("block_storage", _storage, f"SELECT ({portable_sql('block-42', 'row_id')} % 8)::INT AS block, count(*) AS rows, true AS on_disk, true AS measured FROM {_LABELLED} GROUP BY 1")
_LINES = "(VALUES ('one', 0.5, 1.0), ('one', 0.9, 4.0), ('one', 0.93, 9.0), ('two', 0.91, 2.0), ('two', 0.89, 3.0), ('three', 0.2, 0.1))"
add("time_to_accuracy", lambda s, d: measures.time_to_accuracy(s.sql(f"SELECT line, cast(accuracy AS double) AS accuracy, cast(seconds AS double) AS seconds FROM {_LINES} AS t(line, accuracy, seconds)"), F.lit(0.9)), f"SELECT line, min(seconds)::DOUBLE AS seconds FROM {_LINES} t(line, accuracy, seconds) WHERE accuracy >= 0.9 GROUP BY line")
