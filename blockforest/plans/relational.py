"""Relational, window and scalar queries on the given tables, each with its DuckDB twin.

``Q[name] = (Spark SQL, DuckDB SQL)``; one text serves both where the dialects agree.
"""

from __future__ import annotations

from ..functions.hashing import portable_sql

Q: dict[str, tuple[str, str]] = {}


def h(seed: str, value: str) -> str:
    """The portable hash in Spark SQL."""
    return f"cast(conv(substr(md5(concat('{seed}|', cast({value} as string))), 1, 8), 16, 10) as bigint)"


def add(name: str, spark: str, duck: str | None = None) -> None:
    Q[name] = (spark, duck or spark)


add("scan_project_filter", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 7) AS gross FROM lineitem WHERE l_discount BETWEEN 0.05 AND 0.07 AND l_shipdate >= TIMESTAMP '1996-01-01 00:00:00' AND l_shipdate < TIMESTAMP '1997-01-01 00:00:00'")
add("null_safe_filter",
    f"SELECT event_id, a, b FROM (SELECT event_id, CASE WHEN {h('na', 'event_id')} % 5 = 0 THEN NULL ELSE event_type END AS a, CASE WHEN {h('nb', 'event_id')} % 4 = 0 THEN NULL ELSE event_type END AS b FROM events) t WHERE a <=> b AND (a IS NULL OR NOT (a = 'click'))",
    f"SELECT event_id, a, b FROM (SELECT event_id, CASE WHEN {portable_sql('na', 'event_id')} % 5 = 0 THEN NULL ELSE event_type END AS a, CASE WHEN {portable_sql('nb', 'event_id')} % 4 = 0 THEN NULL ELSE event_type END AS b FROM events) t WHERE a IS NOT DISTINCT FROM b AND (a IS NULL OR NOT (a = 'click'))")
add("case_bucket", "SELECT CASE WHEN value < 10 THEN 'low' WHEN value < 50 THEN 'mid' ELSE 'high' END AS bucket, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY 1")
add("join_inner_star", "SELECT r_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY r_name")
add("join_left_outer_labels", "SELECT d.doc_id, d.lang, l.quality, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
add("join_right_full", "SELECT coalesce(c.k, s.k) AS k, coalesce(c.n, 0) AS customers, coalesce(s.n, 0) AS suppliers FROM (SELECT concat(cast(c_nationkey AS varchar(9)), ':', cast(cast(floor(c_acctbal / 500) AS bigint) AS varchar(9))) AS k, count(*) AS n FROM customer GROUP BY 1) c FULL OUTER JOIN (SELECT concat(cast(s_nationkey AS varchar(9)), ':', cast(cast(floor(s_acctbal / 500) AS bigint) AS varchar(9))) AS k, count(*) AS n FROM supplier GROUP BY 1) s ON c.k = s.k")
add("join_semi", "SELECT doc_id, n_chars FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
add("join_anti", "SELECT c_custkey, c_name FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey)")
add("join_cross", "SELECT n_name, event_type FROM nation CROSS JOIN (SELECT DISTINCT event_type FROM events) t")
# A range join by buckets as wide as the range: each supplier looks into two of them, instead of at every part.
add("join_theta_range",
    "SELECT s_suppkey, count(*) AS n FROM (SELECT s_suppkey, s_acctbal, explode(array(floor(s_acctbal / 20), floor(s_acctbal / 20) + 1)) AS b FROM supplier) s JOIN (SELECT p_retailprice, floor(p_retailprice / 20) AS b FROM part) p ON s.b = p.b AND p_retailprice >= s_acctbal AND p_retailprice < s_acctbal + 20 GROUP BY s_suppkey",
    "SELECT s_suppkey, count(*) AS n FROM supplier JOIN part ON p_retailprice >= s_acctbal AND p_retailprice < s_acctbal + 20 GROUP BY s_suppkey")
add("join_asof",
    "SELECT event_id, before_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type <> 'error' THEN event_id END, true) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before_id FROM events) t WHERE event_type = 'error'",
    "SELECT e.event_id, (SELECT o.event_id FROM events o WHERE o.user_id = e.user_id AND o.event_type <> 'error' AND (o.ts < e.ts OR (o.ts = e.ts AND o.event_id < e.event_id)) ORDER BY o.ts DESC, o.event_id DESC LIMIT 1) AS before_id FROM events e WHERE e.event_type = 'error'")
# Counted by a range frame, not by pairs; a user's days are windows of their own, each with the purchases of the next day's first hour.
add("join_interval",
    """WITH e AS (SELECT event_id, user_id, event_type, ts, cast(ts AS date) AS day FROM events
      UNION ALL SELECT event_id, user_id, event_type, ts, date_sub(cast(ts AS date), 1) FROM events WHERE event_type = 'purchase' AND ts <= cast(cast(ts AS date) AS timestamp_ntz) + INTERVAL 1 HOUR)
    SELECT event_id, n FROM (SELECT event_id, event_type, count(CASE WHEN event_type = 'purchase' THEN 1 END) OVER (PARTITION BY user_id, day ORDER BY ts RANGE BETWEEN INTERVAL '0.000001' SECOND FOLLOWING AND INTERVAL '3600' SECOND FOLLOWING) AS n FROM e) t WHERE event_type = 'click' AND n > 0""",
    "SELECT a.event_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase' GROUP BY a.event_id")
add("join_self_dups", "SELECT d.doc_id, c.class_id, c.copies FROM documents d JOIN (SELECT md5(text) AS h, min(doc_id) AS class_id, count(*) AS copies FROM documents GROUP BY md5(text) HAVING count(*) > 1) c ON md5(d.text) = c.h")
add("join_salted",
    "SELECT e.event_type, count(*) AS n, round(sum(e.value * w.weight), 4) AS weighted FROM (SELECT *, pmod(event_id, 4) AS salt FROM events) e JOIN (SELECT event_type, weight, explode(sequence(0, 3)) AS salt FROM (SELECT event_type, count(*) / 1000.0D AS weight FROM events GROUP BY event_type) x) w ON e.event_type = w.event_type AND e.salt = w.salt GROUP BY e.event_type",
    "SELECT e.event_type, count(*) AS n, round(sum(e.value * w.weight), 4) AS weighted FROM events e JOIN (SELECT event_type, count(*) / 1000.0::DOUBLE AS weight FROM events GROUP BY event_type) w USING (event_type) GROUP BY e.event_type")
add("join_lateral", "SELECT n.n_nationkey, c.c_custkey, c.c_acctbal FROM nation n, LATERAL (SELECT c_custkey, c_acctbal FROM customer WHERE c_nationkey = n.n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2) c")
add("agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 4) AS qty, round(avg(l_extendedprice), 6) AS price, min(l_tax) AS low, max(l_tax) AS high FROM lineitem GROUP BY l_returnflag, l_linestatus")
add("agg_stats", "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_discount), 8) AS vp, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_pop(l_quantity, l_tax), 6) AS cp FROM lineitem GROUP BY l_returnflag")
add("agg_distinct", "SELECT l_linestatus, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_linestatus")
add("agg_filter", "SELECT user_id, count(*) FILTER (WHERE event_type = 'error') AS errors, round(sum(value) FILTER (WHERE event_type = 'purchase'), 6) AS spent FROM events GROUP BY user_id")
add("agg_argmax", "SELECT source, max_by(lang, n * 10 - k) AS lang FROM (SELECT source, lang, count(*) AS n, CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END AS k FROM documents GROUP BY source, lang) t GROUP BY source")
add("agg_collect", "SELECT user_id, array_join(array_sort(collect_set(event_type)), ',') AS types FROM events GROUP BY user_id", "SELECT user_id, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS types FROM events GROUP BY user_id")
for kind in ("rollup", "cube"):
    add(f"agg_{kind}", f"SELECT lang, source, cast(grouping(lang) * 2 + grouping(source) AS bigint) AS gid, count(*) AS n FROM documents GROUP BY {kind}(lang, source)")
add("agg_grouping_sets", "SELECT lang, source, cast(grouping(lang) * 2 + grouping(source) AS bigint) AS gid, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
add("agg_pivot",
    f"SELECT * FROM (SELECT {h('block', 'doc_id')} % 4 AS block, lang FROM documents) PIVOT (count(*) FOR lang IN ('de' AS de, 'en' AS en, 'es' AS es, 'fr' AS fr))",
    f"SELECT {portable_sql('block', 'doc_id')} % 4 AS block, count(*) FILTER (WHERE lang = 'de') AS de, count(*) FILTER (WHERE lang = 'en') AS en, count(*) FILTER (WHERE lang = 'es') AS es, count(*) FILTER (WHERE lang = 'fr') AS fr FROM documents GROUP BY 1")
add("agg_unpivot",
    "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, feature, value FROM (SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_discount, l_tax FROM lineitem) UNPIVOT (value FOR feature IN (l_quantity, l_discount, l_tax))",
    "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, feature, value FROM (SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, unnest(['l_quantity', 'l_discount', 'l_tax']) AS feature, unnest([l_quantity, l_discount, l_tax]) AS value FROM lineitem)")
add("agg_percentile", "SELECT lang, percentile(n_chars, 0.5) AS median, percentile(n_chars, 0.9) AS p90 FROM documents GROUP BY lang", "SELECT lang, quantile_cont(n_chars, 0.5) AS median, quantile_cont(n_chars, 0.9) AS p90 FROM documents GROUP BY lang")
add("agg_having", "SELECT user_id, count(*) AS errors FROM events WHERE event_type = 'error' GROUP BY user_id HAVING count(*) > 12")
add("agg_bool_mode", "SELECT lang, bool_and(n_chars > 0) AS all_long, bool_or(n_chars > 20000) AS any_huge, count(*) AS n FROM documents GROUP BY lang")
add("win_rank_family", "SELECT doc_id, lang, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, round(percent_rank() OVER v, 8) AS pr, round(cume_dist() OVER v, 8) AS cd, ntile(10) OVER w AS nt FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars, doc_id), v AS (PARTITION BY lang ORDER BY n_chars)")
add("win_lag_lead", "SELECT event_id, lag(event_id) OVER w AS prev_id, lead(event_id, 2) OVER w AS next2_id, round(value - lag(value, 1, 0.0) OVER w, 6) AS step FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
add("win_first_last_nth", "SELECT event_id, first_value(event_type) OVER w AS f, last_value(event_type) OVER w AS l, nth_value(event_type, 2) OVER w AS s FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)")
add("win_rows_frame", "SELECT event_id, sum(CASE WHEN event_type = 'error' THEN 1 ELSE 0 END) OVER w AS errors, round(avg(value) OVER c, 6) AS smooth FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), c AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING)",
    "SELECT event_id, (sum(CASE WHEN event_type = 'error' THEN 1 ELSE 0 END) OVER w)::BIGINT AS errors, round(avg(value) OVER c, 6) AS smooth FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), c AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING)")
add("win_range_frame", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW), 6) AS hour_sum FROM events")
add("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50")
add("topk_per_group", "SELECT p_brand, p_partkey, p_retailprice FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS rn FROM part) t WHERE rn <= 3")
add("sort_multi", "SELECT c_custkey, c_mktsegment, c_acctbal FROM customer ORDER BY c_mktsegment, c_acctbal DESC NULLS LAST, c_custkey")
add("limit_offset", "SELECT s_suppkey, s_acctbal FROM supplier ORDER BY s_acctbal, s_suppkey LIMIT 20 OFFSET 10")
add("set_union_all", "SELECT n_nationkey AS k FROM nation UNION ALL SELECT c_nationkey FROM customer")
add("set_union_distinct", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
add("set_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
add("set_intersect_all", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
add("set_except", "SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000")
add("set_except_all", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
add("dedup_keep_first", "SELECT doc_id, h FROM (SELECT doc_id, md5(text) AS h, row_number() OVER (PARTITION BY md5(text) ORDER BY doc_id) AS rn FROM documents) t WHERE rn = 1")
add("fn_string", "SELECT doc_id, lower(substr(text, 1, 12)) AS head, length(replace(text, 'e', '')) AS no_e, instr(text, 'th') AS at, concat_ws('-', lang, source) AS tag, reverse(substr(text, 1, 5)) AS rev, lpad(cast(doc_id AS varchar(10)), 6, '0') AS padded FROM documents")
add("fn_regex", "SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, regexp_replace(url, '[0-9]+', '#') AS shape FROM pages", "SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, regexp_replace(url, '[0-9]+', '#', 'g') AS shape FROM pages")
add("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, quarter(o_orderdate) AS q, cast(date_trunc('month', o_orderdate) AS date) AS mo, datediff(DATE '2002-01-01', cast(o_orderdate AS date)) AS age FROM orders", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, quarter(o_orderdate) AS q, date_trunc('month', o_orderdate)::DATE AS mo, date_diff('day', o_orderdate::DATE, DATE '2002-01-01') AS age FROM orders")
add("fn_math", "SELECT p_partkey, round(ln(p_retailprice), 8) AS l, round(log2(p_size), 8) AS l2, round(sqrt(p_retailprice), 8) AS s, floor(p_retailprice / 7) AS f, round(pow(p_size, 1.5), 6) AS p, greatest(p_size, 25) AS g, least(p_size, 25) AS e, abs(p_size - 25) AS a FROM part")
add("fn_array", "SELECT vec_id, size(filter(embedding, x -> x > 0)) AS positive, round(aggregate(embedding, 0D, (a, x) -> a + x), 4) AS total, array_position(transform(slice(embedding, 1, 4), x -> x > 0), true) AS first_positive FROM embeddings", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(list_reduce(list_transform(embedding, lambda x: x::DOUBLE), lambda a, x: a + x), 4) AS total, coalesce(list_position(list_transform(embedding[1:4], lambda x: x > 0), true), 0) AS first_positive FROM embeddings")
add("fn_map", "SELECT user_id, element_at(m, 'error') AS errors, size(m) AS kinds FROM (SELECT user_id, map_from_entries(collect_list(struct(event_type, n))) AS m FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type) x GROUP BY user_id) y", "SELECT user_id, max(CASE WHEN event_type = 'error' THEN n END) AS errors, count(*) AS kinds FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type) GROUP BY user_id")
add("fn_json", "SELECT event_id, cast(get_json_object(props, '$.k') AS bigint) AS k FROM events", "SELECT event_id, json_extract(props, '$.k')::BIGINT AS k FROM events")
add("fn_hash", f"SELECT doc_id, md5(text) AS h, sha2(text, 256) AS s, {h('fn', 'doc_id')} AS p FROM documents", f"SELECT doc_id, md5(text) AS h, sha256(text) AS s, {portable_sql('fn', 'doc_id')} AS p FROM documents")
add("hof_vector", "SELECT a.vec_id, round(sqrt(aggregate(a.embedding, 0D, (s, x) -> s + cast(x AS double) * x)), 4) AS norm, round(aggregate(zip_with(a.embedding, b.embedding, (x, y) -> cast(x AS double) * y), 0D, (s, x) -> s + x), 4) AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = 0", "SELECT a.vec_id, round(sqrt(list_inner_product(a.embedding::DOUBLE[], a.embedding::DOUBLE[])), 4) AS norm, round(list_inner_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = 0")
add("subquery_scalar", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.8 FROM orders)")
add("subquery_exists", "SELECT s_suppkey FROM supplier WHERE s_suppkey IN (SELECT l_suppkey FROM lineitem WHERE l_quantity >= 50)")
add("subquery_correlated", "SELECT o_orderkey FROM orders o WHERE o_totalprice > 1.5 * (SELECT avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
add("cte_recursive", "WITH RECURSIVE walk(node, depth) AS (SELECT o_orderkey, 0 FROM orders WHERE o_orderkey = 1 UNION ALL SELECT o_orderkey, depth + 1 FROM walk JOIN orders ON o_orderkey DIV 2 = node WHERE depth < 6) SELECT depth, count(*) AS nodes, max(node) AS last FROM walk GROUP BY depth", "WITH RECURSIVE walk(node, depth) AS (SELECT o_orderkey, 0 FROM orders WHERE o_orderkey = 1 UNION ALL SELECT o_orderkey, depth + 1 FROM walk JOIN orders ON o_orderkey // 2 = node WHERE depth < 6) SELECT depth, count(*) AS nodes, max(node) AS last FROM walk GROUP BY depth")
add("window_tumbling", "SELECT cast(w.start AS timestamp_ntz) AS start, event_type, n FROM (SELECT window(ts, '1 day') AS w, event_type, count(*) AS n FROM events GROUP BY window(ts, '1 day'), event_type) t", "SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
add("window_sliding", "SELECT cast(w.start AS timestamp_ntz) AS start, n FROM (SELECT window(ts, '2 days', '1 day') AS w, count(*) AS n FROM events GROUP BY window(ts, '2 days', '1 day')) t", "SELECT start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') - INTERVAL 1 DAY]) AS start FROM events) GROUP BY start")
add("window_session",
    "SELECT user_id, cast(w.start AS timestamp_ntz) AS start, n FROM (SELECT user_id, session_window(ts, '6 hours') AS w, count(*) AS n FROM events GROUP BY user_id, session_window(ts, '6 hours')) t",
    "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
