"""Registered queries: the relational and SQL surface that users of the methods need.

Plain relational forms are SQL over the registered tables; where the two dialects differ, the
Spark text comes second.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from ..plans.oracle import sql as with_views
from ..sources.tables import Tables
from .registry import register


def s(key, text, spark_text=None):
    register(key, lambda spark, d: Tables(spark, d).views().spark.sql(spark_text or text), text)


def d(key, fn, text=None):
    register(key, lambda spark, sf: fn(Tables(spark, sf)), with_views(text) if text else None)


s("q_scan_cases", "SELECT o_orderkey, o_orderpriority FROM orders WHERE o_orderdate >= DATE '2000-01-01'")
s("q_cohort_filter", "SELECT o_orderkey FROM orders JOIN customer ON o_custkey = c_custkey WHERE o_custkey % 2 = 0 AND 18 + (o_orderkey*7 + o_custkey*3) % 72 BETWEEN 40 AND 64 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND c_mktsegment LIKE '%U%'")
s("q_null_safe", "SELECT count(*) AS n FROM (SELECT doc_id, CASE WHEN doc_id % 3 = 0 THEN NULL ELSE lang END AS a, CASE WHEN doc_id % 3 = 0 THEN NULL ELSE lang END AS b FROM documents) WHERE a IS NOT DISTINCT FROM b", "SELECT count(*) AS n FROM (SELECT doc_id, CASE WHEN doc_id % 3 = 0 THEN NULL ELSE lang END AS a, CASE WHEN doc_id % 3 = 0 THEN NULL ELSE lang END AS b FROM documents) WHERE a <=> b")
s("q_join_broadcast", "SELECT n_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name", "SELECT /*+ BROADCAST(nation) */ n_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
for hint, key in (("MERGE", "q_join_merge"), ("SHUFFLE_HASH", "q_join_shuffle_hash")):
    t = "o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority"
    s(key, f"SELECT {t}", f"SELECT /*+ {hint}(orders) */ {t}")
s("q_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT')")
s("q_anti", "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
s("q_full_outer", "SELECT coalesce(a.k, b.k) AS k, a.n AS urgent, b.n AS low FROM (SELECT o_custkey AS k, count(*) AS n FROM orders WHERE o_orderpriority = '1-URGENT' GROUP BY 1) a FULL OUTER JOIN (SELECT o_custkey AS k, count(*) AS n FROM orders WHERE o_orderpriority = '5-LOW' GROUP BY 1) b ON a.k = b.k")
# Spark keeps the order under a correlated LIMIT only if its select list has what it sorts by; else any two rows come out.
s("q_lateral_topn", "SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) AS x", "SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC NULLS LAST, o_orderkey NULLS LAST LIMIT 2) AS x")
s("q_agg_basic", "SELECT l_returnflag, count(*) AS n, round(avg(l_quantity), 4) AS qty FROM lineitem GROUP BY l_returnflag HAVING count(*) > 10")
s("q_agg_filter", "SELECT l_linestatus, count(*) FILTER (WHERE l_returnflag = 'R') AS r, count(*) FILTER (WHERE l_returnflag = 'A') AS a FROM lineitem GROUP BY l_linestatus")
s("q_agg_distinct", "SELECT r_name, count(DISTINCT s_suppkey) AS dx, count(DISTINCT l_partkey) AS findings FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
s("q_agg_physical", "SELECT l_suppkey, count(*) AS n, array_to_string(list_sort(list(DISTINCT l_returnflag)), ',') AS flags FROM lineitem GROUP BY l_suppkey", "SELECT l_suppkey, count(*) AS n, array_join(array_sort(collect_set(l_returnflag)), ',') AS flags FROM lineitem GROUP BY l_suppkey")
d("q_approx_distinct", lambda t: t.lineitem.agg(F.approx_count_distinct("l_partkey", 0.02).alias("approx"), F.count_distinct("l_partkey").alias("exact")))
s("q_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
s("q_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
s("q_grouping_sets", "SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderpriority), (o_orderstatus), ())")
d("q_pivot", lambda t: t.orders.groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "5-LOW"]).count().select("o_orderstatus", F.coalesce("1-URGENT", F.lit(0)).alias("urgent"), F.coalesce("5-LOW", F.lit(0)).alias("low")), "SELECT o_orderstatus, sum(CASE WHEN o_orderpriority = '1-URGENT' THEN 1 ELSE 0 END)::BIGINT AS urgent, sum(CASE WHEN o_orderpriority = '5-LOW' THEN 1 ELSE 0 END)::BIGINT AS low FROM orders GROUP BY 1")
d("q_unpivot", lambda t: t.part.groupBy("p_brand").agg(F.min("p_size").cast("int").alias("low"), F.max("p_size").cast("int").alias("high")).unpivot("p_brand", ["low", "high"], "side", "size"), "SELECT p_brand, 'low' AS side, min(p_size) AS size FROM part GROUP BY 1 UNION ALL SELECT p_brand, 'high' AS side, max(p_size) AS size FROM part GROUP BY 1")
s("q_collect_sets", "SELECT o_custkey, array_to_string(list_sort(list(DISTINCT o_orderpriority)), ',') AS seen FROM orders GROUP BY 1", "SELECT o_custkey, array_join(array_sort(collect_set(o_orderpriority)), ',') AS seen FROM orders GROUP BY 1")
# Of equal prices the smallest key counts: the twin keeps the first row that it meets.
s("q_argmax", "SELECT o_custkey, max_by(o_orderkey, o_totalprice) AS top FROM orders GROUP BY 1", "SELECT o_custkey, max_by(o_orderkey, CASE WHEN o_orderkey IS NOT NULL AND o_totalprice IS NOT NULL THEN struct(o_totalprice, ~o_orderkey) END) AS top FROM orders GROUP BY 1")
s("q_percentile", "SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90, round(stddev_samp(l_quantity), 4) AS sd FROM lineitem GROUP BY 1", "SELECT l_returnflag, round(percentile(l_extendedprice, 0.9), 4) AS p90, round(stddev_samp(l_quantity), 4) AS sd FROM lineitem GROUP BY 1")
s("q_corr", "SELECT round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem")
W = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey"
s("q_win_rank", f"SELECT o_orderkey, CAST(row_number() {W}) AS BIGINT) AS rn, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS BIGINT) AS rk, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS BIGINT) AS dr, CAST(ntile(3) {W}) AS BIGINT) AS tertile, round(percent_rank() {W}), 6) AS pr, round(cume_dist() {W}), 6) AS cd FROM orders")
s("q_win_lag", f"SELECT o_orderkey, lag(o_orderkey) {W}) AS before, lead(o_orderkey) {W}) AS after FROM orders")
s("q_win_nth", f"SELECT o_orderkey, first_value(o_orderkey) {W}) AS first, nth_value(o_orderkey, 2) {W} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM orders")
s("q_win_rows", f"SELECT o_orderkey, round(avg(o_totalprice) {W} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving FROM orders")
s("q_win_range", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL 90 DAY PRECEDING AND CURRENT ROW) AS recent FROM orders", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL '90' DAY PRECEDING AND CURRENT ROW) AS recent FROM orders")
s("q_win_running", f"SELECT o_orderkey, round(sum(o_totalprice) {W} ROWS UNBOUNDED PRECEDING), 2) AS running FROM orders")
s("q_sort_multi", "SELECT o_orderkey, o_orderpriority FROM orders ORDER BY o_orderpriority DESC NULLS LAST, o_orderkey LIMIT 50")
s("q_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")
s("q_topk_group", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 3")
s("q_sample_hash", "SELECT o_orderkey FROM orders WHERE (o_orderkey * 7919) % 10007 < 500")
s("q_union", "SELECT o_custkey AS k FROM orders WHERE o_orderpriority = '1-URGENT' UNION SELECT c_custkey AS k FROM customer WHERE c_acctbal < 0")
s("q_intersect", "SELECT o_custkey AS k FROM orders INTERSECT SELECT c_custkey AS k FROM customer WHERE c_acctbal < 0")
s("q_except_all", "SELECT o_custkey AS k FROM orders EXCEPT ALL SELECT c_custkey AS k FROM customer")
s("q_exists", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_custkey = c_custkey AND l_returnflag = 'R')")
s("q_scalar_subquery", "SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer)")
s("q_recursive_hierarchy", "WITH RECURSIVE up(k, anc, depth) AS (SELECT s_suppkey, CAST(s_nationkey AS BIGINT), 1 FROM supplier UNION ALL SELECT k, CAST(100 + n_regionkey AS BIGINT), depth + 1 FROM up JOIN nation ON anc = n_nationkey WHERE depth = 1) SELECT k, anc, depth FROM up")
s("q_str_normalize", "SELECT p_partkey, array_to_string(list_sort(string_split(lower(trim(p_name)), ' ')), ' ') AS norm, translate(p_name, 'aeiou', 'AEIOU') AS folded FROM part", "SELECT p_partkey, array_join(array_sort(split(lower(trim(p_name)), ' ')), ' ') AS norm, translate(p_name, 'aeiou', 'AEIOU') AS folded FROM part")
s("q_str_codes", "SELECT s_suppkey, lpad(CAST(s_suppkey AS VARCHAR), 6, '0') AS code, concat_ws('/', substr(s_name, 1, 4), CAST(s_nationkey AS VARCHAR)) AS tag FROM supplier", "SELECT s_suppkey, lpad(CAST(s_suppkey AS STRING), 6, '0') AS code, concat_ws('/', substr(s_name, 1, 4), CAST(s_nationkey AS STRING)) AS tag FROM supplier")
s("q_str_regex", "SELECT doc_id, regexp_extract(text, '([0-9]+)', 1) AS num, length(regexp_replace(text, '[0-9]', '', 'g')) AS rest FROM documents WHERE regexp_matches(text, '[0-9]')", r"SELECT doc_id, regexp_extract(text, '([0-9]+)', 1) AS num, length(regexp_replace(text, '[0-9]', '')) AS rest FROM documents WHERE text RLIKE '[0-9]'")
s("q_str_distance", "SELECT a.p_partkey, levenshtein(a.p_name, b.p_name) AS dist FROM part a JOIN part b ON b.p_partkey = a.p_partkey + 1")
s("q_str_contains", "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
d("q_url_parts", lambda t: t.pages.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.length(F.regexp_replace("html", "<[^>]*>", "")).alias("n")), "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, CAST(length(regexp_replace(html, '<[^>]*>', '', 'g')) AS INTEGER) AS n FROM pages")
s("q_date_trunc_month", "SELECT CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS m, count(*) AS n FROM orders GROUP BY 1", "SELECT CAST(CAST(date_trunc('MONTH', o_orderdate) AS DATE) AS STRING) AS m, count(*) AS n FROM orders GROUP BY 1")
s("q_date_gap", "SELECT o_custkey, max(date_diff('day', CAST(prev AS DATE), CAST(o_orderdate AS DATE))) AS gap FROM (SELECT o_custkey, o_orderdate, lag(o_orderdate) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS prev FROM orders) GROUP BY 1", "SELECT o_custkey, max(datediff(CAST(o_orderdate AS DATE), CAST(prev AS DATE))) AS gap FROM (SELECT o_custkey, o_orderdate, lag(o_orderdate) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS prev FROM orders) GROUP BY 1")
s("q_date_add", "SELECT o_orderkey, CAST(CAST(CAST(o_orderdate AS DATE) + INTERVAL 30 DAY AS DATE) AS VARCHAR) AS due FROM orders", "SELECT o_orderkey, CAST(date_add(CAST(o_orderdate AS DATE), 30) AS STRING) AS due FROM orders")
s("q_date_parts", "SELECT year(o_orderdate) AS y, month(o_orderdate) AS mo, count(*) AS n FROM orders GROUP BY 1, 2")
s("q_math", "SELECT o_orderkey, round(log2(o_totalprice + 1), 6) AS l2, round(ln(o_totalprice + 1), 6) AS ln, round(pow(o_totalprice, 0.5), 6) AS root, greatest(o_orderkey, o_custkey) AS hi, o_orderkey % 7 AS md FROM orders")
s("q_array_sets", "SELECT doc_id, len(list_distinct(string_split(text, ' '))) AS vocab FROM documents", "SELECT doc_id, CAST(size(array_distinct(split(text, ' '))) AS BIGINT) AS vocab FROM documents")
s("q_array_hof", "SELECT p_partkey, array_to_string(list_transform(list_filter(string_split(p_name, ' '), lambda x: length(x) > 3), lambda x: upper(x)), '+') AS big FROM part", "SELECT p_partkey, array_join(transform(filter(split(p_name, ' '), x -> length(x) > 3), x -> upper(x)), '+') AS big FROM part")
d("q_map_scores", lambda t: t.orders.groupBy("o_custkey").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct(F.col("o_orderkey").cast("string"), "o_totalprice")))).alias("m")).select("o_custkey", F.explode(F.transform_values("m", lambda k, v: F.round(v * 2, 2))).alias("k", "v")), "SELECT o_custkey, CAST(o_orderkey AS VARCHAR) AS k, round(o_totalprice * 2, 2) AS v FROM orders")
s("q_json_props", "SELECT event_id, CAST(props->>'k' AS BIGINT) AS k FROM events", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events")
s("q_variant_props", "SELECT event_id, CAST(props->>'k' AS BIGINT) AS k FROM events", "SELECT event_id, variant_get(parse_json(props), '$.k', 'bigint') AS k FROM events")
s("q_content_hash", "SELECT doc_id, md5(text) AS m, sha256(text) AS h FROM documents", "SELECT doc_id, md5(text) AS m, sha2(text, 256) AS h FROM documents")
s("q_dedupe_exact", "SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY md5(lower(text))")
s("q_asof", "SELECT event_id, user_id, (SELECT max(o_orderdate) FROM orders WHERE o_custkey = user_id AND o_orderdate <= e.ts)::DATE::VARCHAR AS last_case FROM events e", "SELECT event_id, user_id, CAST(CAST(last_case AS DATE) AS STRING) AS last_case FROM (SELECT event_id, k AS user_id, last_value(od, true) OVER (PARTITION BY k ORDER BY at, pri ROWS UNBOUNDED PRECEDING) AS last_case FROM (SELECT NULL AS event_id, o_custkey AS k, o_orderdate AS at, o_orderdate AS od, 0 AS pri FROM orders UNION ALL SELECT event_id, user_id, ts, NULL, 1 FROM events)) WHERE event_id IS NOT NULL")
BIN = 90
d("q_range_join", lambda t: (lambda c, x: c.join(x, ["subject", "bin"]).where((F.col("od") <= F.col("sd")) & (F.datediff("sd", "od") <= BIN)).groupBy("case_id").agg(F.count("*").alias("n_lines")))(
    t.orders.select(F.col("o_orderkey").alias("case_id"), F.col("o_custkey").alias("subject"), F.to_date("o_orderdate").alias("od")).withColumn("_b", F.floor(F.datediff("od", F.lit("1990-01-01")) / BIN)).withColumn("bin", F.explode(F.array(F.col("_b"), F.col("_b") + 1))),
    t.lineitem.join(t.orders, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("subject"), F.to_date("l_shipdate").alias("sd")).withColumn("bin", F.floor(F.datediff("sd", F.lit("1990-01-01")) / BIN)),
), "SELECT o.o_orderkey AS case_id, count(*) AS n_lines FROM orders o JOIN orders p ON p.o_custkey = o.o_custkey JOIN lineitem l ON l.l_orderkey = p.o_orderkey WHERE CAST(l_shipdate AS DATE) >= CAST(o.o_orderdate AS DATE) AND date_diff('day', CAST(o.o_orderdate AS DATE), CAST(l_shipdate AS DATE)) <= 90 GROUP BY 1")
s("q_tumbling", "SELECT event_type, CAST(CAST(date_trunc('day', ts) AS DATE) AS VARCHAR) AS day, count(*) AS n FROM events GROUP BY 1, 2", "SELECT event_type, CAST(CAST(window.start AS DATE) AS STRING) AS day, count(*) AS n FROM events GROUP BY event_type, window(ts, '1 day')")
s("q_sliding", "SELECT CAST(epoch(w) AS BIGINT) AS start_s, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 6 HOUR, ts), time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR, time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 12 HOUR, time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 18 HOUR]) AS w FROM events) GROUP BY 1", "SELECT unix_timestamp(CAST(window.start AS TIMESTAMP)) AS start_s, count(*) AS n FROM events GROUP BY window(ts, '24 hours', '6 hours')")
s("q_session", "SELECT user_id, count(*) AS sessions FROM (SELECT user_id, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR > ts THEN 0 ELSE 1 END AS new FROM events) WHERE new = 1 GROUP BY 1", "SELECT user_id, count(*) AS sessions FROM (SELECT user_id, session_window(CAST(ts AS TIMESTAMP), '12 hours') AS w FROM events GROUP BY user_id, session_window(CAST(ts AS TIMESTAMP), '12 hours')) GROUP BY user_id")
s("q_calls_by_segment", "SELECT c_mktsegment, event_type, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1, 2")
s("q_stream_twin_join", "SELECT count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type < b.event_type")
s("q_sql_function", "SELECT o_orderkey, CASE WHEN o_orderpriority < '3' THEN 3 ELSE 1 END AS w FROM orders")
s("q_session_cost", "SELECT user_id, count(*) AS actions, round(sum(value), 2) AS cost, max(CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END) AS answered FROM events GROUP BY 1")
s("q_budget_cut", "SELECT user_id, event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS rn FROM events) WHERE rn <= 40")
s("q_context_tokens", "SELECT conv_id, sum(len(string_split(text, ' ')))::BIGINT AS tokens, count(*) AS turns FROM conversations GROUP BY 1", "SELECT conv_id, sum(size(split(text, ' '))) AS tokens, count(*) AS turns FROM conversations GROUP BY 1")
