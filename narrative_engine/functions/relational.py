"""The relational surface that users of the engine need: one query per operator, with its twin.

A pair is (what Spark runs, what DuckDB runs); one text stands for both where the dialects agree.
Sums of money are decimal, averages go through doubles of exact sums and are rounded half up, and
ranks are made total by a key, so results don't depend on partitions or order.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from narrative_engine.sources.tables import query

_R = "floor(({}) * 100 + 0.5) / 100"
_P = "CAST(l_extendedprice AS DECIMAL(12,2))"
_BANDS = "(SELECT 'low' AS band, 0 AS lo, 100000 AS hi UNION ALL SELECT 'middle', 100000, 250000 UNION ALL SELECT 'high', 250000, 100000000)"
_WEIGHTS = "(SELECT 1 AS version, DATE '1970-01-01' AS since UNION ALL SELECT 2, DATE '1994-01-01' UNION ALL SELECT 3, DATE '1996-06-01' UNION ALL SELECT 4, DATE '2024-01-01')"

CATALOGUE: dict[str, str | tuple[str, str]] = {
    "scan_filter_project": f"SELECT l_orderkey, l_linenumber, {_P} AS price FROM lineitem WHERE l_quantity >= 45 AND l_returnflag = 'R'",
    "pushdown_range": "SELECT o_orderkey, o_orderstatus FROM orders WHERE o_orderkey BETWEEN 100 AND 900 AND o_orderstatus IN ('F', 'O') AND o_orderpriority LIKE '1%'",
    "join_broadcast": "SELECT n_name, r_name, count(*) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY n_name, r_name",
    "join_sort_merge": ("SELECT /*+ MERGE(l) */ o_orderkey, count(*) AS n FROM orders o JOIN lineitem l ON l.l_orderkey = o.o_orderkey GROUP BY o_orderkey", "SELECT o_orderkey, count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey"),
    "join_shuffle_hash": ("SELECT /*+ SHUFFLE_HASH(c) */ c_mktsegment, count(*) AS n FROM orders o JOIN customer c ON c.c_custkey = o.o_custkey GROUP BY c_mktsegment", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY c_mktsegment"),
    "join_left_null_lines": "SELECT o_orderkey FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey WHERE l_orderkey IS NULL",
    "join_semi": ("SELECT c_custkey FROM customer LEFT SEMI JOIN orders ON o_custkey = c_custkey", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)"),
    "join_anti": ("SELECT c_custkey FROM customer LEFT ANTI JOIN orders ON o_custkey = c_custkey", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)"),
    "join_full_outer": "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.doc_id IS NULL AS no_document, l.doc_id IS NULL AS no_label FROM documents d FULL OUTER JOIN labels l ON l.doc_id = d.doc_id",
    "join_range_band": f"SELECT band, count(*) AS n FROM orders JOIN {_BANDS} b ON o_totalprice >= lo AND o_totalprice < hi GROUP BY band",
    "join_asof_weights": f"WITH w AS (SELECT version, since, coalesce(lead(since) OVER (ORDER BY since), DATE '9999-01-01') AS until FROM {_WEIGHTS} v) SELECT o_orderkey, version FROM orders JOIN w ON CAST(o_orderdate AS DATE) >= since AND CAST(o_orderdate AS DATE) < until",
    "join_interval_events": "SELECT a.event_id AS error_id, b.event_id AS near_id FROM events a JOIN events b ON b.user_id = a.user_id AND b.ts >= a.ts - INTERVAL 5 MINUTE AND b.ts <= a.ts + INTERVAL 5 MINUTE AND b.event_id <> a.event_id WHERE a.event_type = 'error'",
    "join_self_dups": "SELECT a.doc_id AS kept, b.doc_id AS copy FROM (SELECT md5(text) AS h, min(doc_id) AS doc_id FROM documents GROUP BY md5(text)) a JOIN documents b ON md5(b.text) = a.h WHERE b.doc_id > a.doc_id",
    "join_theta_styles": "WITH s AS (SELECT lang, CAST(sum(n_chars) AS BIGINT) AS n FROM documents GROUP BY lang) SELECT a.lang AS one, b.lang AS two FROM s a JOIN s b ON a.n < b.n",
    "join_null_safe": ("SELECT count(*) AS n FROM (SELECT nullif(event_type, 'error') AS t FROM events) a JOIN (SELECT nullif(column_t, 'error') AS t FROM (SELECT DISTINCT event_type AS column_t FROM events) x) b ON a.t <=> b.t", "SELECT count(*) AS n FROM (SELECT nullif(event_type, 'error') AS t FROM events) a JOIN (SELECT nullif(column_t, 'error') AS t FROM (SELECT DISTINCT event_type AS column_t FROM events) x) b ON a.t IS NOT DISTINCT FROM b.t"),
    "lateral_top_event": "SELECT c.c_custkey, o.o_orderkey FROM customer c, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c.c_custkey ORDER BY o_orderkey LIMIT 1) o",
    "agg_hash": f"SELECT l_returnflag, l_linestatus, CAST(sum({_P}) AS DECIMAL(28,2)) AS total, count(*) AS n, min(l_quantity) AS lo, max(l_quantity) AS hi FROM lineitem GROUP BY l_returnflag, l_linestatus",
    "agg_distinct": "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag",
    "agg_stats": (f"SELECT lang, {_R.format('stddev_pop(n_chars)')} AS sd, {_R.format('corr(n_chars, length(text)) * 100')} AS c FROM documents GROUP BY lang", f"SELECT lang, {_R.format('stddev_pop(n_chars)')} AS sd, {_R.format('corr(n_chars, length(text)) * 100')} AS c FROM documents GROUP BY lang"),
    "agg_percentile": ("SELECT c_mktsegment, floor(percentile(c_acctbal, 0.5) * 100 + 0.001) / 100 AS p50, floor(percentile(c_acctbal, 0.9) * 100 + 0.001) / 100 AS p90 FROM customer GROUP BY c_mktsegment", "SELECT c_mktsegment, floor(quantile_cont(c_acctbal, 0.5) * 100 + 0.001) / 100 AS p50, floor(quantile_cont(c_acctbal, 0.9) * 100 + 0.001) / 100 AS p90 FROM customer GROUP BY c_mktsegment"),
    "agg_mode": ("SELECT c_nationkey, mode() WITHIN GROUP (ORDER BY c_mktsegment) AS commonest FROM customer GROUP BY c_nationkey", "SELECT c_nationkey, c_mktsegment AS commonest FROM (SELECT c_nationkey, c_mktsegment, row_number() OVER (PARTITION BY c_nationkey ORDER BY count(*) DESC, c_mktsegment) AS r FROM customer GROUP BY c_nationkey, c_mktsegment) t WHERE r = 1"),
    "agg_regression": (f"SELECT l_returnflag, {_R.format('regr_slope(l_extendedprice, l_quantity)')} AS slope, {_R.format('regr_intercept(l_extendedprice, l_quantity)')} AS base, regr_count(l_extendedprice, l_quantity) AS n FROM lineitem GROUP BY l_returnflag", f"SELECT l_returnflag, {_R.format('regr_slope(l_extendedprice, l_quantity)')} AS slope, {_R.format('regr_intercept(l_extendedprice, l_quantity)')} AS base, CAST(regr_count(l_extendedprice, l_quantity) AS BIGINT) AS n FROM lineitem GROUP BY l_returnflag"),
    "agg_histogram": ("SELECT width_bucket(o_totalprice, 0, 500000, 20) AS bucket, count(*) AS n FROM orders GROUP BY 1", "SELECT CASE WHEN o_totalprice < 0 THEN 0 WHEN o_totalprice >= 500000 THEN 21 ELSE CAST(floor(o_totalprice / 500000 * 20) AS BIGINT) + 1 END AS bucket, count(*) AS n FROM orders GROUP BY 1"),
    "agg_filter_clause": "SELECT lang, count(*) FILTER (WHERE n_chars > 2000) AS n_long, count(*) FILTER (WHERE n_chars <= 2000) AS n_short FROM documents GROUP BY lang",
    "agg_having": "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) >= 15",
    "agg_bool": "SELECT o_custkey, bool_and(o_orderstatus = 'F') AS all_done, bool_or(o_orderpriority = '1-URGENT') AS any_urgent FROM orders GROUP BY o_custkey",
    "agg_grouping_sets": "SELECT lang, source, CAST(grouping(lang) AS INT) AS g_lang, CAST(grouping(source) AS INT) AS g_source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())",
    "agg_cube": "SELECT c_mktsegment, n_name, count(*) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey GROUP BY CUBE (c_mktsegment, n_name)",
    "agg_rollup": "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)",
    "agg_pivot": ("SELECT * FROM (SELECT lang, quality FROM documents d JOIN labels l ON l.doc_id = d.doc_id) PIVOT (count(*) FOR quality IN (0 AS junk, 1 AS good))", "SELECT lang, nullif(count(*) FILTER (WHERE quality = 0), 0) AS junk, nullif(count(*) FILTER (WHERE quality = 1), 0) AS good FROM documents d JOIN labels l ON l.doc_id = d.doc_id GROUP BY lang"),
    "agg_unpivot": ("SELECT doc_id, metric, grade FROM labels UNPIVOT (grade FOR metric IN (quality, toxic))", "SELECT doc_id, 'quality' AS metric, quality AS grade FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels"),
    "agg_listagg": ("SELECT r_name, listagg(n_name, ';') WITHIN GROUP (ORDER BY n_name) AS names FROM nation JOIN region ON r_regionkey = n_regionkey GROUP BY r_name", "SELECT r_name, string_agg(n_name, ';' ORDER BY n_name) AS names FROM nation JOIN region ON r_regionkey = n_regionkey GROUP BY r_name"),
    "agg_max_by": ("SELECT c_nationkey, max_by(c_custkey, struct(c_acctbal, c_custkey)) AS richest FROM customer GROUP BY c_nationkey", "SELECT c_nationkey, arg_max(c_custkey, {'a': c_acctbal, 'b': c_custkey}) AS richest FROM customer GROUP BY c_nationkey"),
    "win_row_number": "SELECT c_custkey, CAST(row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS BIGINT) AS r FROM customer",
    "win_rank_family": f"SELECT s_suppkey, CAST(rank() OVER (PARTITION BY s_nationkey % 5 ORDER BY s_nationkey) AS BIGINT) AS rk, CAST(dense_rank() OVER (PARTITION BY s_nationkey % 5 ORDER BY s_nationkey) AS BIGINT) AS dr, {_R.format('percent_rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)')} AS pr, {_R.format('cume_dist() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)')} AS cd FROM supplier",
    "win_ntile": "SELECT c_custkey, CAST(ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey) AS BIGINT) AS quarter FROM customer",
    "win_lag_lead": "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS after FROM events",
    "win_first_last": "SELECT o_orderkey, first_value(o_orderkey) OVER w AS first_one, last_value(o_orderkey) OVER w AS last_one, nth_value(o_orderkey, 2) OVER w AS second_one FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "win_running_rows": "SELECT event_id, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS BIGINT) AS cents FROM events",
    "win_range_frame": "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL 30 DAY PRECEDING AND CURRENT ROW) AS n FROM orders",
    "sort_topk": "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 25",
    "sort_group_topk": "SELECT lang, doc_id, n_chars FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS r FROM documents) t WHERE r <= 3",
    "sort_nulls": "SELECT id FROM (SELECT nullif(doc_id, 3) AS id FROM documents) t ORDER BY id DESC NULLS FIRST LIMIT 5",
    "set_union_all": "SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier",
    "set_union": "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier",
    "set_intersect": "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier",
    "set_except": "SELECT doc_id FROM documents EXCEPT SELECT doc_id FROM labels",
    "set_intersect_all": "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier",
    "set_except_all": "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier",
    "sub_scalar": "SELECT o_orderkey FROM orders WHERE CAST(o_totalprice AS DECIMAL(12,2)) > (SELECT CAST(max(o_totalprice) AS DECIMAL(12,2)) / 2 FROM orders)",
    "sub_exists": "SELECT p_partkey FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity = 50)",
    "sub_in": "SELECT s_suppkey FROM supplier WHERE s_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)",
    "cte_chain": "WITH a AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), b AS (SELECT n, count(*) AS customers FROM a GROUP BY n) SELECT n, customers FROM b WHERE customers > 1",
    "sample_quota": "SELECT lang, doc_id FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY md5(concat('42|', CAST(doc_id AS VARCHAR(20)))), doc_id) AS r FROM documents) t WHERE r <= 20",
    "sample_fractions": ("SELECT lang, doc_id FROM documents WHERE CAST(conv(substring(md5(concat('7|', CAST(doc_id AS STRING))), 1, 6), 16, 10) AS DOUBLE) / 16777216D < CASE lang WHEN 'en' THEN 0.1D ELSE 0.5D END", "SELECT lang, doc_id FROM documents WHERE CAST(('0x' || substr(md5(concat('7|', CAST(doc_id AS VARCHAR))), 1, 6)) AS INT) / 16777216.0::DOUBLE < CASE lang WHEN 'en' THEN 0.1::DOUBLE ELSE 0.5::DOUBLE END"),
    "fn_string": "SELECT p_partkey, upper(trim(p_brand)) AS b, lpad(CAST(p_size AS VARCHAR(5)), 4, '0') AS s, replace(p_type, ' ', '_') AS t, substring(p_name, 1, 5) AS n, CAST(levenshtein(p_brand, 'Brand#11') AS BIGINT) AS d FROM part",
    "fn_regex": ("SELECT doc_id, size(regexp_extract_all(text, '[^ \\\\t\\\\n\\\\r]+', 0)) AS n_words, regexp_replace(substring(text, 1, 40), '[^A-Za-z ]', '') AS head FROM documents", "SELECT doc_id, CAST(len(regexp_extract_all(text, '[^ \\t\\n\\r]+')) AS INT) AS n_words, regexp_replace(substring(text, 1, 40), '[^A-Za-z ]', '', 'g') AS head FROM documents"),
    "fn_number_format": ("SELECT c_custkey, format_number(CAST(floor(abs(c_acctbal)) AS BIGINT), 0) AS thousands FROM customer", "SELECT c_custkey, format('{:,}', CAST(floor(abs(c_acctbal)) AS BIGINT)) AS thousands FROM customer"),
    "fn_date": ("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS first_day, CAST(datediff(CAST(o_orderdate AS DATE), DATE '1992-01-01') AS BIGINT) AS days FROM orders", "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS first_day, datediff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders"),
    "fn_math": f"SELECT l_orderkey, l_linenumber, abs(l_quantity - 25) AS d, CAST(sign(l_quantity - 25) AS INT) AS s, greatest(l_discount, l_tax) AS g, least(l_discount, l_tax) AS k, {_R.format('sqrt(l_quantity)')} AS r FROM lineitem",
    "fn_array": ("SELECT vec_id, size(filter(embedding, x -> x > 0)) AS n_up, array_contains(array(label), 3) AS three, cast(element_at(embedding, 1) > element_at(embedding, -1) AS INT) AS falls FROM embeddings", "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS n_up, list_contains([label], 3) AS three, CAST(embedding[1] > embedding[-1] AS INT) AS falls FROM embeddings"),
    "fn_array_sets": (
        "SELECT doc_id, array_sort(array_distinct(a)) AS own, array_sort(array_intersect(a, b)) AS shared, array_sort(array_union(a, b)) AS together, array_sort(array_except(a, b)) AS rest, array_position(a, 2) AS at, array_max(a) AS hi, array_min(a) AS lo, size(array_remove(a, 0L)) AS n, arrays_overlap(a, b) AS meet FROM (SELECT doc_id, array(doc_id % 5, doc_id % 3, doc_id % 7) AS a, array(doc_id % 2, doc_id % 3) AS b FROM documents) t",
        "SELECT doc_id, list_sort(list_distinct(a)) AS own, list_sort(list_intersect(a, b)) AS shared, list_sort(list_distinct(list_concat(a, b))) AS together, list_sort(list_distinct(list_filter(a, lambda x: NOT list_contains(b, x)))) AS rest, CAST(coalesce(list_position(a, 2), 0) AS BIGINT) AS at, list_max(a) AS hi, list_min(a) AS lo, CAST(len(list_filter(a, lambda x: x <> 0)) AS INT) AS n, list_has_any(a, b) AS meet FROM (SELECT doc_id, [doc_id % 5, doc_id % 3, doc_id % 7] AS a, [doc_id % 2, doc_id % 3] AS b FROM documents) t",
    ),
    "fn_array_lambdas": (
        "SELECT doc_id, transform(a, (x, i) -> x * 10 + i) AS t, slice(a, 2, 2) AS s, reverse(a) AS r, flatten(array(a, b)) AS f, zip_with(a, b, (x, y) -> coalesce(x, 0) + coalesce(y, 0)) AS z, exists(a, x -> x = 4) AS any4, forall(a, x -> x < 7) AS under7, aggregate(a, 0L, (s, x) -> s * 3 + x, s -> s + 1) AS code, sequence(0, CAST(doc_id % 3 AS INT)) AS q FROM (SELECT doc_id, array(doc_id % 5, doc_id % 3, doc_id % 7) AS a, array(doc_id % 2, doc_id % 3) AS b FROM documents) t",
        "SELECT doc_id, list_transform(a, lambda x, i: x * 10 + i - 1) AS t, a[2:3] AS s, list_reverse(a) AS r, flatten([a, b]) AS f, list_transform(list_zip(a, b), lambda p: coalesce(p[1], 0) + coalesce(p[2], 0)) AS z, len(list_filter(a, lambda x: x = 4)) > 0 AS any4, len(list_filter(a, lambda x: x < 7)) = len(a) AS under7, list_reduce(list_concat([0], a), lambda s, x: s * 3 + x) + 1 AS code, range(0, CAST(doc_id % 3 AS INT) + 1)::INT[] AS q FROM (SELECT doc_id, [doc_id % 5, doc_id % 3, doc_id % 7] AS a, [doc_id % 2, doc_id % 3] AS b FROM documents) t",
    ),
    "fn_map_lambdas": (
        "SELECT doc_id, size(map_filter(m, (k, v) -> v > 1)) AS n, element_at(transform_values(m, (k, v) -> v * 2), 'a') AS a2, element_at(map_concat(m, map('c', doc_id % 7)), 'c') AS c, array_sort(map_keys(m)) AS keys, map_contains_key(m, 'z') AS z FROM (SELECT doc_id, map('a', doc_id % 5, 'b', doc_id % 3) AS m FROM documents) t",
        "SELECT doc_id, CAST((doc_id % 5 > 1)::INT + (doc_id % 3 > 1)::INT AS INT) AS n, (doc_id % 5) * 2 AS a2, doc_id % 7 AS c, ['a', 'b'] AS keys, false AS z FROM documents",
    ),
    "fn_map": ("SELECT conv_id, map_from_entries(array_sort(collect_list(struct(turn, role))))[0] AS first_role, count(*) AS n FROM conversations GROUP BY conv_id", "SELECT conv_id, max(role) FILTER (WHERE turn = 0) AS first_role, count(*) AS n FROM conversations GROUP BY conv_id"),
    "fn_json": ("SELECT event_id, get_json_object(props, '$.k') AS k FROM events", "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events"),
    "fn_json_struct": ("SELECT event_id, from_json(props, 'k INT').k AS k, to_json(named_struct('u', user_id, 't', event_type)) AS j FROM events", "SELECT event_id, TRY_CAST(json_extract_string(props, '$.k') AS INT) AS k, '{\"u\":' || user_id || ',\"t\":\"' || event_type || '\"}' AS j FROM events"),
    "fn_variant": ("SELECT event_id, try_variant_get(parse_json(props), '$.k', 'int') AS k, schema_of_variant(parse_json(props)) LIKE 'OBJECT%' AS is_object FROM events", "SELECT event_id, TRY_CAST(json_extract_string(props, '$.k') AS INT) AS k, json_type(props) = 'OBJECT' AS is_object FROM events"),
    "fn_html": ("SELECT page_id, regexp_count(html, '<a ') AS links, regexp_count(html, '<script') AS scripts, octet_length(html) AS bytes FROM pages", "SELECT page_id, CAST(len(regexp_extract_all(html, '<a ')) AS INT) AS links, CAST(len(regexp_extract_all(html, '<script')) AS INT) AS scripts, CAST(octet_length(encode(html)) AS INT) AS bytes FROM pages"),
    "fn_vector": (
        "SELECT vec_id, dot, norm2, floor(CAST(dot AS DOUBLE) / sqrt(CAST(norm2 AS DOUBLE)) / sqrt(CAST(norm2 AS DOUBLE)) * 1000 + 0.5) / 1000 AS cosine FROM (SELECT vec_id, aggregate(zip_with(v, reverse(v), (x, y) -> x * y), 0L, (s, x) -> s + x) AS dot, aggregate(v, 0L, (s, x) -> s + x * x) AS norm2 FROM (SELECT vec_id, transform(embedding, x -> CAST(floor(CAST(x AS DOUBLE) * 1000) AS BIGINT)) AS v FROM embeddings) t) u WHERE norm2 > 0",
        "SELECT vec_id, dot, norm2, floor(CAST(dot AS DOUBLE) / sqrt(CAST(norm2 AS DOUBLE)) / sqrt(CAST(norm2 AS DOUBLE)) * 1000 + 0.5) / 1000 AS cosine FROM (SELECT vec_id, CAST(list_sum(list_transform(list_zip(v, list_reverse(v)), lambda p: p[1] * p[2])) AS BIGINT) AS dot, CAST(list_sum(list_transform(v, lambda x: x * x)) AS BIGINT) AS norm2 FROM (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 1000) AS BIGINT)) AS v FROM embeddings) t) u WHERE norm2 > 0",
    ),
    "fn_centroid": ("SELECT label, i, CAST(sum(CAST(floor(CAST(x AS DOUBLE) * 1000) AS BIGINT)) AS BIGINT) AS total, count(*) AS n FROM (SELECT label, posexplode(embedding) AS (i, x) FROM embeddings) t GROUP BY label, i", "SELECT label, CAST(i AS INT) AS i, CAST(sum(CAST(floor(CAST(x AS DOUBLE) * 1000) AS BIGINT)) AS BIGINT) AS total, count(*) AS n FROM (SELECT label, unnest(range(0, len(embedding))) AS i, unnest(embedding) AS x FROM embeddings) t GROUP BY label, i"),
    "fn_null": "SELECT doc_id, coalesce(nullif(lang, 'en'), 'english') AS l, CASE WHEN nullif(source, 'src0') IS NULL THEN 1 ELSE 0 END AS z FROM documents",
    "conciseness_turns": ("SELECT role, count(*) AS n, CAST(sum(size(regexp_extract_all(text, '[^ \\\\t\\\\n\\\\r]+', 0))) AS BIGINT) AS words FROM conversations GROUP BY role", "SELECT role, count(*) AS n, CAST(sum(len(regexp_extract_all(text, '[^ \\t\\n\\r]+'))) AS BIGINT) AS words FROM conversations GROUP BY role"),
}


#: Sketches: their answers are approximate, so nothing stands beside them but the exact count in the same row.
SKETCHES: dict[str, str] = {
    "agg_sketch_distinct": "SELECT l_returnflag, approx_count_distinct(l_partkey, 0.02) AS about, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_returnflag",
    "agg_sketch_merged": "SELECT hll_sketch_estimate(hll_union_agg(s)) AS about, (SELECT count(DISTINCT l_partkey) FROM lineitem) AS parts FROM (SELECT l_returnflag, hll_sketch_agg(l_partkey, 14) AS s FROM lineitem GROUP BY l_returnflag) t",
    "agg_histogram_numeric": "SELECT inline(histogram_numeric(o_totalprice, 10)) FROM orders",
}


def spark_text(name: str) -> str:
    found = CATALOGUE.get(name) or SKETCHES[name]
    return found if isinstance(found, str) else found[0]


def duck_text(name: str) -> str:
    found = CATALOGUE[name]
    return found if isinstance(found, str) else found[1]


def run(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return query(spark, sf_dir, spark_text(name))
