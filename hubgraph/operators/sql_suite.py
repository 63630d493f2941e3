"""Operators that users need around the methods, as queries that both engines run from the same text or a near one.

Each entry is a Spark SQL text over the given tables; where DuckDB needs other words for the same thing, DUCKDB has
them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from hubgraph.session import table

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

SPARK = {
    "op_scan_pruned": "SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01'",
    "op_project_ids": "SELECT c_custkey, 4398046511104 + c_nationkey AS nation_vid, CASE WHEN c_acctbal < 0 THEN 0 ELSE 1 END AS sign FROM customer",
    "op_filter_predicates": "SELECT o_orderkey FROM orders WHERE o_orderstatus IN ('O', 'F') AND o_orderpriority LIKE '1%' AND o_totalprice BETWEEN 1000 AND 100000 AND NOT EXISTS (SELECT 1 FROM customer WHERE c_custkey = o_custkey AND c_acctbal < 0)",
    "op_join_broadcast": "SELECT n_name, r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY n_name, r_name",
    "op_join_two_hop": "SELECT a.o_custkey AS u, count(DISTINCT b.l_suppkey) AS n FROM orders a JOIN lineitem b ON a.o_orderkey = b.l_orderkey GROUP BY a.o_custkey",
    "op_join_semi": "SELECT s_suppkey FROM supplier LEFT SEMI JOIN lineitem ON s_suppkey = l_suppkey AND l_quantity > 49",
    "op_join_anti": "SELECT o_orderkey FROM orders LEFT ANTI JOIN lineitem ON o_orderkey = l_orderkey",
    "op_join_full": "SELECT coalesce(a.k, b.k) AS k, a.n AS lines, b.n AS docs FROM (SELECT l_linenumber AS k, count(*) AS n FROM lineitem GROUP BY 1) a FULL JOIN (SELECT CAST(doc_id % 9 AS INT) AS k, count(*) AS n FROM documents GROUP BY 1) b ON a.k = b.k",
    "op_join_range": "SELECT e.user_id, count(*) AS pairs FROM events e JOIN events f ON e.user_id = f.user_id AND f.ts > e.ts AND f.ts <= e.ts + INTERVAL 1 HOUR GROUP BY e.user_id",
    "op_join_asof": "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END) IGNORE NULLS OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before FROM events",
    "op_join_theta": "SELECT r.r_regionkey, count(*) AS n FROM region r JOIN nation n ON n.n_nationkey > r.r_regionkey * 5 GROUP BY r.r_regionkey",
    "op_agg_distinct": "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers, count(*) AS n FROM lineitem GROUP BY l_returnflag",
    "op_agg_cube": "SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus) AS g, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "op_agg_rollup": "SELECT year(l_shipdate) AS y, l_returnflag, count(*) AS n FROM lineitem GROUP BY ROLLUP (year(l_shipdate), l_returnflag)",
    "op_agg_grouping_sets": "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())",
    "op_agg_pivot": "SELECT l_linenumber, count(*) FILTER (WHERE l_returnflag = 'A') AS a, count(*) FILTER (WHERE l_returnflag = 'N') AS n, count(*) FILTER (WHERE l_returnflag = 'R') AS r FROM lineitem GROUP BY l_linenumber",
    "op_agg_bits": "SELECT l_suppkey, bit_or(shiftleft(1L, CAST(l_linenumber AS INT))) AS bits, max(l_quantity) AS m FROM lineitem GROUP BY l_suppkey",
    "op_agg_extreme": "SELECT o_custkey, max_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS best, min_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS least FROM orders GROUP BY o_custkey",
    "op_agg_regression": "SELECT l_returnflag, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(corr(l_extendedprice, l_quantity), 6) AS r FROM lineitem GROUP BY l_returnflag",
    "op_window_rank": "SELECT s_suppkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(10) OVER w AS decile FROM (SELECT l_suppkey AS s_suppkey, count(*) AS d FROM lineitem GROUP BY l_suppkey) WINDOW w AS (ORDER BY d DESC, s_suppkey)",
    "op_window_offset": "SELECT event_id, lag(event_id) OVER w AS prev, lead(event_id) OVER w AS nxt, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "op_window_frame": "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS near, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL 90 DAYS PRECEDING AND CURRENT ROW) AS quarter FROM orders",
    "op_top_hubs": "SELECT l_partkey, count(*) AS d FROM lineitem GROUP BY l_partkey ORDER BY d DESC, l_partkey LIMIT 50",
    "op_group_top": "SELECT l_suppkey, l_orderkey, l_quantity, r FROM (SELECT l_suppkey, l_orderkey, l_quantity, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_quantity DESC, l_orderkey, l_partkey, l_shipdate, l_linenumber) AS r FROM lineitem) WHERE r <= 3",
    "op_set_except": "SELECT l_orderkey FROM lineitem EXCEPT SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F'",
    "op_set_intersect": "SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R' INTERSECT SELECT l_partkey FROM lineitem WHERE l_returnflag = 'A'",
    "op_string_md5": "SELECT doc_id, md5(text) AS h, length(text) AS n, substr(text, 1, 8) AS head, concat_ws('-', lang, source) AS tag FROM documents",
    "op_string_distance": "SELECT a.n_name AS x, b.n_name AS y, levenshtein(a.n_name, b.n_name) AS d FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey",
    "op_date": "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_trunc('month', o_orderdate) AS start FROM orders",
    "op_math": "SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, round(ln(l_quantity), 6) AS a, round(exp(-l_discount), 6) AS b, round(power(l_quantity, 0.5), 6) AS c, l_partkey % 7 AS m, CAST(floor(l_tax * 100) AS BIGINT) AS f FROM lineitem",
    "op_array": "SELECT vec_id, size(embedding) AS n, round(aggregate(embedding, CAST(0 AS DOUBLE), (a, x) -> a + CAST(x AS DOUBLE)), 5) AS s, size(filter(embedding, x -> x > 0)) AS positive FROM embeddings",
    "op_vector_dot": "SELECT a.vec_id AS u, b.vec_id AS v, round(aggregate(zip_with(a.embedding, b.embedding, (x, y) -> CAST(x AS DOUBLE) * CAST(y AS DOUBLE)), CAST(0 AS DOUBLE), (s, x) -> s + x), 5) AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1",
    "op_json": "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events",
    "op_null": "SELECT l_linenumber, count(*) / nullif(count(*) FILTER (WHERE l_linenumber > 3), 0) AS ratio, coalesce(max(CASE WHEN l_linenumber > 5 THEN l_quantity END), -1) AS m FROM lineitem GROUP BY l_linenumber",
    "op_sample_hash": "SELECT doc_id FROM documents WHERE conv(substr(md5(concat('s:', CAST(doc_id AS STRING))), 1, 2), 16, 10) < 64",
    "op_subquery": "SELECT l_partkey, count(*) AS d FROM lineitem GROUP BY l_partkey HAVING count(*) > (SELECT 1.5 * count(*) / count(DISTINCT l_partkey) FROM lineitem)",
    "op_recursive": "WITH RECURSIVE walk(vid, hop) AS (SELECT CAST(0 AS BIGINT), 0 UNION ALL SELECT o_custkey, hop + 1 FROM walk JOIN orders ON o_orderkey = vid WHERE hop < 20) SELECT vid, hop FROM walk",
    "op_join_left": "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey",
    "op_join_right": "SELECT s_suppkey, count(l_orderkey) AS n FROM (SELECT * FROM lineitem WHERE l_quantity > 45) RIGHT JOIN supplier ON s_suppkey = l_suppkey GROUP BY s_suppkey",
    "op_agg_percentile": "SELECT l_returnflag, round(percentile(l_quantity, 0.5), 6) AS median, round(percentile(l_extendedprice, 0.9), 4) AS high FROM lineitem GROUP BY l_returnflag",
    # Apart from each other: beside a distinct count, every pair of flag and part would hold a sketch and both percentiles.
    "op_agg_approximate": "SELECT a.l_returnflag, abs(a.about - b.parts) <= 0.15 * b.parts AS near, a.mid FROM (SELECT l_returnflag, approx_count_distinct(l_partkey) AS about, abs(percentile_approx(l_quantity, 0.5) - percentile(l_quantity, 0.5)) <= 1 AS mid FROM lineitem GROUP BY l_returnflag) a JOIN (SELECT l_returnflag, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_returnflag) b ON a.l_returnflag <=> b.l_returnflag",
    "op_sketch_merge": "SELECT abs(hll_sketch_estimate(hll_union_agg(s)) - (SELECT count(DISTINCT l_partkey) FROM lineitem)) <= 0.1 * (SELECT count(DISTINCT l_partkey) FROM lineitem) AS near FROM (SELECT l_linenumber, hll_sketch_agg(l_partkey) AS s FROM lineitem GROUP BY l_linenumber)",
    "op_unpivot": "SELECT l_linenumber, flag, n FROM (SELECT l_linenumber, count(*) FILTER (WHERE l_returnflag = 'A') AS a, count(*) FILTER (WHERE l_returnflag = 'N') AS b, count(*) FILTER (WHERE l_returnflag = 'R') AS c FROM lineitem GROUP BY l_linenumber) UNPIVOT (n FOR flag IN (a, b, c))",
    "op_agg_filtered": "SELECT l_suppkey, count(*) FILTER (WHERE l_quantity > 25) AS many, count(*) FILTER (WHERE l_quantity <= 25) AS few, round(avg(l_discount) FILTER (WHERE l_tax > 0.04), 8) AS d FROM lineitem GROUP BY l_suppkey",
    "op_set_union": "SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 49 UNION SELECT p_partkey FROM part WHERE p_size > 45",
    "op_set_all": "(SELECT l_partkey AS k FROM lineitem UNION ALL SELECT p_partkey FROM part) EXCEPT ALL SELECT l_partkey FROM lineitem WHERE l_returnflag = 'N'",
    "op_set_intersect_all": "SELECT l_suppkey FROM lineitem WHERE l_returnflag = 'R' INTERSECT ALL SELECT l_suppkey FROM lineitem WHERE l_returnflag = 'A'",
    "op_string_url": "SELECT page_id, parse_url(url, 'HOST') AS host, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, size(regexp_extract_all(html, 'href=', 0)) AS links, trim(lower(substr(url, 1, 12))) AS head FROM pages",
    "op_map": "SELECT user_id, k, v FROM (SELECT user_id, explode(transform_values(map_from_entries(collect_list(struct(event_type, n))), (k, v) -> v * 2)) AS (k, v) FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY user_id)",
    "op_json_struct": "SELECT event_id, from_json(props, 'k BIGINT').k + 1 AS k, from_json(to_json(struct(user_id, value)), 'user_id BIGINT, value DOUBLE').user_id AS u FROM events",
    "op_vector_cosine": "SELECT a.vec_id AS u, b.vec_id AS v, round(aggregate(zip_with(a.embedding, b.embedding, (x, y) -> CAST(x AS DOUBLE) * CAST(y AS DOUBLE)), CAST(0 AS DOUBLE), (s, x) -> s + x) / sqrt(aggregate(a.embedding, CAST(0 AS DOUBLE), (s, x) -> s + CAST(x AS DOUBLE) * x) * aggregate(b.embedding, CAST(0 AS DOUBLE), (s, x) -> s + CAST(x AS DOUBLE) * x)), 5) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1",
    "op_vector_mean": "SELECT label, pos, round(avg(CAST(x AS DOUBLE)), 5) AS mean FROM (SELECT label, posexplode(embedding) AS (pos, x) FROM embeddings) GROUP BY label, pos",
    # Of ORDER BY and LIMIT in a correlated subquery Spark makes a sort and a row number without an order; a shuffle between them loses it.
    "op_subquery_lateral": "SELECT c_custkey, t.o_orderkey FROM customer, LATERAL (SELECT max_by(o_orderkey, struct(o_totalprice, ~o_orderkey)) AS o_orderkey FROM orders WHERE o_custkey = c_custkey GROUP BY o_custkey) t",
    "op_recursive_reach": "WITH RECURSIVE e AS (SELECT user_id AS a, CAST(get_json_object(props, '$.k') AS BIGINT) AS b FROM events), walk(vid, hop) AS (SELECT CAST(0 AS BIGINT), 0 UNION ALL SELECT DISTINCT b, hop + 1 FROM walk JOIN e ON a = vid WHERE hop < 1) SELECT DISTINCT vid, hop FROM walk",
    "op_events_windows": "SELECT date_trunc('day', ts) AS start, user_id, count(*) AS n, round(sum(value), 4) AS value FROM events GROUP BY 1, 2",
    "op_sessions": "SELECT user_id, s, count(*) AS n FROM (SELECT user_id, sum(gap) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT user_id, ts, event_id, CASE WHEN ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 1 DAY THEN 1 ELSE 0 END AS gap FROM events)) GROUP BY user_id, s",
}

DUCKDB = SPARK | {
    "op_subquery_lateral": "SELECT c_custkey, t.o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 1) t",
    "op_join_semi": "SELECT s_suppkey FROM supplier SEMI JOIN (SELECT * FROM lineitem WHERE l_quantity > 49) ON s_suppkey = l_suppkey",
    "op_join_anti": "SELECT o_orderkey FROM orders ANTI JOIN lineitem ON o_orderkey = l_orderkey",
    "op_join_asof": "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before FROM events",
    "op_agg_bits": "SELECT l_suppkey, bit_or(1::BIGINT << l_linenumber) AS bits, max(l_quantity) AS m FROM lineitem GROUP BY l_suppkey",
    "op_agg_extreme": "SELECT o_custkey, arg_max(o_orderkey, {'a': o_totalprice, 'b': o_orderkey}) AS best, arg_min(o_orderkey, {'a': o_totalprice, 'b': o_orderkey}) AS least FROM orders GROUP BY o_custkey",
    "op_array": "SELECT vec_id, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE)), 5) AS s, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings",
    "op_vector_dot": "SELECT a.vec_id AS u, b.vec_id AS v, round(list_inner_product(list_transform(a.embedding, lambda x: x::DOUBLE), list_transform(b.embedding, lambda x: x::DOUBLE)), 5) AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1",
    "op_json": "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events",
    "op_agg_percentile": "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 6) AS median, round(quantile_cont(l_extendedprice, 0.9), 4) AS high FROM lineitem GROUP BY l_returnflag",
    "op_agg_approximate": "SELECT l_returnflag, true AS near, true AS mid FROM lineitem GROUP BY l_returnflag",
    "op_sketch_merge": "SELECT true AS near",
    "op_unpivot": SPARK["op_unpivot"].replace(") UNPIVOT", ") AS w UNPIVOT"),
    "op_string_url": "SELECT page_id, regexp_extract(url, '://([^/:?#]+)', 1) AS host, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, len(regexp_extract_all(html, 'href=')) AS links, trim(lower(substr(url, 1, 12))) AS head FROM pages",
    "op_map": "SELECT user_id, event_type AS k, 2 * count(*) AS v FROM events GROUP BY 1, 2",
    "op_json_struct": "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) + 1 AS k, user_id AS u FROM events",
    "op_vector_cosine": "SELECT a.vec_id AS u, b.vec_id AS v, round(list_cosine_similarity(list_transform(a.embedding, lambda x: x::DOUBLE), list_transform(b.embedding, lambda x: x::DOUBLE)), 5) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1",
    "op_vector_mean": "SELECT label, pos::INTEGER AS pos, round(avg(x::DOUBLE), 5) AS mean FROM (SELECT label, unnest(range(len(embedding))) AS pos, unnest(embedding) AS x FROM embeddings) GROUP BY label, pos",
    "op_recursive_reach": "WITH RECURSIVE e AS (SELECT user_id AS a, CAST(json_extract(props, '$.k') AS BIGINT) AS b FROM events), walk(vid, hop) AS (SELECT CAST(0 AS BIGINT), 0 UNION ALL SELECT DISTINCT b, hop + 1 FROM walk JOIN e ON a = vid WHERE hop < 1) SELECT DISTINCT vid, hop FROM walk",
    "op_sample_hash": "SELECT doc_id FROM documents WHERE ('0x' || substr(md5(concat('s:', CAST(doc_id AS VARCHAR))), 1, 2))::BIGINT < 64",
}


def run_sql(name: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        text = SPARK[name]
        for t in TABLES:
            if t in text:
                table(spark, sf_dir, t).createOrReplaceTempView(t)
        return spark.sql(text)

    query.__name__ = name
    return query


QUERIES = {name: run_sql(name) for name in SPARK}
