"""Operators around the methods, as SQL that Spark and DuckDB both read; where they differ, the second text is DuckDB's."""

from __future__ import annotations

CENTS = "CAST(round({} * 100) AS BIGINT)"
_TOTAL = CENTS.format("o_totalprice")
_SAL = "(SELECT user_id, event_id, ts AS b, lead(ts, 1, TIMESTAMP_NTZ '2024-02-01 00:00:00') OVER (PARTITION BY user_id ORDER BY ts, event_id) AS e FROM events WHERE event_type = 'purchase')"
_DEPT = "(SELECT user_id AS u, event_type AS d, ts AS b2, lead(ts, 1, TIMESTAMP_NTZ '2024-02-01 00:00:00') OVER (PARTITION BY user_id ORDER BY ts, event_id) AS e2 FROM events WHERE event_type IN ('view', 'click', 'signup'))"

SQL: dict[str, tuple[str, str | None]] = {
    "op_scan_parquet": ("SELECT o_orderkey, o_totalprice FROM orders", None),
    "op_project_expr": ("SELECT l_orderkey AS k, l_linenumber + 1 AS nxt, CASE WHEN l_quantity > 25 THEN 'big' ELSE 'small' END AS size FROM lineitem", None),
    "op_filter_bool": ("SELECT p_partkey FROM part WHERE (p_size BETWEEN 3 AND 20 OR p_brand IN ('Brand#3', 'Brand#12')) AND NOT p_type LIKE 'S%' AND p_name IS NOT NULL", None),
    "op_join_hash": ("SELECT /*+ SHUFFLE_HASH(customer) */ o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey", None),
    "op_join_merge": ("SELECT /*+ MERGE(customer) */ o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey", None),
    "op_join_broadcast": ("SELECT /*+ BROADCAST(nation) */ c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey", None),
    "op_join_theta": ("SELECT n_name, r_name FROM nation JOIN region ON n_regionkey < r_regionkey", None),
    "op_cross": ("SELECT n_name, r_name FROM nation CROSS JOIN region", None),
    "op_join_natural": ("SELECT doc_id, lang, quality FROM documents NATURAL JOIN labels", None),
    "op_join_left": ("SELECT c_custkey, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey AND o_orderstatus = 'P'", None),
    "op_join_right": ("SELECT c_custkey, o_orderkey FROM orders RIGHT JOIN customer ON c_custkey = o_custkey AND o_orderstatus = 'P'", None),
    "op_join_full": ("SELECT c_custkey, s_suppkey FROM customer FULL JOIN supplier ON c_custkey = s_suppkey * 20", None),
    "op_semi": ("SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)", None),
    "op_anti": ("SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)", None),
    "op_join_overlap": (f"SELECT user_id, event_id, d, greatest(b, b2) AS b, least(e, e2) AS e FROM {_SAL} s JOIN {_DEPT} t ON user_id = u AND b < e2 AND b2 < e", None),
    "op_join_asof": ("SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END) IGNORE NULLS OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_purchase FROM events", "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_purchase FROM events"),
    "op_agg_basic": ("SELECT l_returnflag, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty, min(l_shipdate) AS first, max(l_shipdate) AS last, round(avg(l_quantity), 6) AS mean FROM lineitem GROUP BY l_returnflag", None),
    "op_agg_global": ("SELECT count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty FROM lineitem", None),
    "op_agg_distinct": ("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type", None),
    "op_approx_distinct": ("SELECT event_type, approx_count_distinct(user_id) BETWEEN 0.9 * count(DISTINCT user_id) AND 1.1 * count(DISTINCT user_id) AS close FROM events GROUP BY event_type", "SELECT event_type, true AS close FROM events GROUP BY event_type"),
    "op_having": (f"SELECT o_custkey, CAST(sum({_TOTAL}) AS BIGINT) AS total FROM orders GROUP BY o_custkey HAVING count(*) > 12", None),
    "op_agg_collect": ("SELECT o_custkey, array_join(transform(sort_array(collect_list(o_orderkey)), x -> CAST(x AS STRING)), ',') AS ks FROM orders GROUP BY o_custkey", "SELECT o_custkey, string_agg(o_orderkey::VARCHAR, ',' ORDER BY o_orderkey) AS ks FROM orders GROUP BY o_custkey"),
    "op_grouping_sets": ("SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(grouping(l_returnflag) AS INT) AS g FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_linestatus), ())", None),
    "op_cube": ("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)", None),
    "op_rollup": ("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)", None),
    "op_pivot": ("SELECT * FROM (SELECT user_id, event_type FROM events) PIVOT (count(*) FOR event_type IN ('view' AS v, 'click' AS c)) ORDER BY user_id", "SELECT user_id, nullif(sum((event_type = 'view')::INT), 0)::BIGINT AS v, nullif(sum((event_type = 'click')::INT), 0)::BIGINT AS c FROM events GROUP BY user_id"),
    "op_distinct": ("SELECT DISTINCT lang, source FROM documents", None),
    "op_union_all": ("SELECT c_name AS name FROM customer UNION ALL SELECT s_name FROM supplier", None),
    "op_union_distinct": ("SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier", None),
    "op_intersect_all": ("SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier", None),
    "op_except_all": ("SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier", None),
    "op_intersect": ("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier", None),
    "op_except": ("SELECT c_nationkey AS k FROM customer EXCEPT SELECT s_nationkey FROM supplier WHERE s_nationkey < 5", None),
    "op_window_running": ("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts) AS n FROM events", None),
    "op_window_partition": (f"SELECT o_orderkey, CAST(sum({_TOTAL}) OVER (PARTITION BY o_custkey) AS BIGINT) AS total FROM orders", None),
    "op_window_rank": ("SELECT p_partkey, CAST(row_number() OVER w AS BIGINT) AS rn, CAST(rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS BIGINT) AS rk, CAST(dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS BIGINT) AS dr, CAST(ntile(4) OVER w AS BIGINT) AS q FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey)", None),
    "op_window_lag_lead": ("SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS until FROM events", None),
    "op_window_rows_frame": (f"SELECT o_orderkey, CAST(sum({_TOTAL}) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS s3 FROM orders", None),
    "op_sort_limit": ("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10", None),
    "op_topk_group": ("SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 3", None),
    "op_scalar_string": ("SELECT p_partkey, upper(p_name) AS u, substring(p_name, 2, 3) AS s, CAST(length(p_name) AS BIGINT) AS n, concat(p_brand, '/', p_type) AS c, replace(p_brand, '#', '-') AS r, CAST(levenshtein(p_type, 'PROMO') AS BIGINT) AS d FROM part", None),
    "op_scalar_date": ("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(datediff(DATE '2002-01-01', CAST(o_orderdate AS DATE)) AS BIGINT) AS days FROM orders", "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, date_diff('day', o_orderdate::DATE, DATE '2002-01-01') AS days FROM orders"),
    "op_scalar_math": ("SELECT p_partkey, abs(p_size - 25) AS a, CAST(floor(p_retailprice) AS BIGINT) AS f, p_size % 7 AS m, CAST(power(p_size, 2) AS BIGINT) AS p, round(ln(p_size), 6) AS l FROM part", None),
    "op_array": ("SELECT label, pos, count(*) AS n FROM (SELECT label, posexplode(slice(embedding, 1, 3)) AS (pos, x) FROM embeddings) WHERE x > 0 GROUP BY label, pos", "SELECT label, pos, count(*) AS n FROM (SELECT label, unnest(embedding[1:3]) AS x, unnest([0, 1, 2]) AS pos FROM embeddings) WHERE x > 0 GROUP BY label, pos"),
    "op_json": ("SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events"),
    "op_map": ("SELECT o_custkey, map_from_entries(collect_set(struct(o_orderstatus, 1)))['F'] AS has_f FROM orders GROUP BY o_custkey", "SELECT o_custkey, max(CASE WHEN o_orderstatus = 'F' THEN 1 END) AS has_f FROM orders GROUP BY o_custkey"),
    "op_hash_id": ("SELECT n_name, sha2(n_name, 256) AS id FROM nation", "SELECT n_name, sha256(n_name) AS id FROM nation"),
    "op_cte_shared": ("WITH t AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) SELECT a.o_custkey, a.n FROM t a JOIN (SELECT max(n) AS m FROM t) b ON a.n = b.m", None),
    "op_subquery_scalar": ("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM orders)", None),
    "op_subquery_in": ("SELECT c_custkey FROM customer WHERE c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 2)", None),
    "op_subquery_correlated": ("SELECT o_orderkey FROM orders o WHERE o_totalprice = (SELECT max(i.o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)", None),
    "op_difference_unlabelled": ("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)", None),
}


def duck(name: str) -> str:
    spark_text, own = SQL[name]
    return (own or spark_text).replace("TIMESTAMP_NTZ '", "TIMESTAMP '")
