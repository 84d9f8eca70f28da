"""Relational operations around the methods, as SQL that Spark and other engines run alike."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..sources.tables import TABLES, views

#: name -> SQL, or (Spark SQL, other engines' SQL) where the dialects differ.
SQL: dict[str, str | tuple[str, str]] = {
    "scan_pruned_orders": "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderstatus = 'F' AND o_totalprice > 100000",
    "proj_edges": "SELECT DISTINCT l_orderkey * 16 AS v0, (l_suppkey * 8 + 2) * 2 AS v1 FROM lineitem",
    "filter_text_like": "SELECT doc_id FROM documents WHERE lower(text) LIKE '%license%' OR lang IN ('de', 'fr')",
    "filter_active": "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 50000 AND 60000 AND o_orderpriority IS NOT NULL",
    "join_inner_returns": "SELECT o_custkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' GROUP BY o_custkey",
    "join_broadcast_nation": ("SELECT /*+ BROADCAST(nation) */ n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"),
    "join_sortmerge_lines": ("SELECT /*+ MERGE(orders) */ o_orderstatus, CAST(sum(l_linenumber) AS BIGINT) AS s FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus", "SELECT o_orderstatus, CAST(sum(l_linenumber) AS BIGINT) AS s FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus"),
    "join_left_labels": "SELECT d.doc_id, l.quality, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id",
    "join_full_assign": "SELECT coalesce(a.k, b.k) AS k, a.n AS n_orders, b.n AS n_suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_acctbal > 0 GROUP BY c_nationkey) a FULL OUTER JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier WHERE s_acctbal > 0 GROUP BY s_nationkey) b ON a.k = b.k",
    "semi_orders_with_lines": "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)",
    "anti_unlabelled_docs": "SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)",
    "cross_states": "SELECT a.x, b.y, CASE WHEN a.x = b.y THEN 0.7 ELSE CAST(0 AS DOUBLE) END AS logpsi FROM (SELECT 0 AS x UNION ALL SELECT 1) a CROSS JOIN (SELECT 0 AS y UNION ALL SELECT 1) b",
    "theta_price_band": "SELECT b.band, count(*) AS n FROM part JOIN (SELECT 0 AS band, 0 AS lo, 1000 AS hi UNION ALL SELECT 1, 1000, 1500 UNION ALL SELECT 2, 1500, 100000) b ON p_retailprice >= b.lo AND p_retailprice < b.hi GROUP BY b.band",
    "range_grid_neighbours": "WITH p AS (SELECT DISTINCT CAST(l_partkey % 100 AS INT) AS c, l_linenumber AS r FROM lineitem) SELECT a.r, a.c, count(*) AS n FROM p a JOIN p b ON b.r BETWEEN a.r - 1 AND a.r + 1 AND b.c BETWEEN a.c - 1 AND a.c + 1 GROUP BY a.r, a.c",
    "interval_event_sessions": "WITH s AS (SELECT user_id, min(ts) AS lo, max(ts) AS hi FROM events WHERE event_type = 'login' GROUP BY user_id) SELECT e.user_id, count(*) AS n FROM events e JOIN s ON e.user_id = s.user_id AND e.ts BETWEEN s.lo AND s.hi GROUP BY e.user_id",
    "asof_error_before_purchase": (
        "SELECT event_id, last_error FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'error' THEN event_id END, true) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_error FROM events) t WHERE event_type = 'purchase'",
        "SELECT event_id, last_error FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'error' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_error FROM events) t WHERE event_type = 'purchase'",
    ),
    "agg_work_by_block": "SELECT l_suppkey % 8 AS block, count(*) AS n, min(l_quantity) AS lo, max(l_quantity) AS hi, round(avg(l_quantity), 6) AS mean, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem GROUP BY l_suppkey % 8",
    "agg_logsumexp": "WITH m AS (SELECT l_suppkey, max(l_discount) AS top FROM lineitem GROUP BY l_suppkey) SELECT l.l_suppkey, round(max(m.top) + ln(sum(exp(l.l_discount - m.top))), 6) AS lse FROM lineitem l JOIN m ON l.l_suppkey = m.l_suppkey GROUP BY l.l_suppkey",
    "agg_distinct_neighbours": "SELECT l_suppkey, count(DISTINCT l_orderkey) AS orders, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_suppkey",
    "agg_decimal_revenue": ("SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS DOUBLE) AS revenue FROM lineitem GROUP BY l_returnflag", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS DOUBLE) AS revenue FROM lineitem GROUP BY l_returnflag"),
    "cube_status_priority": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)",
    "rollup_region_nation": "SELECT n_regionkey, n_nationkey, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_nationkey)",
    "gsets_type_flag": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    "win_rank_residual": "SELECT c_custkey, rank() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC) AS rk, dense_rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS dr, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rn, round(percent_rank() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal), 6) AS pr, round(cume_dist() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal), 6) AS cd FROM customer",
    "win_ntile_work": "SELECT s_suppkey, ntile(8) OVER (ORDER BY s_suppkey) AS block FROM supplier",
    "win_chain_edges": "SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts) AS next_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts) AS prev_id, first_value(event_id) OVER (PARTITION BY user_id ORDER BY ts) AS first_id FROM events",
    "win_prefix_work": "SELECT s_suppkey, CAST(sum(s_nationkey) OVER (ORDER BY s_suppkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS upto FROM supplier",
    "win_moving_avg": "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS mean3 FROM events",
    "win_range_hours": ("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL '6' HOUR PRECEDING AND CURRENT ROW) AS n FROM events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 6 HOUR PRECEDING AND CURRENT ROW) AS n FROM events"),
    "topk_supplier_degree": "SELECT l_suppkey, count(DISTINCT l_orderkey) AS degree FROM lineitem GROUP BY l_suppkey ORDER BY degree DESC, l_suppkey LIMIT 10",
    "topk_per_block": "SELECT block, c_custkey FROM (SELECT c_custkey % 8 AS block, c_custkey, row_number() OVER (PARTITION BY c_custkey % 8 ORDER BY c_acctbal DESC, c_custkey) AS k FROM customer) t WHERE k <= 3",
    "set_union_edges": "SELECT l_orderkey AS a, l_suppkey AS b FROM lineitem UNION SELECT o_orderkey, o_custkey FROM orders",
    "set_intersect_keys": "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier",
    "set_except_keys": "SELECT o_orderkey AS k FROM orders EXCEPT SELECT l_orderkey FROM lineitem",
    "sub_above_avg_degree": "WITH d AS (SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey) SELECT l_suppkey, n FROM d WHERE n > (SELECT avg(n) FROM d) AND l_suppkey IN (SELECT s_suppkey FROM supplier)",
    "cte_bfs_hops": "WITH RECURSIVE hop(v, h) AS (SELECT CAST(0 AS BIGINT) AS v, 0 AS h UNION ALL SELECT 2 * v + d, h + 1 FROM hop CROSS JOIN (SELECT 1 AS d UNION ALL SELECT 2) c WHERE h < 5) SELECT v, h FROM hop",
    "date_ship_week": ("SELECT CAST(floor(datediff(l_shipdate, DATE '1995-01-01') / 7) AS INT) AS week, count(*) AS n FROM lineitem GROUP BY 1", "SELECT CAST(floor(date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) / 7) AS INT) AS week, count(*) AS n FROM lineitem GROUP BY 1"),
    "date_interval_shift": "SELECT o_orderkey, o_orderdate + INTERVAL '30' DAY AS due FROM orders WHERE o_orderpriority = '1-URGENT'",
    "date_gap_sessions": ("SELECT event_id FROM (SELECT event_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events) t WHERE p + INTERVAL '12' HOUR < ts", "SELECT event_id FROM (SELECT event_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events) t WHERE p + INTERVAL 12 HOUR < ts"),
    "str_page_host": "SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS host FROM pages",
    "str_doc_prefix_block": "SELECT md5(lower(substr(text, 1, 24))) AS block, count(*) AS n FROM documents GROUP BY 1",
    "math_gaussian_noise": (
        "SELECT s_suppkey, round(sqrt(-2 * ln(CAST(conv(substr(md5(concat('a|', s_suppkey)), 1, 8), 16, 10) AS DOUBLE) / 4294967296 + 1e-12)) * cos(2 * pi() * CAST(conv(substr(md5(concat('b|', s_suppkey)), 1, 8), 16, 10) AS DOUBLE) / 4294967296), 6) AS z FROM supplier",
        "SELECT s_suppkey, round(sqrt(-2 * ln(CAST(('0x' || substr(md5('a|' || s_suppkey), 1, 8))::BIGINT AS DOUBLE) / 4294967296 + 1e-12)) * cos(2 * pi() * CAST(('0x' || substr(md5('b|' || s_suppkey), 1, 8))::BIGINT AS DOUBLE) / 4294967296), 6) AS z FROM supplier",
    ),
    "arr_embedding_norm": (
        "SELECT vec_id, round(sqrt(aggregate(embedding, CAST(0 AS DOUBLE), (a, x) -> a + CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 5) AS norm FROM embeddings",
        "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 5) AS norm FROM embeddings",
    ),
    "json_event_k": ("SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS k FROM events", "SELECT event_id, CAST(json_extract(props, '$.k') AS INT) AS k FROM events"),
    "sample_md5_edges": "SELECT l_orderkey, l_suppkey, count(*) AS n FROM lineitem WHERE substr(md5(concat(CAST(l_orderkey AS STRING), '|', CAST(l_suppkey AS STRING))), 1, 1) IN ('0', '1') GROUP BY l_orderkey, l_suppkey",
    "pivot_beliefs": ("SELECT * FROM (SELECT user_id, event_type FROM events) PIVOT (count(*) FOR event_type IN ('click' AS click, 'error' AS error, 'login' AS login))", "SELECT user_id, nullif(count(*) FILTER (event_type = 'click'), 0) AS click, nullif(count(*) FILTER (event_type = 'error'), 0) AS error, nullif(count(*) FILTER (event_type = 'login'), 0) AS login FROM events GROUP BY user_id"),
    "unpivot_states": ("SELECT doc_id, label, value FROM labels UNPIVOT (value FOR label IN (quality, toxic))", "SELECT doc_id, 'quality' AS label, quality AS value FROM labels WHERE quality IS NOT NULL UNION ALL SELECT doc_id, 'toxic', toxic FROM labels WHERE toxic IS NOT NULL"),
    "map_round_metrics": ("SELECT user_id, map_from_entries(collect_list(struct(event_type, n)))['click'] AS clicks FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type) t GROUP BY user_id", "SELECT user_id, nullif(count(*) FILTER (event_type = 'click'), 0) AS clicks FROM events GROUP BY user_id"),
    "queue_top_per_block": ("SELECT c_nationkey AS block, max_by(c_custkey, struct(c_acctbal, -c_custkey)) AS vid FROM customer GROUP BY c_nationkey", "SELECT block, vid FROM (SELECT c_nationkey AS block, c_custkey AS vid, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS k FROM customer) t WHERE k = 1"),
}


def _sql(text: str) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        views(spark, sf_dir, *[t for t in TABLES if t in text])
        return spark.sql(text)

    return query


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: _sql(s if isinstance(s, str) else s[0]) for name, s in SQL.items()}


def oracle_sql() -> dict[str, str]:
    return {name: s if isinstance(s, str) else s[1] for name, s in SQL.items()}
