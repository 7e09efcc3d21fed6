"""The joins, aggregates, windows and set operations around the methods, on the workloads' points.

Each entry is SQL that Spark and DuckDB both run; Spark plans it declaratively.
"""

from __future__ import annotations

QUERIES = {
    "relational_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n, max(l_quantity) AS top FROM {lineitem} GROUP BY CUBE (l_returnflag, l_linestatus)",
    "relational_rollup": "SELECT r_name, n_name, count(*) AS n FROM {customer} JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)",
    "relational_grouping_sets": "SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM {orders} GROUP BY GROUPING SETS ((o_orderpriority), (o_orderstatus), ())",
    "relational_semi": "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_totalprice > 200000)",
    "relational_anti": "SELECT c_custkey FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey)",
    "relational_except": "SELECT p_partkey FROM {part} EXCEPT SELECT l_partkey FROM {lineitem} WHERE l_quantity > 45",
    "relational_intersect": "SELECT c_nationkey AS nation FROM {customer} INTERSECT SELECT s_nationkey FROM {supplier}",
    "relational_union": "SELECT 'customer' AS kind, count(*) AS n FROM {customer} UNION ALL SELECT 'supplier', count(*) FROM {supplier}",
    "relational_topk": "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 25",
    "relational_quota_rank": "SELECT c_custkey, c_mktsegment, CAST(r AS BIGINT) AS r FROM (SELECT c_custkey, c_mktsegment, row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_custkey) AS r FROM {customer}) x WHERE r <= 3",
    "relational_running_min": "SELECT event_id, min(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS low FROM {events}",
    "relational_pivot": "SELECT l_returnflag, " + ", ".join(f"CAST(sum(CASE WHEN p_type = '{t}' THEN 1 ELSE 0 END) AS BIGINT) AS {t.lower()}" for t in ("ECONOMY", "STANDARD", "PROMO")) + " FROM {lineitem} JOIN {part} ON l_partkey = p_partkey GROUP BY l_returnflag",
    "relational_distinct_positions": "SELECT count(*) AS n, count(DISTINCT p_size) AS sizes FROM {part}",
    "relational_quotas": "SELECT label, count(*) AS n, CAST(floor(count(*) * 20.0 / sum(count(*)) OVER ()) AS BIGINT) AS quota FROM {embeddings} GROUP BY label",
}

#: Forms that differ by engine: (Spark, DuckDB).
PAIRS = {
    # a band join meets on buckets as wide as the band; the wanted range decides
    "relational_band": (
        "SELECT s_suppkey, count(*) AS n FROM (SELECT s_suppkey, s_acctbal, floor(s_acctbal / 20) + o AS b FROM {supplier} CROSS JOIN (VALUES (-1), (0), (1)) t(o)) s JOIN (SELECT c_acctbal, floor(c_acctbal / 20) AS b FROM {customer}) c ON c.b = s.b AND c_acctbal BETWEEN s_acctbal - 10 AND s_acctbal + 10 GROUP BY s_suppkey",
        "SELECT s.s_suppkey, count(*) AS n FROM supplier s JOIN customer c ON c.c_acctbal BETWEEN s.s_acctbal - 10 AND s.s_acctbal + 10 GROUP BY s.s_suppkey",
    ),
    "relational_asof": (
        "SELECT event_id, seen FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END) IGNORE NULLS OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS seen FROM {events}) x WHERE event_type = 'purchase'",
        "SELECT p.event_id, max(v.event_id) AS seen FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND (v.ts < p.ts OR v.ts = p.ts AND v.event_id < p.event_id) WHERE p.event_type = 'purchase' GROUP BY p.event_id",
    ),
    "relational_sample": (
        "SELECT c_custkey, c_mktsegment FROM {customer} WHERE conv(substr(md5(CAST(c_custkey AS STRING)), 1, 6), 16, 10) % 100 < CASE c_mktsegment WHEN 'BUILDING' THEN 20 ELSE 5 END",
        "SELECT c_custkey, c_mktsegment FROM customer WHERE CAST('0x' || substr(md5(CAST(c_custkey AS VARCHAR)), 1, 6) AS BIGINT) % 100 < CASE c_mktsegment WHEN 'BUILDING' THEN 20 ELSE 5 END",
    ),
    "relational_json": ("SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM {events}", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events"),
    "relational_map": ("SELECT c_custkey, element_at(map(0, 2, 1, 3), c_nationkey % 2) AS cap FROM {customer}", "SELECT c_custkey, CASE c_nationkey % 2 WHEN 0 THEN 2 ELSE 3 END AS cap FROM customer"),
    "relational_session": (
        "SELECT user_id, count(*) AS n FROM {events} GROUP BY user_id, session_window(ts, '2 hours')",
        "SELECT user_id, count(*) AS n FROM (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 2 HOURS THEN 0 ELSE 1 END AS fresh FROM events) a) b GROUP BY user_id, s",
    ),
    "relational_window_counts": ("SELECT CAST(CAST(ts AS DATE) AS STRING) AS day, event_type, count(*) AS n FROM {events} GROUP BY 1, 2", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2"),
}
