"""Operators around the methods: feature building, cells and candidates, scoring and reporting.

Each is one declarative statement that Spark and DuckDB both run; `{k}` stands for the JSON field access of the engine.
"""

from __future__ import annotations

B = "CAST({} AS BIGINT)".format
D = "CAST({} AS DOUBLE)".format
CELL = "CAST(floor(l_quantity / 5) AS INT)"

STATEMENTS: dict[str, str] = {
    "src_parquet_pruned": "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice > 400000",
    "proj_party_view": "SELECT o_orderkey AS inst_id, CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END AS status, CAST(substr(o_orderpriority, 1, 1) AS INT) AS prio FROM orders",
    "filter_between_in": "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 12 AND l_returnflag IN ('A', 'R')",
    "filter_like_regex": "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%a%' AND length(p_brand) > 7",
    "null_guard": f"SELECT c_custkey, coalesce(n, 0) AS n, coalesce(s / nullif(n, 0), {D('0')}) AS mean FROM customer LEFT JOIN (SELECT o_custkey, {B('count(*)')} AS n, round(sum(o_totalprice), 2) AS s FROM orders WHERE o_orderstatus = 'P' GROUP BY o_custkey) x ON c_custkey = o_custkey",
    "hash_split": "SELECT o_orderkey, substr(md5(CAST(o_orderkey AS STRING)), 1, 1) < 'c' AS in_train FROM orders",
    "join_inner_align": f"SELECT o_orderkey, o_totalprice, n FROM orders JOIN (SELECT l_orderkey, {B('count(*)')} AS n FROM lineitem GROUP BY l_orderkey) x ON o_orderkey = l_orderkey",
    "join_broadcast_dict": f"SELECT r_name, {B('count(*)')} AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name",
    "join_left_cells": f"WITH a AS (SELECT {CELL} AS bin, {B('count(*)')} AS n FROM lineitem GROUP BY 1), b AS (SELECT {CELL} AS bin, {B('count(*)')} AS m FROM lineitem WHERE l_tax > 0.05 AND l_quantity < 40 GROUP BY 1) SELECT a.bin, n - coalesce(m, 0) AS rest FROM a LEFT JOIN b ON a.bin = b.bin",
    "join_full_outer": f"SELECT {B('sum(CASE WHEN l_orderkey IS NULL THEN 1 ELSE 0 END)')} AS only_left, {B('sum(CASE WHEN o_orderkey IS NULL THEN 1 ELSE 0 END)')} AS only_right, {B('count(*)')} AS n FROM orders FULL OUTER JOIN (SELECT DISTINCT l_orderkey FROM lineitem) x ON o_orderkey = l_orderkey",
    "join_semi_survivors": "SELECT o_orderkey FROM orders LEFT SEMI JOIN (SELECT l_orderkey FROM lineitem WHERE l_quantity >= 49) x ON o_orderkey = l_orderkey",
    "join_anti_lost": "SELECT o_orderkey FROM orders LEFT ANTI JOIN lineitem ON o_orderkey = l_orderkey",
    "join_cross_grid": "SELECT r_regionkey AS node, f.id AS fid FROM region CROSS JOIN (SELECT DISTINCT n_regionkey * 10 AS id FROM nation) f",
    "join_range_bins": f"WITH e AS (SELECT n_nationkey AS bin, n_nationkey * 20000 AS lo, (n_nationkey + 1) * 20000 AS hi FROM nation) SELECT bin, {B('count(*)')} AS n FROM orders JOIN e ON o_totalprice >= lo AND o_totalprice < hi GROUP BY bin",
    "join_asof_event": "SELECT event_id, user_id, max(CASE WHEN event_type = 'view' THEN event_id END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_view FROM events",
    "join_interval": f"SELECT {B('count(*)')} AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
    "join_nullsafe": f"SELECT {B('count(*)')} AS n FROM (SELECT nullif(n_regionkey, 2) AS k FROM nation) a JOIN (SELECT nullif(r_regionkey, 2) AS k FROM region) b ON a.k IS NOT DISTINCT FROM b.k",
    "agg_hash_partial": f"SELECT l_linenumber AS fid, {CELL} AS bin, {B('count(*)')} AS n FROM lineitem GROUP BY 1, 2",
    "agg_distinct": f"SELECT l_partkey, {B('count(DISTINCT l_suppkey)')} AS suppliers FROM lineitem GROUP BY l_partkey",
    "agg_rollup_cells": f"SELECT l_returnflag, l_linestatus, {B('count(*)')} AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "agg_cube": f"SELECT l_returnflag, l_linestatus, {B('count(*)')} AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "agg_grouping_sets": f"SELECT l_returnflag, l_linenumber, {B('count(*)')} AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linenumber), ())",
    "agg_argmax": "SELECT o_custkey, max_by(o_orderkey, o_totalprice) AS best FROM orders GROUP BY o_custkey",
    "agg_stats": "SELECT l_returnflag, round(avg(l_quantity), 6) AS mean, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_discount), 6) AS c FROM lineitem GROUP BY l_returnflag",
    "agg_having": f"SELECT o_custkey, {B('count(*)')} AS n FROM orders GROUP BY o_custkey HAVING count(*) >= 15",
    "win_rank_family": f"SELECT p_partkey, {B('row_number() OVER w')} AS rn, {B('rank() OVER v')} AS rk, {B('dense_rank() OVER v')} AS dr, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd, {B('ntile(4) OVER w')} AS nt FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey), v AS (PARTITION BY p_brand ORDER BY p_size)",
    "win_running_sum": f"SELECT bin, {B('sum(n) OVER (ORDER BY bin ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)')} AS upto FROM (SELECT {CELL} AS bin, count(*) AS n FROM lineitem GROUP BY 1) x",
    "win_range_frame": f"SELECT event_id, {B('count(*) OVER (PARTITION BY user_id ORDER BY dayofyear(ts) RANGE BETWEEN 6 PRECEDING AND CURRENT ROW)')} AS week FROM events",
    "win_lag_lead": "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "win_first_last_nth": "SELECT event_id, first_value(event_id) OVER w AS f, last_value(event_id) OVER w AS l, nth_value(event_id, 2) OVER w AS s FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "sort_total": "SELECT s_suppkey, s_acctbal FROM supplier ORDER BY s_acctbal DESC, s_suppkey",
    "topk_splits": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10",
    "topk_per_node": "SELECT o_orderpriority, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) x WHERE rn <= 3",
    "set_union_infos": "SELECT c_custkey AS id FROM customer WHERE c_acctbal > 9000 UNION ALL SELECT s_suppkey FROM supplier WHERE s_acctbal > 9000",
    "set_intersect_ids": "SELECT o_orderkey AS id FROM orders INTERSECT SELECT l_orderkey FROM lineitem",
    "set_except_ids": "SELECT c_custkey AS id FROM customer EXCEPT SELECT o_custkey FROM orders",
    "set_distinct": "SELECT DISTINCT p_brand, p_type FROM part",
    "fn_math": "SELECT o_orderkey, CAST(floor(o_totalprice / 1000) AS BIGINT) AS f, round(power(o_totalprice / 1000, 2), 4) AS p, round(exp(-o_totalprice / 100000), 6) AS e, round(ln(o_totalprice), 6) AS l, round(sqrt(o_totalprice), 6) AS s, greatest(o_totalprice, 1000) AS g FROM orders",
    "fn_bits": "SELECT c_custkey, bit_count(c_custkey) AS ones, (c_custkey & 255) AS low FROM customer",
    "fn_decimal": "SELECT l_returnflag, CAST(sum(CAST(floor(l_quantity * CAST(1073741824.0 AS DOUBLE)) AS DECIMAL(38, 0))) AS STRING) AS s FROM lineitem GROUP BY l_returnflag",
    "fn_string": f"SELECT p_partkey, {B('length(trim(p_name))')} AS n, substr(p_brand, 7, 2) AS no, md5(p_name) AS h, upper(p_type) AS t FROM part",
    "fn_date": f"SELECT o_orderkey, {B('year(o_orderdate)')} AS y, {B('dayofyear(o_orderdate)')} AS d, {B('month(o_orderdate)')} AS m, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS STRING) AS start FROM orders",
    "fn_json": f"SELECT event_id, {B('{k}')} AS k FROM events",
}

#: Statements whose text differs in one function between the engines.
DUCK = {
    "fn_json": {"{k}": "json_extract_string(props, '$.k')"},
    "fn_decimal": {"AS STRING": "AS VARCHAR"},
    "fn_date": {"AS STRING": "AS VARCHAR"},
    "hash_split": {"AS STRING": "AS VARCHAR"},
    "join_semi_survivors": {"LEFT SEMI JOIN": "SEMI JOIN"},
    "join_anti_lost": {"LEFT ANTI JOIN": "ANTI JOIN"},
    "fn_bits": {"bit_count(c_custkey)": "CAST(bit_count(c_custkey) AS INT)"},
}
SPARK = {"fn_json": {"{k}": "get_json_object(props, '$.k')"}}


def statement(name: str, engine: str) -> str:
    text = STATEMENTS[name]
    for a, b in (SPARK if engine == "spark" else DUCK).get(name, {}).items():
        text = text.replace(a, b)
    return text
