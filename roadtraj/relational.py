"""Relational operators on the given tables: one SQL text each, run by Spark over views and by DuckDB."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from roadtraj.sources.tables import register_views

TEXTS: dict[str, tuple[tuple[str, ...], str]] = {
    "op_broadcast_join": (("nation", "region"), "SELECT n_nationkey, n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey"),
    "op_shuffle_join": (("orders", "lineitem"), "SELECT o_orderkey, count(*) AS n, sum(l_linenumber) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey"),
    "op_semi_join": (("customer", "orders"), "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')"),
    "op_anti_join": (("customer", "orders"), "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)"),
    "op_left_outer": (("supplier", "nation"), "SELECT n_nationkey, count(s_suppkey) AS suppliers FROM nation LEFT JOIN supplier ON s_nationkey = n_nationkey GROUP BY n_nationkey"),
    "op_full_outer": (("supplier", "customer"), "SELECT coalesce(a.k, b.k) AS k, a.n AS suppliers, b.n AS customers FROM (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY s_nationkey) a FULL OUTER JOIN (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY c_nationkey) b ON a.k = b.k"),
    "op_self_join": (("nation",), "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey"),
    "op_null_safe_join": (("orders",), "SELECT count(*) AS n FROM (SELECT DISTINCT o_orderstatus AS s FROM orders) a JOIN (SELECT DISTINCT o_orderstatus AS s FROM orders) b ON a.s IS NOT DISTINCT FROM b.s"),
    "op_hash_aggregate": (("lineitem",), "SELECT l_returnflag, l_linestatus, count(*) AS n, min(l_quantity) AS least, max(l_quantity) AS most FROM lineitem GROUP BY l_returnflag, l_linestatus"),
    "op_count_distinct": (("lineitem",), "SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag"),
    "op_grouping_sets": (("orders",), "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())"),
    "op_rollup": (("part",), "SELECT p_brand, p_size, count(*) AS n FROM part GROUP BY ROLLUP (p_brand, p_size)"),
    "op_window_rank": (("customer",), "SELECT c_custkey, rank() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC) AS r, dense_rank() OVER (PARTITION BY c_mktsegment ORDER BY c_nationkey) AS dr FROM customer"),
    "op_window_frame": (("events",), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS n, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS was, lead(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS later FROM events"),
    "op_ntile": (("supplier",), "SELECT s_suppkey, ntile(4) OVER (ORDER BY s_acctbal, s_suppkey) AS quarter FROM supplier"),
    "op_top_k_per_group": (("orders",), "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) t WHERE k <= 2"),
    "op_top_k": (("part",), "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 10"),
    "op_union": (("customer", "supplier"), "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier"),
    "op_intersect": (("customer", "supplier"), "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier"),
    "op_except": (("nation", "supplier"), "SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier"),
    "op_filter_pushdown": (("lineitem",), "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_quantity BETWEEN 10 AND 11 AND l_returnflag IN ('A', 'R')"),
    "op_case_like": (("part",), "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS size_class FROM part WHERE p_type LIKE '%A%'"),
    "op_having": (("orders",), "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 12"),
    "op_scalar_subquery": (("part",), "SELECT p_partkey FROM part WHERE p_size = (SELECT max(p_size) FROM part)"),
    "op_labels_join": (("documents", "labels"), "SELECT d.lang, l.quality, l.toxic, count(*) AS n FROM documents d JOIN labels l ON d.doc_id = l.doc_id GROUP BY d.lang, l.quality, l.toxic"),
}


def _run(names: tuple[str, ...], text: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        register_views(spark, sf_dir, *names)
        return spark.sql(text)

    return run


# JSON and dates are spelt differently in both dialects.
_JSON = "SELECT CAST({0} AS INT) AS k, count(*) AS n FROM events GROUP BY 1"
_DAYS = "SELECT {0} AS days, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"

QUERIES: dict[str, Callable] = {name: _run(*x) for name, x in TEXTS.items()}
QUERIES["op_json"] = _run(("events",), _JSON.format("get_json_object(props, '$.k')"))
QUERIES["op_dates"] = _run(("lineitem", "orders"), _DAYS.format("datediff(l_shipdate, o_orderdate)"))
ORACLE_SQL: dict[str, str] = {name: text for name, (_, text) in TEXTS.items()}
ORACLE_SQL["op_json"] = _JSON.format("json_extract_string(props, '$.k')")
ORACLE_SQL["op_dates"] = _DAYS.format("date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE))")
