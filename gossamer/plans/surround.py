"""Operators around the methods. Each text runs on Spark (tables by name in braces) and, without the braces, on DuckDB."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

from gossamer.sources.points import table

BOTH = {
    "cube_flags": "SELECT l_returnflag, l_linestatus, cast(coalesce(cluster, -1) AS int) AS cluster, count(*) AS n, round(avg(l_quantity), 6) AS mean_quantity, cast(grouping(l_returnflag) + 2 * grouping(l_linestatus) + 4 * grouping(cluster) AS bigint) AS level FROM (SELECT l_returnflag, l_linestatus, l_quantity, CASE WHEN l_quantity < 17 THEN 0 WHEN l_quantity < 34 THEN 1 ELSE 2 END AS cluster FROM {lineitem}) t GROUP BY CUBE (l_returnflag, l_linestatus, cluster)",
    "rollup_orders": "SELECT o_orderstatus, o_orderpriority, count(*) AS n, round(max(o_totalprice), 2) AS largest FROM {orders} GROUP BY ROLLUP (o_orderstatus, o_orderpriority)",
    "grouping_sets_documents": "SELECT lang, source, count(*) AS n, cast(sum(n_chars) AS bigint) AS chars FROM {documents} GROUP BY GROUPING SETS ((lang), (source), ())",
    "star_join_regions": "SELECT r_name, CASE WHEN l_quantity < 17 THEN 0 WHEN l_quantity < 34 THEN 1 ELSE 2 END AS cluster, count(*) AS n FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey JOIN {customer} ON o_custkey = c_custkey JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey GROUP BY 1, 2",
    "docs_join_labels": "SELECT source, count(*) AS n, cast(sum(quality) AS bigint) AS good, cast(sum(CASE WHEN toxic = 1 THEN 1 ELSE 0 END) AS bigint) AS toxic FROM {documents} d JOIN {labels} l ON d.doc_id = l.doc_id GROUP BY source",
    "antijoin_unlabelled": "SELECT d.doc_id, d.lang FROM {documents} d LEFT ANTI JOIN {labels} l ON d.doc_id = l.doc_id",
    "semijoin_labelled": "SELECT d.doc_id, d.lang FROM {documents} d LEFT SEMI JOIN {labels} l ON d.doc_id = l.doc_id",
    "interval_events": "SELECT e.user_id, count(*) AS n FROM (SELECT user_id, min(ts) AS first_error FROM {events} WHERE event_type = 'error' GROUP BY user_id) f JOIN {events} e ON e.user_id = f.user_id AND e.ts >= f.first_error - INTERVAL 1 HOUR AND e.ts <= f.first_error + INTERVAL 1 HOUR GROUP BY e.user_id",
    "running_minimum": "SELECT o_orderkey, round(min(o_totalprice) OVER w, 2) AS best, round(o_totalprice - lag(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey), 2) AS step, cast(row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS bigint) AS place FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)",
    "quartiles": "SELECT l_returnflag, cast(t AS int) AS quarter, count(*) AS n, round(max(l_extendedprice), 2) AS upper FROM (SELECT l_returnflag, l_extendedprice, ntile(4) OVER (PARTITION BY l_returnflag ORDER BY l_extendedprice, l_orderkey, l_linenumber, l_partkey, l_suppkey) AS t FROM {lineitem}) q GROUP BY 1, 2",
    "distinct_touched": "SELECT l_returnflag, count(DISTINCT l_orderkey) AS orders, count(DISTINCT l_partkey) AS parts FROM {lineitem} GROUP BY l_returnflag",
    "conversation_gaps": "SELECT conv_id, turn, role, lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS role_before, coalesce(turn - lag(turn) OVER (PARTITION BY conv_id ORDER BY turn), 0) AS gap FROM {conversations}",
    "page_hosts": "SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host, count(*) AS n, cast(sum(length(regexp_replace(html, '<[^>]*>', '', 'g'))) AS bigint) AS chars FROM {pages} GROUP BY 1",
    "date_features": "SELECT cast(year(o_orderdate) AS int) AS y, cast(quarter(o_orderdate) AS int) AS q, cast(month(o_orderdate) AS int) AS m, count(*) AS n FROM {orders} GROUP BY 1, 2, 3",
    "ship_delay": "SELECT cast(datediff('day', o_orderdate, l_shipdate) AS bigint) AS days, count(*) AS n FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey GROUP BY 1",
    "correlated": "SELECT c_custkey, c_mktsegment FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'F') AND c_acctbal > (SELECT avg(c_acctbal) FROM {customer})",
    "recursive_steps": "WITH RECURSIVE r(l_returnflag, l_linestatus, t, w, c) AS (SELECT l_returnflag, l_linestatus, 0, max(l_quantity), avg(l_quantity) FROM {lineitem} GROUP BY l_returnflag, l_linestatus UNION ALL SELECT l_returnflag, l_linestatus, t + 1, w - 0.5 * (w - c), c FROM r WHERE t < 10) SELECT l_returnflag, l_linestatus, t, cast(w AS double) AS w FROM r",
    "set_operations": "SELECT c_nationkey FROM {customer} INTERSECT SELECT s_nationkey FROM {supplier} EXCEPT SELECT n_nationkey FROM {nation} WHERE n_regionkey = 0",
    "union_all_counts": "SELECT kind, count(*) AS n FROM (SELECT 'customer' AS kind FROM {customer} UNION ALL SELECT 'supplier' FROM {supplier} UNION ALL SELECT 'part' FROM {part}) u GROUP BY kind",
    "moving_average": "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(avg(l_quantity) OVER (PARTITION BY l_suppkey ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS moving FROM {lineitem}",
    "rank_parts": "SELECT p_partkey, cast(rank() OVER (PARTITION BY p_size ORDER BY p_retailprice DESC) AS bigint) AS r, cast(dense_rank() OVER (PARTITION BY p_size ORDER BY p_retailprice DESC) AS bigint) AS dr FROM {part}",
    "large_groups": "SELECT l_suppkey, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM {lineitem} WHERE l_quantity BETWEEN 5 AND 45 AND l_returnflag IN ('A', 'N') GROUP BY l_suppkey HAVING count(*) > 5",
    "like_filter": "SELECT p_partkey, p_name, upper(substring(p_brand, 1, 7)) AS brand FROM {part} WHERE p_type LIKE 'ECON%' OR p_name LIKE 'b%t'",
    "pivot_status": "SELECT o_orderpriority, count(CASE WHEN o_orderstatus = 'F' THEN 1 END) AS f, count(CASE WHEN o_orderstatus = 'O' THEN 1 END) AS o, count(CASE WHEN o_orderstatus = 'P' THEN 1 END) AS p FROM {orders} GROUP BY o_orderpriority",
}

#: where the two dialects name a thing differently: (text for Spark, text for DuckDB)
APART = {
    "LEFT ANTI JOIN": ("LEFT ANTI JOIN", "ANTI JOIN"), "LEFT SEMI JOIN": ("LEFT SEMI JOIN", "SEMI JOIN"),
    ", 'g')": (")", ", 'g')"), "datediff('day', o_orderdate, l_shipdate)": ("datediff(l_shipdate, o_orderdate)", "date_diff('day', o_orderdate, l_shipdate)"),
}


def spark_text(text: str) -> str:
    for written, (here, _) in APART.items():
        text = text.replace(written, here)
    return text


def duck_text(text: str) -> str:
    for written, (_, there) in APART.items():
        text = text.replace(written, there)
    return re.sub(r"\{(\w+)\}", r"\1", text)


def query(text: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.sql(spark_text(text), **{name: table(spark, sf_dir, name) for name in set(re.findall(r"\{(\w+)\}", text))})

    return run
