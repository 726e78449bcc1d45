"""Relational once-loops over the star schema: every operator a program's surroundings need.

Each is one declarative statement, handed to Catalyst with the tables as DataFrames.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

from ..sources.tables import table

STATEMENTS = {
    "once_select_filter": "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(l_extendedprice * (1 - l_discount), 4) AS net FROM {lineitem} WHERE l_quantity < 5 AND l_discount >= 0.05",
    "once_join_group": """SELECT n_name, r_name, count(*) AS orders, round(sum(round(o_totalprice, 2)), 1) AS total FROM {orders} JOIN {customer} ON o_custkey = c_custkey JOIN {nation} ON c_nationkey = n_nationkey
      JOIN {region} ON n_regionkey = r_regionkey GROUP BY n_name, r_name""",
    "once_semi": "SELECT c_custkey, c_name FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_totalprice > 300000)",
    "once_anti": "SELECT c_custkey, c_name FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey)",
    "once_outer": "SELECT s_suppkey, count(l_orderkey) AS lines FROM {supplier} LEFT JOIN {lineitem} ON s_suppkey = l_suppkey AND l_quantity > 45 GROUP BY s_suppkey",
    "once_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(CAST(round(l_quantity) AS BIGINT)) AS qty, grouping(l_returnflag) + grouping(l_linestatus) AS level FROM {lineitem} GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "once_cube": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM {orders} GROUP BY CUBE (o_orderstatus, o_orderpriority)",
    "once_grouping_sets": "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM {customer} GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())",
    "once_window": """SELECT o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS k, rank() OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice DESC, o_orderkey) AS r,
      ntile(4) OVER (PARTITION BY o_orderstatus ORDER BY o_orderkey) AS quarter,
      sum(CAST(round(o_totalprice) AS BIGINT)) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS last_three FROM {orders}""",
    "once_setops": "(SELECT l_suppkey AS k FROM {lineitem} WHERE l_quantity > 40 INTERSECT SELECT s_suppkey FROM {supplier}) EXCEPT SELECT l_suppkey FROM {lineitem} WHERE l_discount > 0.09 AND l_tax > 0.07",
    "once_topk": "SELECT p_partkey, p_brand, p_retailprice FROM {part} ORDER BY p_retailprice DESC, p_partkey LIMIT 25",
    "once_distinct": "SELECT p_brand, count(DISTINCT p_type) AS types, count(DISTINCT p_size) AS sizes FROM {part} GROUP BY p_brand",
    "once_having": "SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey HAVING count(*) >= 12",
    "once_scalar_subquery": "SELECT p_partkey, p_retailprice FROM {part} WHERE p_retailprice > (SELECT avg(p_retailprice) * 1.2 FROM {part})",
    "once_correlated": "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey FROM {lineitem} a WHERE l_quantity > (SELECT 1.8 * avg(b.l_quantity) FROM {lineitem} b WHERE b.l_partkey = a.l_partkey)",
    "once_interval_join": """SELECT a.event_id, count(*) AS near FROM {events} a JOIN {events} b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR GROUP BY a.event_id""",
    "once_asof": """SELECT event_id, prev FROM (SELECT event_id, event_type, lag(CASE WHEN event_type = 'purchase' THEN event_id END) OVER w AS l0,
      max(CASE WHEN event_type = 'purchase' THEN event_id END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prev FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) t WHERE event_type <> 'purchase'""",
    "once_scalar_functions": "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, upper(substring(o_orderpriority, 1, 3)) AS p, abs(round(o_totalprice - 150000)) AS gap, coalesce(nullif(o_orderstatus, 'F'), '-') AS s FROM {orders}",
    "once_strings": "SELECT c_custkey, lower(c_name) AS name, length(c_name) AS n, replace(c_name, '#', '') AS bare, concat(c_mktsegment, ':', CAST(c_nationkey AS VARCHAR(10))) AS tag FROM {customer}",
    "once_pivot": """SELECT l_suppkey, sum(CASE WHEN l_returnflag = 'A' THEN 1 ELSE 0 END) AS a, sum(CASE WHEN l_returnflag = 'N' THEN 1 ELSE 0 END) AS n, sum(CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END) AS r FROM {lineitem} GROUP BY l_suppkey""",
    "once_case_profile": "SELECT CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS class, count(*) AS n, min(p_retailprice) AS low, max(p_retailprice) AS high FROM {part} GROUP BY 1",
}
#: Where the engines' words differ: (Spark, DuckDB).
TWO = {
    "once_json": ("SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM {events}", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events"),
    "once_array_map": (
        "SELECT vec_id, size(embedding) AS d, round(aggregate(transform(embedding, x -> CAST(x AS DOUBLE) * CAST(x AS DOUBLE)), 0D, (a, x) -> a + x), 5) AS norm2, size(filter(embedding, x -> x > 0)) AS positive FROM {embeddings}",
        "SELECT vec_id, CAST(len(embedding) AS INT) AS d, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 5) AS norm2, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS positive FROM embeddings",
    ),
    "once_collect": ("SELECT o_custkey, concat_ws(',', sort_array(collect_list(o_orderkey))) AS ids FROM {orders} GROUP BY o_custkey", "SELECT o_custkey, array_to_string(list_sort(list(o_orderkey)), ',') AS ids FROM orders GROUP BY o_custkey"),
    "once_date_trunc": ("SELECT date_format(date_trunc('MONTH', o_orderdate), 'yyyy-MM') AS month, count(*) AS n FROM {orders} GROUP BY 1", "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS n FROM orders GROUP BY 1"),
}


def _run(text: str):
    names = sorted(set(re.findall(r"\{(\w+)\}", text)))

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.sql(text, **{n: table(spark, sf_dir, n) for n in names})

    return query


def _cast(text: str) -> str:
    return re.sub(r"\{(\w+)\}", r"\1", text)


QUERIES = {k: _run(v) for k, v in STATEMENTS.items()} | {k: _run(v[0]) for k, v in TWO.items()}
ORACLES = {k: _cast(v) for k, v in STATEMENTS.items()} | {k: v[1] for k, v in TWO.items()}
