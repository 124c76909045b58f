"""Surrounding operators on the given tables: one portable SQL text each, run by Spark and by DuckDB."""

from __future__ import annotations

from linkedrank.plans.catalog import LINE_ID
from linkedrank.queries import _oracles, _queries
from linkedrank.sources import TABLES, read_table

PORTABLE = {
    "scan_pushdown": "SELECT o_orderkey, o_orderpriority FROM {orders} WHERE o_orderkey BETWEEN 100 AND 900 AND o_orderpriority IS NOT NULL",
    "filter_keywords": "SELECT p_partkey FROM {part} WHERE lower(p_name) LIKE '%widget%' OR lower(p_type) LIKE '%economy%'",
    "filter_isin": "SELECT c_custkey, c_name FROM {customer} WHERE c_mktsegment IN ('BUILDING', 'MACHINERY')",
    "join_line_part": "SELECT p_brand, count(*) AS n FROM {lineitem} JOIN {part} ON l_partkey = p_partkey GROUP BY p_brand",
    "semi_reduced": "SELECT count(*) AS n FROM {orders} WHERE EXISTS (SELECT 1 FROM {lineitem} WHERE l_orderkey = o_orderkey)",
    "anti_free": "SELECT count(*) AS n FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey)",
    "outer_stats": "SELECT n_name, count(s_suppkey) AS n FROM {nation} LEFT JOIN {supplier} ON s_nationkey = n_nationkey GROUP BY n_name",
    "theta_bounds": "SELECT b.lo, count(*) AS n FROM {part} JOIN (SELECT * FROM (VALUES (1, 10), (11, 30), (31, 60)) AS v(lo, hi)) b ON p_size >= b.lo AND p_size <= b.hi GROUP BY b.lo",
    "asof_stats": "SELECT event_id, max(CASE WHEN event_type = 'view' THEN event_id END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_view FROM {events}",
    "self_pairs": "SELECT count(*) AS n FROM {supplier} a JOIN {supplier} b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey",
    "df_by_word": "SELECT c_mktsegment AS word, count(DISTINCT c_custkey) AS df FROM {customer} GROUP BY c_mktsegment",
    "distinct_words": "SELECT count(DISTINCT p_type) AS n FROM {part}",
    "rollup_reports": "SELECT lang, source, count(*) AS n FROM {documents} GROUP BY ROLLUP (lang, source)",
    "cube_lang_source": "SELECT lang, source, count(*) AS n FROM {documents} GROUP BY CUBE (lang, source)",
    "pivot_tf": "SELECT c_nationkey, CAST(sum(CASE WHEN c_mktsegment = 'BUILDING' THEN 1 ELSE 0 END) AS BIGINT) AS building, CAST(sum(CASE WHEN c_mktsegment = 'MACHINERY' THEN 1 ELSE 0 END) AS BIGINT) AS machinery FROM {customer} GROUP BY c_nationkey",
    "rank_row_scores": "SELECT p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS rn, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS dr FROM {part}",
    "running_stats": "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS n FROM {events}",
    "lag_mark": "SELECT o_orderkey, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS before FROM {orders}",
    "topk_global": "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 100",
    "topk_per_query": "SELECT * FROM (SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rn FROM {customer}) x WHERE rn <= 3",
    "union_networks": "SELECT s_nationkey AS k FROM {supplier} UNION ALL SELECT c_nationkey AS k FROM {customer}",
    "answers_diff": "SELECT c_nationkey AS k FROM {customer} EXCEPT ALL SELECT s_nationkey AS k FROM {supplier}",
    "answers_common": "SELECT c_nationkey AS k FROM {customer} INTERSECT SELECT s_nationkey AS k FROM {supplier}",
    "clean_pages": "SELECT page_id, length(regexp_replace(html, '<[^>]*>', ' '{g})) AS n FROM {pages}",
    "events_by_day": "SELECT CAST(CAST(ts AS DATE) AS STRING) AS day, event_type, count(*) AS n FROM {events} GROUP BY CAST(CAST(ts AS DATE) AS STRING), event_type",
    "recursive_partners": (  # partners of a batch of 20 changed parts, down to depth M/2 + 1 at M = 6
        f"WITH RECURSIVE l AS (SELECT {LINE_ID} AS id, l_partkey, l_orderkey FROM {{lineitem}}), e(rel, k, to_rel, to_k) AS ("
        "SELECT 'part', CAST(l_partkey AS STRING), 'lineitem', id FROM l "
        "UNION ALL SELECT 'lineitem', id, 'orders', CAST(l_orderkey AS STRING) FROM l "
        "UNION ALL SELECT 'orders', CAST(o_orderkey AS STRING), 'customer', CAST(o_custkey AS STRING) FROM {orders} "
        "UNION ALL SELECT 'customer', CAST(c_custkey AS STRING), 'nation', CAST(c_nationkey AS STRING) FROM {customer}), "
        "r(source, rel, k, depth) AS (SELECT p_partkey, 'part', CAST(p_partkey AS STRING), 0 FROM {part} WHERE p_partkey BETWEEN 1 AND 20 "
        "UNION ALL SELECT r.source, e.to_rel, e.to_k, r.depth + 1 FROM r JOIN e ON e.rel = r.rel AND e.k = r.k WHERE r.depth < 4) "
        "SELECT source, rel, k, depth FROM r"),
}


def _run(sql):
    def run(spark, sf_dir):
        return spark.sql(sql.replace("{g}", ""), **{t: read_table(spark, sf_dir, t) for t in TABLES if "{" + t + "}" in sql})

    return run


for _name, _sql in PORTABLE.items():
    _queries[_name] = _run(_sql)
    _oracles[_name] = _sql.replace("{g}", ", 'g'").format(**{t: t for t in TABLES})
