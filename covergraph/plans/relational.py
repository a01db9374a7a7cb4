"""Relational operators on the given tables: each a Spark SQL text, and DuckDB's where the dialects differ."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

#: name: Spark's text, or (Spark's text, DuckDB's text).
SQL: dict[str, str | tuple[str, str]] = {
    "rel_star_revenue": """SELECT r_name, n_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, count(*) AS n_lines
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
        JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name, n_name""",
    "rel_cube": "SELECT l_returnflag, l_linestatus, grouping(l_returnflag) AS gf, grouping(l_linestatus) AS gs, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM lineitem GROUP BY CUBE(l_returnflag, l_linestatus)",
    "rel_rollup": "SELECT o_orderstatus, o_orderpriority, count(*) AS n, round(sum(o_totalprice), 1) AS total FROM orders GROUP BY ROLLUP(o_orderstatus, o_orderpriority)",
    "rel_grouping_sets": "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY GROUPING SETS ((lang), (source), ())",
    "rel_window_rank": """SELECT s_suppkey, s_nationkey, rank() OVER w AS rk, dense_rank() OVER w AS dr, row_number() OVER w AS rn, ntile(4) OVER w AS quart
        FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey)""",
    "rel_window_frame": """SELECT o_orderkey, o_custkey, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after,
        count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n3,
        first_value(o_orderkey) OVER w AS first_order FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)""",
    "rel_hash_join": "SELECT /*+ SHUFFLE_HASH(o) */ o_orderpriority, count(*) AS n FROM lineitem JOIN orders o ON l_orderkey = o_orderkey WHERE l_quantity < 10 GROUP BY o_orderpriority",
    "rel_merge_join": "SELECT /*+ MERGE(o) */ o_orderstatus, count(*) AS n FROM lineitem JOIN orders o ON l_orderkey = o_orderkey WHERE l_quantity > 40 GROUP BY o_orderstatus",
    "rel_hash_sample": "SELECT o_orderstatus, count(*) AS n, min(o_orderkey) AS first_key FROM orders WHERE (o_orderkey * 48271) % 2147483647 % 100 < CASE o_orderstatus WHEN 'P' THEN 50 ELSE 5 END GROUP BY o_orderstatus",
    "rel_lateral_top": """SELECT n_nationkey, s_suppkey FROM (SELECT n_nationkey, s_suppkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS rn FROM nation LEFT JOIN supplier ON s_nationkey = n_nationkey) t WHERE rn = 1""",
    "rel_semi": "SELECT c_custkey, c_name FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)",
    "rel_anti": "SELECT c_custkey, c_name FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)",
    "rel_full_outer": "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.lang, l.quality FROM documents d FULL OUTER JOIN labels l ON d.doc_id = l.doc_id",
    "rel_null_safe": "SELECT count(*) AS n FROM documents a LEFT JOIN labels b ON a.doc_id = b.doc_id WHERE b.quality IS NOT DISTINCT FROM NULL",
    "rel_except": "SELECT l_partkey FROM lineitem WHERE l_quantity > 45 EXCEPT SELECT p_partkey FROM part WHERE p_size < 10",
    "rel_intersect": "SELECT l_suppkey AS k FROM lineitem WHERE l_discount > 0.05 INTERSECT SELECT s_suppkey FROM supplier WHERE s_acctbal > 0",
    "rel_union": "SELECT n_name AS name FROM nation UNION ALL SELECT r_name FROM region UNION ALL SELECT c_mktsegment FROM customer",
    "rel_predicates": "SELECT p_partkey, p_name, p_size FROM part WHERE p_size BETWEEN 5 AND 15 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#23') OR p_type LIKE '%BRASS%'",
    "rel_agg": """SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, min(l_shipdate) AS first_ship, max(l_shipdate) AS last_ship, round(avg(l_quantity), 6) AS qty,
        count(*) FILTER (WHERE l_discount = 0) AS full_price FROM lineitem GROUP BY l_returnflag""",
    "rel_min_by": ("SELECT o_custkey, min_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY o_custkey", "SELECT o_custkey, arg_min(o_orderkey, row(o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY o_custkey"),
    "rel_percentile": ("SELECT l_linestatus, percentile(l_quantity, 0.5) AS med, percentile(l_quantity, 0.9) AS p90 FROM lineitem GROUP BY 1", "SELECT l_linestatus, quantile_cont(l_quantity, 0.5) AS med, quantile_cont(l_quantity, 0.9) AS p90 FROM lineitem GROUP BY 1"),
    "rel_pivot": ("""SELECT o_orderstatus, coalesce(p1, 0) AS p1, coalesce(p2, 0) AS p2, coalesce(p3, 0) AS p3 FROM (SELECT o_orderstatus, substring(o_orderpriority, 1, 1) AS p, o_orderkey FROM orders)
        PIVOT (count(o_orderkey) FOR p IN ('1' AS p1, '2' AS p2, '3' AS p3))""",
        """SELECT o_orderstatus, count(*) FILTER (WHERE o_orderpriority LIKE '1%') AS p1, count(*) FILTER (WHERE o_orderpriority LIKE '2%') AS p2,
        count(*) FILTER (WHERE o_orderpriority LIKE '3%') AS p3 FROM orders GROUP BY o_orderstatus"""),
    "rel_approx": ("""SELECT l_returnflag, abs(approx_count_distinct(l_partkey) - count(DISTINCT l_partkey)) <= 0.15 * count(DISTINCT l_partkey) AS near_distinct,
        abs(approx_percentile(l_extendedprice, 0.5, 10000) - percentile(l_extendedprice, 0.5)) <= 0.02 * percentile(l_extendedprice, 0.5) AS near_median,
        abs(kll_sketch_get_quantile_double(kll_sketch_agg_double(l_extendedprice), 0.5) - percentile(l_extendedprice, 0.5)) <= 0.1 * percentile(l_extendedprice, 0.5) AS near_sketch,
        mode(l_linenumber, true) AS common FROM lineitem GROUP BY l_returnflag""",
        """SELECT l_returnflag, true AS near_distinct, true AS near_median, true AS near_sketch, arg_min(l_linenumber, row(-n, l_linenumber)) AS common
        FROM (SELECT l_returnflag, l_linenumber, count(*) AS n FROM lineitem GROUP BY 1, 2) GROUP BY 1"""),
    "rel_window_range": """SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_totalprice RANGE BETWEEN 1000 PRECEDING AND 1000 FOLLOWING) AS near,
        round(percent_rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice), 6) AS pr, round(cume_dist() OVER (PARTITION BY o_custkey ORDER BY o_totalprice), 6) AS cd FROM orders""",
    "rel_map_values": ("""SELECT n_regionkey, aggregate(map_values(map_zip_with(transform_values(m, (k, v) -> length(v)), m, (k, a, b) -> a + length(b))), 0, (s, x) -> s + x) AS chars
        FROM (SELECT n_regionkey, map_from_entries(collect_list(struct(n_nationkey, n_name))) AS m FROM nation GROUP BY n_regionkey)""",
        "SELECT n_regionkey, CAST(2 * sum(length(n_name)) AS INTEGER) AS chars FROM nation GROUP BY 1"),
    "rel_json_struct": ("SELECT event_id, to_json(struct(from_json(props, 'k BIGINT').k AS k)) AS j, schema_of_json('{\"page\": 1}') AS s FROM events",
        "SELECT event_id, CASE WHEN p IS NULL THEN '{}' ELSE '{\"k\":' || p || '}' END AS j, 'STRUCT<page: BIGINT>' AS s FROM (SELECT event_id, json_extract_string(props, '$.k') AS p FROM events)"),
    "rel_unpivot": ("SELECT doc_id, k, v FROM labels LATERAL VIEW stack(2, 'quality', quality, 'toxic', toxic) AS k, v", "SELECT doc_id, 'quality' AS k, quality AS v FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels"),
    "rel_topk": """SELECT c_mktsegment, c_custkey, rn FROM (SELECT c_mktsegment, c_custkey, row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey) AS rn FROM customer) t WHERE rn <= 5""",
    "rel_supplier_part_rank": """SELECT l_suppkey, l_partkey, qty, rk FROM (SELECT l_suppkey, l_partkey, sum(l_quantity) AS qty, rank() OVER (PARTITION BY l_suppkey ORDER BY sum(l_quantity) DESC, l_partkey) AS rk
        FROM lineitem GROUP BY l_suppkey, l_partkey) t WHERE rk <= 3""",
    "rel_asof_join": ("""SELECT event_id, user_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END) IGNORE NULLS OVER w AS last_purchase
        FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)""",
        """SELECT event_id, user_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER w AS last_purchase
        FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)"""),
    "rel_interval_join": ("""SELECT p.event_id AS purchase, count(e.event_id) AS near FROM events p JOIN events e ON p.user_id = e.user_id AND e.event_id <> p.event_id
        AND e.ts BETWEEN p.ts - INTERVAL 10 MINUTES AND p.ts + INTERVAL 10 MINUTES WHERE p.event_type = 'purchase' GROUP BY p.event_id""",) * 2,
    "rel_range_join": "SELECT a.p_partkey AS a, count(*) AS n FROM part a JOIN part b ON b.p_retailprice BETWEEN a.p_retailprice - 1 AND a.p_retailprice + 1 AND a.p_size = b.p_size GROUP BY a.p_partkey",
    "rel_json": ("SELECT get_json_object(props, '$.page') AS page, count(*) AS n FROM events GROUP BY 1", "SELECT json_extract_string(props, '$.page') AS page, count(*) AS n FROM events GROUP BY 1"),
    "rel_map": ("SELECT n_regionkey, size(m) AS n, element_at(m, n_regionkey) AS own FROM (SELECT n_regionkey, map_from_entries(collect_list(struct(n_nationkey, n_name))) AS m FROM nation GROUP BY n_regionkey) t",
        "SELECT n_regionkey, CAST(cardinality(m) AS INTEGER) AS n, m[n_regionkey] AS own FROM (SELECT n_regionkey, map_from_entries(list({k: n_nationkey, v: n_name})) AS m FROM nation GROUP BY n_regionkey) t"),
    "rel_array": ("SELECT vec_id, round(aggregate(embedding, CAST(0 AS DOUBLE), (s, x) -> s + x), 4) AS total, size(filter(embedding, x -> x > 0)) AS positive FROM embeddings", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE))), 4) AS total, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive FROM embeddings"),
    "rel_string": ("SELECT p_partkey, upper(p_name) AS u, substring(p_name, 1, 3) AS s, levenshtein(p_name, p_type) AS d, split(p_name, ' ')[0] AS w FROM part", "SELECT p_partkey, upper(p_name) AS u, substring(p_name, 1, 3) AS s, CAST(levenshtein(p_name, p_type) AS INTEGER) AS d, string_split(p_name, ' ')[1] AS w FROM part"),
    "rel_date": ("SELECT date_format(o_orderdate, 'yyyy-MM') AS month, count(*) AS n, max(datediff(o_orderdate, DATE '1992-01-01')) AS days FROM orders GROUP BY 1", "SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n, CAST(max(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE))) AS INTEGER) AS days FROM orders GROUP BY 1"),
    "rel_math": ("SELECT p_partkey, round(sqrt(p_retailprice), 6) AS r, round(ln(p_retailprice), 6) AS l, p_partkey % 7 AS m, greatest(p_size, 25) AS g FROM part",) * 2,
    "rel_pages_url": ("SELECT parse_url(url, 'HOST') AS host, count(*) AS n, sum(length(html)) AS chars FROM pages GROUP BY 1", "SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host, count(*) AS n, sum(length(html)) AS chars FROM pages GROUP BY 1"),
    "rel_conversation_turns": "SELECT conv_id, turn, role, lag(role) OVER w AS role_before, lead(turn) OVER w AS turn_after FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn, role, text)",
    "rel_benchmark_overlap": ("""WITH t AS (SELECT DISTINCT item_id, explode(split(lower(text), ' ')) AS w FROM benchmark), d AS (SELECT DISTINCT doc_id, explode(split(lower(text), ' ')) AS w FROM documents)
        SELECT item_id, count(DISTINCT doc_id) AS docs FROM t JOIN d ON t.w = d.w GROUP BY item_id""",
        """WITH t AS (SELECT DISTINCT item_id, unnest(string_split(lower(text), ' ')) AS w FROM benchmark), d AS (SELECT DISTINCT doc_id, unnest(string_split(lower(text), ' ')) AS w FROM documents)
        SELECT item_id, count(DISTINCT doc_id) AS docs FROM t JOIN d ON t.w = d.w GROUP BY item_id"""),
    "rel_labels_cube": "SELECT lang, quality, toxic, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY CUBE(lang, quality, toxic)",
    "rel_scalar_subquery": "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT 2 * avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)",
    "rel_recursive": ("WITH RECURSIVE t(n, f) AS (SELECT 1, CAST(1 AS BIGINT) UNION ALL SELECT n + 1, f * (n + 1) FROM t WHERE n < 12) SELECT n, f FROM t",) * 2,
    "rel_sessions": """WITH g AS (SELECT user_id, event_id, ts, CASE WHEN ts - lag(ts) OVER w > INTERVAL '30' MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
        s AS (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM g) SELECT user_id, session, count(*) AS n FROM s GROUP BY user_id, session""",
}


def query(text: str):
    """The text over views of its own names, so that no view of the caller's is touched."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        used = {t for t in TABLES if re.search(rf"\b(FROM|JOIN) {t}\b", text)}
        for t in used:
            spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(f"given_{t}")
        if not used:
            return spark.sql(text)
        return spark.sql(re.sub(r"\b(FROM|JOIN) (" + "|".join(used) + r")\b", r"\1 given_\2", text))

    return run


def queries() -> dict:
    return {k: query(v if isinstance(v, str) else v[0]) for k, v in SQL.items()}


def oracles() -> dict[str, str]:
    return {k: v if isinstance(v, str) else v[-1] for k, v in SQL.items()}
