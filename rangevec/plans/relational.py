"""The relational operators around the index, each as a named query with SQL for both engines."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..sources.tables import load

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

# (name, SQL of Spark, SQL of DuckDB where it differs)
STATEMENTS: list[tuple[str, str] | tuple[str, str, str]] = [
    ("join_broadcast", "SELECT /*+ BROADCAST(nation) */ c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey"),
    ("join_sortmerge", "SELECT /*+ MERGE(lineitem) */ o_orderkey, sum(l_quantity) AS qty FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey"),
    ("join_hash", "SELECT /*+ SHUFFLE_HASH(part) */ p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand"),
    ("join_nested_loop", "SELECT a.r_name AS a_name, b.r_name AS b_name FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey"),
    ("join_range", "SELECT b.band, count(*) AS n FROM orders JOIN (SELECT * FROM (VALUES (0, 0.0, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 1e9)) AS t(band, lo, hi)) b ON o_totalprice >= b.lo AND o_totalprice < b.hi GROUP BY b.band"),
    ("join_interval", "SELECT e.user_id, count(*) AS n FROM events e JOIN (SELECT user_id, min(ts) AS t0 FROM events GROUP BY user_id) f ON e.user_id = f.user_id AND e.ts <= f.t0 + INTERVAL 7 DAYS GROUP BY e.user_id"),
    ("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)"),
    ("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')"),
    ("join_left", "SELECT vec_id, p_retailprice FROM embeddings LEFT JOIN part ON vec_id = p_partkey"),
    ("join_full", "SELECT coalesce(a.n_nationkey, b.s_nationkey) AS k, b.n FROM nation a FULL JOIN (SELECT s_nationkey, count(*) AS n FROM supplier GROUP BY s_nationkey) b ON a.n_nationkey = b.s_nationkey"),
    ("join_cross", "SELECT r_name, n_name FROM region CROSS JOIN nation WHERE r_regionkey <> n_regionkey"),
    ("join_lateral_topk", "SELECT c_custkey, t.o_orderkey, t.o_totalprice FROM customer, LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) t"),
    ("agg_hash", "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS qty, round(avg(l_extendedprice), 4) AS price, count(*) AS n, min(l_discount) AS lo, max(l_tax) AS hi, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem GROUP BY l_returnflag, l_linestatus"),
    ("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_returnflag"),
    ("agg_approx_distinct", "SELECT abs(approx_count_distinct(l_partkey) - count(DISTINCT l_partkey)) <= 0.1 * count(DISTINCT l_partkey) AS close FROM lineitem", "SELECT TRUE AS close"),
    ("agg_percentile", "SELECT event_type, round(percentile(value, 0.5), 6) AS med, round(percentile(value, 0.9), 6) AS p90 FROM events GROUP BY event_type", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS med, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY event_type"),
    ("agg_collect", "SELECT n_regionkey, array_join(array_sort(collect_list(n_name)), ',') AS names FROM nation GROUP BY n_regionkey", "SELECT n_regionkey, array_to_string(list_sort(list(n_name)), ',') AS names FROM nation GROUP BY n_regionkey"),
    ("agg_min_by", "SELECT o_orderpriority, min_by(o_orderkey, o_totalprice) AS cheapest, max_by(o_orderkey, o_totalprice) AS dearest FROM orders GROUP BY o_orderpriority"),
    ("agg_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)"),
    ("agg_rollup", "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY ROLLUP (lang, source)"),
    ("agg_grouping_sets", "SELECT event_type, user_id, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (user_id), ())"),
    ("agg_pivot", "SELECT * FROM (SELECT l_returnflag, l_linestatus, l_quantity FROM lineitem) PIVOT (sum(l_quantity) FOR l_linestatus IN ('F' AS f, 'O' AS o))", "SELECT l_returnflag, sum(l_quantity) FILTER (l_linestatus = 'F') AS f, sum(l_quantity) FILTER (l_linestatus = 'O') AS o FROM lineitem GROUP BY l_returnflag"),
    ("agg_regr", "SELECT l_returnflag, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(corr(l_extendedprice, l_quantity), 6) AS r FROM lineitem GROUP BY l_returnflag"),
    ("agg_histogram", "SELECT CAST(floor(value / 10) AS INT) AS bucket, count(*) AS n FROM events GROUP BY CAST(floor(value / 10) AS INT)"),
    ("win_row_number", "SELECT vec_id, label, row_number() OVER (PARTITION BY label ORDER BY vec_id) AS n FROM embeddings"),
    ("win_rank", "SELECT event_id, rank() OVER (PARTITION BY event_type ORDER BY value) AS r, dense_rank() OVER (PARTITION BY event_type ORDER BY value) AS d FROM events"),
    ("win_ntile", "SELECT o_orderkey, ntile(8) OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice, o_orderkey) AS bucket FROM orders"),
    ("win_percent_rank", "SELECT o_orderkey, round(percent_rank() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice), 9) AS p, round(cume_dist() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice), 9) AS c FROM orders"),
    ("win_lag_lead", "SELECT event_id, lag(value) OVER (PARTITION BY user_id ORDER BY event_id) AS before, lead(value) OVER (PARTITION BY user_id ORDER BY event_id) AS after FROM events"),
    ("win_running", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 2) AS run FROM orders"),
    ("win_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice RANGE BETWEEN 1000 PRECEDING AND 1000 FOLLOWING) AS near FROM orders"),
    ("win_first_last", "SELECT event_id, first_value(event_type) OVER w AS a, last_value(event_type) OVER w AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"),
    ("set_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier"),
    ("set_union_all", "SELECT k, count(*) AS n FROM (SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier) t GROUP BY k"),
    ("set_intersect", "SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 45 INTERSECT SELECT p_partkey FROM part WHERE p_size < 20"),
    ("set_except", "SELECT p_partkey AS k FROM part EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity > 45"),
    ("set_distinct", "SELECT DISTINCT p_brand, p_size FROM part"),
    ("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25"),
    ("topk_per_group", "SELECT o_orderpriority, o_orderkey, r FROM (SELECT o_orderpriority, o_orderkey, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) t WHERE r <= 5"),
    ("topk_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 10 OFFSET 40"),
    ("filter_predicates", "SELECT o_orderkey FROM orders WHERE (o_totalprice BETWEEN 50000 AND 90000 OR o_orderpriority IN ('1-URGENT', '2-HIGH')) AND NOT o_orderstatus = 'P' AND o_orderdate >= TIMESTAMP '1996-01-01 00:00:00'"),
    ("filter_like", "SELECT p_partkey FROM part WHERE p_name LIKE '%a%' AND p_brand IS NOT NULL"),
    ("fn_string", "SELECT doc_id, length(text) AS n, md5(lower(text)) AS h, substring(text, 1, 12) AS head FROM documents"),
    ("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS first FROM orders"),
    ("fn_math", "SELECT event_id, round(sqrt(value), 6) AS s, round(ln(1 + value), 6) AS l, CAST(floor(value) AS BIGINT) AS f, round(power(value, 2), 4) AS p FROM events"),
    ("fn_bit", "SELECT vec_id, vec_id & 7 AS lo, shiftright(vec_id, 3) AS hi FROM embeddings", "SELECT vec_id, vec_id & 7 AS lo, vec_id >> 3 AS hi FROM embeddings"),
    ("fn_array", "SELECT vec_id, size(embedding) AS d, round(CAST(embedding[0] AS DOUBLE), 6) AS first, round(aggregate(embedding, 0D, (a, x) -> a + x), 5) AS total FROM embeddings", "SELECT vec_id, len(embedding) AS d, round(embedding[1]::DOUBLE, 6) AS first, round(list_sum(embedding::DOUBLE[]), 5) AS total FROM embeddings"),
    ("fn_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events"),
    ("fn_map", "SELECT user_id, element_at(m, 'click') AS clicks FROM (SELECT user_id, map_from_entries(collect_list(struct(event_type, n))) AS m FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type) GROUP BY user_id) WHERE map_contains_key(m, 'click')", "SELECT user_id, count(*) AS clicks FROM events WHERE event_type = 'click' GROUP BY user_id"),
    ("fn_explode", "SELECT vec_id, pos, round(CAST(x AS DOUBLE), 6) AS x FROM (SELECT vec_id, posexplode(slice(embedding, 1, 4)) AS (pos, x) FROM embeddings)", "SELECT vec_id, i AS pos, round(embedding[i + 1]::DOUBLE, 6) AS x FROM embeddings, range(0, 4) t(i)"),
    ("stream_window_counts_batch", "SELECT CAST(date_trunc('day', ts) AS DATE) AS day, event_type, count(*) AS n FROM events GROUP BY date_trunc('day', ts), event_type"),
]


def _query(sql: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        for t in TABLES:
            if t in sql:
                load(spark, sf_dir, t).createOrReplaceTempView(t)
        return spark.sql(sql)

    return run


QUERIES = {s[0]: _query(s[1]) for s in STATEMENTS}
SQL = {s[0]: s[-1] for s in STATEMENTS}
