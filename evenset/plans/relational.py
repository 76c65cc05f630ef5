"""The relational surface: one statement per operator, valid in Spark SQL and in DuckDB alike. Tables are
written in braces; Spark binds them to DataFrames, the oracle to views."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

from ..sources.tables import table

L, O, C, N, R = "{lineitem}", "{orders}", "{customer}", "{nation}", "{region}"
B = lambda x: f"CAST({x} AS BIGINT)"

SHARED = {
    "scan_parquet_pruned": f"SELECT l_orderkey, l_quantity FROM {L} WHERE l_shipdate >= TIMESTAMP '1998-01-01 00:00:00' AND l_quantity > 45",
    "project_expressions": f"SELECT l_orderkey, l_linenumber, l_extendedprice * (1 - l_discount) AS net, CAST(l_quantity AS BIGINT) AS qty FROM {L}",
    "filter_predicates": f"SELECT o_orderkey FROM {O} WHERE o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 1000 AND 90000 AND NOT o_orderpriority LIKE '%LOW%'",
    "case_class_label": "SELECT doc_id, CASE WHEN CAST(substring(source, 4, 10) AS INT) < 10 THEN concat('A:', lang) ELSE concat('B:', lang, ':', source) END AS class FROM {documents}",
    "null_handling": f"SELECT c_custkey, coalesce(CAST(o_orderkey AS BIGINT), -1) AS o, nullif(c_mktsegment, 'BUILDING') AS seg FROM {C} LEFT JOIN {O} ON c_custkey = o_custkey",
    "join_broadcast_hash": "SELECT p_brand, count(*) AS n FROM {lineitem} JOIN {part} ON l_partkey = p_partkey GROUP BY p_brand",
    "join_left": f"SELECT c_custkey, count(o_orderkey) AS n FROM {C} LEFT JOIN {O} ON c_custkey = o_custkey GROUP BY c_custkey",
    "join_right": f"SELECT c_custkey, count(o_orderkey) AS n FROM {O} RIGHT JOIN {C} ON c_custkey = o_custkey GROUP BY c_custkey",
    "join_full": f"SELECT a.c_custkey AS a, b.o_custkey AS b, count(*) AS n FROM (SELECT * FROM {C} WHERE c_custkey % 2 = 0) a FULL JOIN {O} b ON a.c_custkey = b.o_custkey GROUP BY 1, 2",
    "join_semi": "SELECT doc_id FROM {documents} d WHERE EXISTS (SELECT 1 FROM {labels} l WHERE l.doc_id = d.doc_id)",
    "join_anti": "SELECT doc_id FROM {documents} d WHERE NOT EXISTS (SELECT 1 FROM {labels} l WHERE l.doc_id = d.doc_id)",
    "join_theta": "SELECT b.lo, count(*) AS n FROM (SELECT 0 AS lo UNION ALL SELECT 100000 UNION ALL SELECT 200000) b JOIN {orders} ON o_totalprice > b.lo GROUP BY b.lo",
    "join_range_bins": f"SELECT b.bin, count(*) AS n FROM (SELECT DISTINCT CAST(floor(l_extendedprice / 10000) AS BIGINT) AS bin FROM {L}) b JOIN {L} ON CAST(floor(l_extendedprice / 10000) AS BIGINT) = b.bin AND l_extendedprice >= b.bin * 10000 AND l_extendedprice < b.bin * 10000 + 5000 GROUP BY b.bin",
    "join_self_pairs": "SELECT a.lang AS lang, count(*) AS pairs FROM {documents} a JOIN {documents} b ON a.source = b.source AND a.lang = b.lang AND a.doc_id < b.doc_id GROUP BY a.lang",
    "join_star_multi": f"SELECT r_name, count(*) AS n, round(sum(l_extendedprice), 2) AS price FROM {L} JOIN {O} ON l_orderkey = o_orderkey JOIN {C} ON o_custkey = c_custkey JOIN {N} ON c_nationkey = n_nationkey JOIN {R} ON n_regionkey = r_regionkey GROUP BY r_name",
    "join_null_safe": "SELECT count(*) AS n FROM {labels} a JOIN {labels} b ON nullif(a.doc_id, 0) IS NOT DISTINCT FROM nullif(b.doc_id, 0)",
    "join_interval_time": "SELECT count(*) AS n FROM {events} a JOIN {events} b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL '1' HOUR",
    "agg_hash_basic": f"SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, min(l_tax) AS tax, round(avg(l_discount), 6) AS disc FROM {L} GROUP BY 1, 2",
    "agg_two_phase_salted": f"SELECT l_returnflag, {B('sum(n)')} AS n FROM (SELECT l_returnflag, l_orderkey % 16 AS salt, count(*) AS n FROM {L} GROUP BY 1, 2) x GROUP BY 1",
    "agg_distinct": "SELECT lang, count(DISTINCT source) AS sources FROM {documents} GROUP BY lang",
    "agg_multi_distinct": f"SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps, count(DISTINCT l_returnflag) AS flags FROM {L}",
    "agg_grouping_sets": "SELECT lang, source, count(*) AS n FROM {documents} GROUP BY GROUPING SETS ((lang), (source), ())",
    "agg_rollup": "SELECT lang, source, count(*) AS n FROM {documents} GROUP BY ROLLUP (lang, source)",
    "agg_cube": "SELECT lang, source, count(*) AS n FROM {documents} GROUP BY CUBE (lang, source)",
    "agg_statistics": f"SELECT l_returnflag, round(stddev_samp(l_quantity), 4) AS sd, round(var_pop(l_discount), 8) AS v, round(corr(l_quantity, l_extendedprice), 6) AS c FROM {L} GROUP BY 1",
    "agg_conditional": "SELECT quality, count(*) FILTER (WHERE toxic = 1) AS toxic, bool_and(toxic = 0) AS clean FROM {labels} GROUP BY quality",
    "agg_min_max_by": f"SELECT o_orderpriority, max(o_totalprice) AS top, min(o_orderkey) AS first_key FROM {O} GROUP BY 1",
    "agg_histogram": "SELECT CAST(floor(log10(n_chars)) AS BIGINT) AS bin, count(*) AS n FROM {documents} WHERE n_chars > 0 GROUP BY 1",
    "agg_having": "SELECT user_id, count(*) AS n FROM {events} GROUP BY user_id HAVING count(*) > 5",
    "agg_median_mode": f"SELECT o_orderpriority, round(median(o_totalprice), 4) AS med FROM {O} GROUP BY 1",
    "window_ranking": f"SELECT o_orderkey, {B('rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC)')} AS rk, {B('dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC)')} AS dr, {B('ntile(4) OVER (PARTITION BY o_orderpriority ORDER BY o_orderkey)')} AS nt FROM {O}",
    "window_analytic": "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prev, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nxt FROM {events}",
    "window_running_rows": f"SELECT c_custkey, {B('sum(c_nationkey) OVER (PARTITION BY c_mktsegment ORDER BY c_custkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)')} AS s FROM {C}",
    "window_range_frame": f"SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderpriority ORDER BY o_orderkey RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS n FROM {O}",
    "window_whole_partition": "SELECT doc_id, round(CAST(n_chars AS DOUBLE) / CAST(sum(n_chars) OVER (PARTITION BY lang) AS DOUBLE), 10) AS share FROM {documents}",
    "topk_global": "SELECT p_partkey, p_retailprice FROM {part} ORDER BY p_retailprice DESC, p_partkey LIMIT 10",
    "topk_per_group": f"SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM {O}) x WHERE r <= 3",
    "sort_nulls_offset": f"SELECT c_custkey, o_orderkey FROM {C} LEFT JOIN {O} ON c_custkey = o_custkey ORDER BY o_orderkey ASC NULLS LAST, c_custkey LIMIT 20 OFFSET 5",
    "set_union": f"SELECT c_nationkey AS k FROM {C} UNION SELECT n_nationkey FROM {N}",
    "set_union_all": f"SELECT c_nationkey AS k FROM {C} UNION ALL SELECT n_nationkey FROM {N}",
    "set_intersect": f"SELECT c_custkey AS k FROM {C} INTERSECT SELECT o_custkey FROM {O}",
    "set_except": f"SELECT c_custkey AS k FROM {C} EXCEPT SELECT o_custkey FROM {O}",
    "set_except_all": f"SELECT o_custkey AS k FROM {O} EXCEPT ALL SELECT c_custkey FROM {C}",
    "set_distinct": f"SELECT DISTINCT l_returnflag, l_linestatus FROM {L}",
    "subquery_scalar": f"SELECT o_orderkey FROM {O} WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.9 FROM {O})",
    "subquery_exists": f"SELECT c_custkey FROM {C} WHERE EXISTS (SELECT 1 FROM {O} WHERE o_custkey = c_custkey AND o_totalprice > 100000)",
    "subquery_in": f"SELECT c_custkey FROM {C} WHERE c_custkey IN (SELECT o_custkey FROM {O} WHERE o_orderstatus = 'F')",
    "subquery_correlated": f"SELECT c_custkey, (SELECT max(o_totalprice) FROM {O} WHERE o_custkey = c_custkey) AS top FROM {C}",
    "cte_recursive_path": "WITH RECURSIVE up(node, lvl) AS (SELECT o_orderkey, 0 FROM {orders} WHERE o_orderkey = 1 UNION ALL SELECT o_orderkey, lvl + 1 FROM up JOIN {orders} ON o_orderkey = node * 2 WHERE lvl < 10) SELECT node, lvl FROM up",
    "fn_string": "SELECT p_partkey, upper(p_name) AS u, reverse(p_brand) AS r, lpad(p_brand, 12, '.') AS lp, replace(p_type, 'e', 'E') AS rp, translate(p_name, 'ab', 'xy') AS tr, concat_ws('-', p_brand, p_type) AS cw, length(p_name) AS n FROM {part}",
    "fn_hash": "SELECT doc_id, md5(text) AS m FROM {documents}",
    "fn_date": f"SELECT o_orderkey, CAST(extract(year FROM o_orderdate) AS BIGINT) AS y, CAST(extract(month FROM o_orderdate) AS BIGINT) AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS d FROM {O}",
    "fn_math": f"SELECT l_orderkey, l_linenumber, round(sqrt(l_quantity), 6) AS s, round(ln(l_extendedprice), 6) AS g, CAST(floor(l_tax * 100 + 0.5) AS BIGINT) AS t, greatest(l_discount, l_tax) AS g2, abs(l_quantity - 25) AS a FROM {L}",
    "fn_conditional": f"SELECT o_orderkey, coalesce(nullif(o_orderstatus, 'F'), 'done') AS s, CASE WHEN o_totalprice > 100000 THEN 'big' WHEN o_totalprice > 10000 THEN 'mid' ELSE 'low' END AS c FROM {O}",
    "fn_decimal": f"SELECT o_orderpriority, CAST(sum(CAST(o_totalprice AS DECIMAL(18, 2))) AS DOUBLE) AS s FROM {O} GROUP BY 1",
    "sample_md5_threshold": "SELECT doc_id FROM {documents} WHERE md5(concat('17:', CAST(doc_id AS STRING))) < '20'",
    "roc_auc_length_score": "SELECT round(sum(p * (below + q / 2.0)) / (sum(p) * sum(q)), 8) AS auc FROM (SELECT p, q, coalesce(sum(q) OVER (ORDER BY n_chars ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM (SELECT n_chars, sum(CAST(quality AS DOUBLE)) AS p, sum(1.0 - CAST(quality AS DOUBLE)) AS q FROM {documents} d JOIN {labels} l ON d.doc_id = l.doc_id GROUP BY n_chars) x) y",
}

# (Spark, DuckDB) where the dialects part.
PAIRS = {
    "join_asof": (
        "SELECT event_id, last(CASE WHEN event_type = 'view' THEN event_id END, true) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prev FROM {events}",
        "SELECT event_id, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prev FROM {events}",
    ),
    "join_lateral_topk": (
        # ranks are spelt out: Spark turns a LIMIT in a LATERAL into row numbers without an order, after a shuffle
        "SELECT c_custkey, o_orderkey FROM {customer}, LATERAL (SELECT o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey NULLS LAST) AS r FROM {orders}) WHERE o_custkey = c_custkey AND r <= 2)",
        "SELECT c_custkey, o_orderkey FROM {customer}, LATERAL (SELECT o_orderkey FROM {orders} WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) x",
    ),
    "join_shuffle_hash": (
        "SELECT /*+ SHUFFLE_HASH(o) */ o_orderpriority, count(*) AS n FROM {lineitem} l JOIN {orders} o ON l_orderkey = o_orderkey GROUP BY 1",
        "SELECT o_orderpriority, count(*) AS n FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey GROUP BY 1",
    ),
    "join_sort_merge": (
        "SELECT /*+ MERGE(o) */ o_orderstatus, count(*) AS n FROM {lineitem} l JOIN {orders} o ON l_orderkey = o_orderkey GROUP BY 1",
        "SELECT o_orderstatus, count(*) AS n FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey GROUP BY 1",
    ),
    "agg_sort_object": (
        "SELECT conv_id, array_join(transform(array_sort(collect_list(struct(turn, role))), x -> x.role), ',') AS roles FROM {conversations} GROUP BY conv_id",
        "SELECT conv_id, string_agg(role, ',' ORDER BY turn, role) AS roles FROM {conversations} GROUP BY conv_id",
    ),
    "agg_percentiles": (
        "SELECT o_orderpriority, round(percentile(o_totalprice, 0.9), 4) AS p FROM {orders} GROUP BY 1",
        "SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.9), 4) AS p FROM {orders} GROUP BY 1",
    ),
    "agg_pivot": (
        "SELECT * FROM (SELECT user_id, event_type FROM {events}) PIVOT (count(*) AS n FOR event_type IN ('view' AS view, 'click' AS click))",
        "SELECT user_id, nullif(count(*) FILTER (WHERE event_type = 'view'), 0) AS \"view\", nullif(count(*) FILTER (WHERE event_type = 'click'), 0) AS click FROM {events} GROUP BY user_id",
    ),
    "agg_unpivot": (
        "SELECT doc_id, name, value FROM {labels} UNPIVOT (value FOR name IN (quality, toxic))",
        "SELECT doc_id, 'quality' AS name, quality AS value FROM {labels} UNION ALL SELECT doc_id, 'toxic', toxic FROM {labels}",
    ),
    "lateral_view_explode": (
        "SELECT vec_id, pos, x FROM {embeddings} LATERAL VIEW posexplode(slice(embedding, 1, 4)) t AS pos, x",
        "SELECT vec_id, CAST(i - 1 AS INTEGER) AS pos, embedding[i] AS x FROM {embeddings}, unnest([1, 2, 3, 4]) AS u(i)",
    ),
    "fn_regex": (
        "SELECT doc_id, regexp_count(text, '[0-9]+') AS nums, regexp_extract(text, '([a-z]+)@', 1) AS who, length(regexp_replace(text, '[aeiou]', '')) AS n FROM {documents}",
        "SELECT doc_id, CAST(len(regexp_extract_all(text, '[0-9]+')) AS INTEGER) AS nums, regexp_extract(text, '([a-z]+)@', 1) AS who, CAST(length(regexp_replace(text, '[aeiou]', '', 'g')) AS INTEGER) AS n FROM {documents}",
    ),
    "fn_array": (
        "SELECT vec_id, round(aggregate(embedding, CAST(0 AS DOUBLE), (s, x) -> s + x), 6) AS s, array_max(embedding) AS mx, size(filter(embedding, x -> x > 0)) AS pos FROM {embeddings}",
        "SELECT vec_id, round(list_sum([CAST(x AS DOUBLE) FOR x IN embedding]), 6) AS s, list_max(embedding) AS mx, CAST(len([x FOR x IN embedding IF x > 0]) AS INTEGER) AS pos FROM {embeddings}",
    ),
    "fn_vector": (
        "SELECT vec_id, round(sqrt(aggregate(embedding, CAST(0 AS DOUBLE), (s, x) -> s + CAST(x AS DOUBLE) * x)), 5) AS norm FROM {embeddings}",
        "SELECT vec_id, round(sqrt(list_sum([CAST(x AS DOUBLE) * x FOR x IN embedding])), 5) AS norm FROM {embeddings}",
    ),
    "fn_json": (
        "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM {events}",
        "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM {events}",
    ),
    "fn_map": (
        "SELECT lang, element_at(map_from_entries(collect_list(struct(source, n))), 'src1') AS src1 FROM (SELECT lang, source, count(*) AS n FROM {documents} GROUP BY 1, 2) GROUP BY lang",
        "SELECT lang, max(CASE WHEN source = 'src1' THEN n END) AS src1 FROM (SELECT lang, source, count(*) AS n FROM {documents} GROUP BY 1, 2) GROUP BY lang",
    ),
    "fn_struct": (
        "SELECT s.k AS k, s.v AS v FROM (SELECT named_struct('k', n_nationkey, 'v', n_name) AS s FROM {nation})",
        "SELECT n_nationkey AS k, n_name AS v FROM {nation}",
    ),
    "agg_vector_mean": (
        "SELECT label, pos, round(avg(CAST(x AS DOUBLE)), 6) AS m FROM {embeddings} LATERAL VIEW posexplode(embedding) t AS pos, x GROUP BY label, pos",
        "SELECT label, CAST(i - 1 AS INTEGER) AS pos, round(avg(CAST(embedding[i] AS DOUBLE)), 6) AS m FROM {embeddings}, unnest(range(1, 65)) AS u(i) GROUP BY 1, 2",
    ),
}

# The casts that the DuckDB side needs so that integer types agree.
_TYPES = {
    "fn_string": "SELECT * REPLACE (CAST(n AS INTEGER) AS n) FROM ({})",
}


def statements() -> dict[str, tuple[str, str]]:
    return {k: (v, v) for k, v in SHARED.items()} | PAIRS


def spark_query(text: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        names = set(re.findall(r"\{(\w+)\}", text))
        return spark.sql(text, **{n: table(spark, sf_dir, n) for n in names})

    return run


def duck_text(name: str, text: str) -> str:
    return _TYPES.get(name, "{}").format(re.sub(r"\{(\w+)\}", r"\1", text))
