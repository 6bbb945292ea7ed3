"""Relational queries around the searches: one text for both engines, tables in braces."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from objann.sources.tables import load_table

TEXTS = {
    "report_rollup": "SELECT lang, source, count(*) AS n, sum(n_chars) AS chars FROM {documents} GROUP BY ROLLUP (lang, source)",
    "report_cube": "SELECT lang, source, count(*) AS n FROM {documents} GROUP BY CUBE (lang, source)",
    "report_grouping_sets": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    "report_pivot": "SELECT source, sum(CASE WHEN lang = 'en' THEN 1 ELSE 0 END) AS en, sum(CASE WHEN lang = 'de' THEN 1 ELSE 0 END) AS de FROM {documents} GROUP BY source",
    "window_frames": "SELECT event_id, sum(event_id) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS running, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS remaining FROM {events}",
    "top_k_per_group": "SELECT l_suppkey, l_orderkey, l_extendedprice, rk FROM (SELECT l_suppkey, l_orderkey, l_extendedprice, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey, l_quantity) AS rk FROM {lineitem}) r WHERE rk <= 3",
    "asof_events": "SELECT event_id, user_id, last_view FROM (SELECT event_id, user_id, event_type, max(CASE WHEN event_type = 'view' THEN ts END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_view FROM {events}) r WHERE event_type = 'purchase'",
    "distinct_counts": "SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_partkey) AS parts FROM {lineitem} GROUP BY l_returnflag",
    "extremes_with_payload": "SELECT user_id, max(value) AS best, max_by(event_id, value) AS event FROM {events} GROUP BY user_id HAVING count(*) = count(DISTINCT value)",
    "supplier_regions": "SELECT r_name, count(*) AS suppliers, sum(CASE WHEN s_acctbal > 0 THEN 1 ELSE 0 END) AS solvent FROM {supplier} s JOIN {nation} n ON s.s_nationkey = n.n_nationkey JOIN {region} r ON n.n_regionkey = r.r_regionkey GROUP BY r_name",
    "unlabelled_anti": "SELECT doc_id, lang FROM {documents} d WHERE NOT EXISTS (SELECT 1 FROM {labels} l WHERE l.doc_id = d.doc_id)",
    "labelled_semi": "SELECT doc_id, lang FROM {documents} d WHERE EXISTS (SELECT 1 FROM {labels} l WHERE l.doc_id = d.doc_id AND l.quality = 1)",
    "labels_outer": "SELECT d.doc_id, l.quality, l.toxic FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id",
    "setop_agreement": "SELECT l_suppkey AS id FROM {lineitem} WHERE l_returnflag = 'R' INTERSECT SELECT s_suppkey FROM {supplier} WHERE s_acctbal > 0",
    "setop_difference": "SELECT p_partkey AS id FROM {part} EXCEPT SELECT l_partkey FROM {lineitem} WHERE l_quantity > 45",
    "scalar_string": "SELECT doc_id, lower(lang) AS lang, length(text) AS n, substring(text, 1, 10) AS head, replace(source, 'src', '') AS number, concat(lang, '-', source) AS tag FROM {documents}",
    "scalar_date": "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, day(o_orderdate) AS d, date_trunc('month', o_orderdate) AS month_start FROM {orders}",
    "scalar_math": "SELECT l_orderkey, l_linenumber, l_partkey, CAST(floor(l_quantity / 7) AS BIGINT) AS f, round(sqrt(l_extendedprice), 6) AS s, greatest(l_discount, l_tax) AS g, least(l_discount, l_tax) AS l FROM {lineitem}",
    "cte_subquery": "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS total FROM {orders} GROUP BY o_custkey) SELECT o_custkey, round(total, 2) AS total FROM big WHERE total > (SELECT avg(total) FROM big)",
    "ranking_functions": "SELECT c_custkey, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey) AS quarter FROM {customer} WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_nationkey)",
    "join_shuffle_hash": "SELECT /*+ SHUFFLE_HASH(o) */ o_orderpriority, count(*) AS n FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey GROUP BY o_orderpriority",
    "join_sort_merge": "SELECT /*+ MERGE(o) */ o_orderkey, count(*) AS n FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey WHERE l_quantity > 49 GROUP BY o_orderkey",
    "join_cross": "SELECT r_name, n_name FROM {region} CROSS JOIN {nation}",
    "join_theta": "SELECT a.n_name AS one, b.n_name AS other FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey",
    "join_full_outer": "SELECT s_suppkey, n_nationkey FROM (SELECT * FROM {supplier} WHERE s_acctbal > 5000) s FULL OUTER JOIN {nation} n ON s.s_nationkey = n.n_nationkey",
    "quantiles_exact": "SELECT l_returnflag, percentile_disc(0.5) WITHIN GROUP (ORDER BY l_extendedprice) AS median, percentile_disc(0.9) WITHIN GROUP (ORDER BY l_quantity) AS high FROM {lineitem} GROUP BY l_returnflag",
    "lag_lead": "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS later, first_value(event_id) OVER w AS first FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "range_frames": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND 500 FOLLOWING) AS near FROM {events}",
    "global_top_k": "SELECT l_orderkey, l_linenumber, l_partkey, l_extendedprice FROM {lineitem} ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey, l_quantity, l_suppkey LIMIT 100",
    "hash_sample": "SELECT o_orderkey, o_totalprice FROM {orders} WHERE substring(md5(CAST(o_orderkey AS STRING)), 1, 1) = '0'",
    "lateral_subquery": "SELECT n_name, t.total FROM {nation} n, LATERAL (SELECT CAST(sum(CASE WHEN s_acctbal > 0 THEN 1 ELSE 0 END) AS BIGINT) AS total FROM {supplier} s WHERE s.s_nationkey = n.n_nationkey) t",
    "setop_intersect_all": "SELECT s_nationkey AS k FROM {supplier} INTERSECT ALL SELECT c_nationkey FROM {customer}",
    "setop_except_all": "SELECT c_nationkey AS k FROM {customer} EXCEPT ALL SELECT s_nationkey FROM {supplier}",
    "null_safe_filters": "SELECT d.doc_id FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id WHERE (l.toxic IS NOT DISTINCT FROM NULL AND d.lang IN ('en', 'de')) OR (l.toxic = 1 AND d.source LIKE 'src1%') OR (l.quality BETWEEN 1 AND 1 AND NOT (d.n_chars > 500))",
}

TABLE = re.compile(r"\{(\w+)\}")


def run_text(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    return spark.sql(text, **{name: load_table(spark, sf_dir, name) for name in set(TABLE.findall(text))})


def duckdb_text(text: str) -> str:
    return TABLE.sub(r"\1", text)


def _arrays(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Array, map and JSON functions over vectors and event properties."""
    e = load_table(spark, sf_dir, "embeddings")
    whole = F.transform("embedding", lambda x: F.floor(x.cast("double") * 1000 + 0.5).cast("long"))
    v = F.col("v")
    return e.select("vec_id", whole.alias("v")).select(
        "vec_id",
        F.aggregate(v, F.lit(0).cast("long"), lambda a, x: a + x).alias("total"),
        F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("positive"),
        F.exists(v, lambda x: x > 400).alias("large"),
        F.array_max(v).alias("most"),
        F.array_position(v, F.array_max(v)).cast("long").alias("place"),
        F.array_join(F.slice(v, 2, 3).cast("array<string>"), "/").alias("part"),
        F.size(F.array_distinct(v)).cast("long").alias("different"),
        F.element_at(F.map_from_arrays(F.sequence(F.lit(1), F.lit(64)), v), 5).alias("fifth"),
        F.size(F.flatten(F.array(v, v))).cast("long").alias("twice"),
    )


def _json(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load_table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long").alias("p"), F.get_json_object("props", "$.k").cast("long").alias("k"))
    return e.select("event_id", F.col("p.k").alias("parsed"), "k", F.to_json(F.struct(F.col("k").alias("k"))).alias("again"))


def _approximate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sketches against exact values: whether they are within their stated error."""
    lines = load_table(spark, sf_dir, "lineitem")
    found = lines.agg(
        F.approx_count_distinct("l_partkey", 0.03).alias("a"), F.countDistinct("l_partkey").alias("b"), F.percentile_approx("l_extendedprice", 0.5, 1000).alias("c"), F.expr("percentile_disc(0.495) WITHIN GROUP (ORDER BY l_extendedprice)").alias("low"), F.expr("percentile_disc(0.505) WITHIN GROUP (ORDER BY l_extendedprice)").alias("high")
    )
    return found.select((F.abs(F.col("a") - F.col("b")) <= 0.12 * F.col("b")).alias("distinct_fits"), F.col("c").between(F.col("low"), F.col("high")).alias("median_fits"))


def queries() -> dict:
    return {"scalar_arrays": _arrays, "scalar_json": _json, "approximate_aggregates": _approximate}


def oracles() -> dict[str, str]:
    return {
        "scalar_arrays": """WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 1000 + 0.5) AS BIGINT)) AS v FROM embeddings)
          SELECT vec_id, CAST(list_sum(v) AS BIGINT) AS total, len(list_filter(v, lambda x: x > 0)) AS positive, len(list_filter(v, lambda x: x > 400)) > 0 AS large, list_max(v) AS most, CAST(list_position(v, list_max(v)) AS BIGINT) AS place,
                 array_to_string(v[2:4], '/') AS part, len(list_distinct(v)) AS different, v[5] AS fifth, CAST(128 AS BIGINT) AS twice FROM e""",
        "scalar_json": "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS parsed, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, concat('{\"k\":', json_extract_string(props, '$.k'), '}') AS again FROM events",
        "approximate_aggregates": "SELECT true AS distinct_fits, true AS median_fits",
    }
