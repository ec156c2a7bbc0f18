"""Operators around the searches, which the engine must leave whole: each runs on the given tables, over a search
result where that makes sense, and has one text for both engines."""

from __future__ import annotations

from collections.abc import Callable
from uuid import uuid4

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from polymetric.fixtures import run_sql
from polymetric.store import new_folder

#: name -> ANSI text that Spark and DuckDB both run.
SQL = {
    "o1_scan_projection": "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity < 3",
    "o6_project_expr": "SELECT p_partkey, CAST(p_size AS DOUBLE) AS size, CAST(p_retailprice AS DOUBLE) * 2 AS twice, 'x' AS tag FROM part",
    "o7_filter_pred": "SELECT p_partkey FROM part WHERE p_size BETWEEN 5 AND 20 AND p_type IN ('SMALL', 'LARGE') AND p_name LIKE 'r%' AND p_brand IS NOT NULL AND NOT p_size = 7",
    "o8_join_equi_inner": "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey",
    "o9_join_left": "SELECT o_orderkey, count(l_orderkey) AS n FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey",
    "o9_join_full": "SELECT c_custkey, o_orderkey FROM customer FULL OUTER JOIN orders ON c_custkey = o_custkey",
    "o10_join_semi": "SELECT c_custkey FROM customer LEFT SEMI JOIN orders ON c_custkey = o_custkey",
    "o10_join_anti": "SELECT c_custkey FROM customer LEFT ANTI JOIN orders ON c_custkey = o_custkey",
    "o11_join_cross_broadcast": "SELECT n_nationkey, r_regionkey FROM nation CROSS JOIN region",
    "o12_join_theta_range": "SELECT n_nationkey, p_partkey FROM nation JOIN part ON p_size BETWEEN n_nationkey AND n_nationkey + 1",
    "o14_join_interval": "SELECT a.event_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL '1' HOUR",
    "o16_agg_group": "SELECT p_brand, count(*) AS n, min(p_size) AS lo, max(p_size) AS hi, round(avg(p_size), 6) AS mean FROM part GROUP BY p_brand",
    "o17_agg_distinct": "SELECT p_type, count(DISTINCT p_brand) AS n FROM part GROUP BY p_type",
    "o18_cube": "SELECT p_type, p_brand, count(*) AS n FROM part GROUP BY CUBE (p_type, p_brand)",
    "o18_rollup": "SELECT p_type, p_brand, count(*) AS n FROM part GROUP BY ROLLUP (p_type, p_brand)",
    "o18_grouping_sets": "SELECT p_type, p_brand, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_type), (p_brand), ())",
    "o19_agg_stat": "SELECT round(avg(p_size), 6) AS mean, round(var_pop(p_size), 6) AS var, round(stddev_pop(p_size), 6) AS sd, round(corr(p_size, CAST(p_retailprice AS DOUBLE)), 6) AS c FROM part",
    "o20_agg_argmin": "SELECT p_brand, min_by(p_partkey, p_partkey) AS first, max_by(p_partkey, p_partkey) AS last FROM part GROUP BY p_brand",
    "o23_agg_having": "SELECT p_brand, count(*) AS n FROM part GROUP BY p_brand HAVING count(*) >= 80",
    "o24_win_rank": "SELECT p_partkey, CAST(row_number() OVER w AS INT) AS rn, CAST(rank() OVER w AS INT) AS rk, CAST(dense_rank() OVER w AS INT) AS dr, CAST(ntile(4) OVER w AS INT) AS q FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_partkey)",
    "o25_win_analytic": "SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(value) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "o26_win_frames": "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS s3, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS top FROM events",
    "o27_sort_limit": "SELECT o_orderkey, CAST(o_totalprice AS DOUBLE) AS price FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5",
    "o28_topk_per_group": "SELECT p_brand, p_partkey FROM (SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS rn FROM part) t WHERE rn <= 3",
    "o29_union": "SELECT o_custkey AS k FROM orders UNION SELECT c_custkey FROM customer",
    "o29_intersect": "SELECT c_custkey AS k FROM customer INTERSECT SELECT o_custkey FROM orders",
    "o29_except_all": "SELECT p_size AS k FROM part EXCEPT ALL SELECT CAST(n_nationkey AS INT) FROM nation",
    "o30_distinct": "SELECT DISTINCT p_brand, p_type FROM part",
    "o31_subquery": "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders) AND EXISTS (SELECT 1 FROM lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 45)",
    "o32_cte": "WITH t AS (SELECT p_brand, count(*) AS n FROM part GROUP BY p_brand), u AS (SELECT max(n) AS m FROM t) SELECT p_brand, n FROM t, u WHERE n = m",
    "o33_sample_hashed": "SELECT o_orderkey FROM orders WHERE (o_orderkey * 7919 + 13) % 10007 < 500",
    "f1_strings": "SELECT p_partkey, lower(p_name) AS lo, trim(p_name) AS t, substr(p_name, 2, 3) AS s, length(p_name) AS n, replace(p_name, 'e', 'a') AS r, translate(p_name, 'ab', 'ba') AS x, CAST(levenshtein(p_name, 'red bolt') AS INT) AS d FROM part",
    "f2_dates": "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, CAST(day(o_orderdate) AS INT) AS d, CAST(quarter(o_orderdate) AS INT) AS q FROM orders",
    "f3_math": "SELECT p_partkey, round(sqrt(p_size), 6) AS r, round(exp(p_size / 50.0), 6) AS e, round(ln(p_size + 1), 6) AS l, round(pow(p_size, 2), 6) AS p, greatest(p_size, 10) AS g, least(p_size, 10) AS s, abs(p_size - 25) AS a FROM part",
    "f7_conditional": "SELECT p_partkey, CASE WHEN p_size > 25 THEN 'big' ELSE 'small' END AS c, coalesce(nullif(p_size, 7), -1) AS n FROM part",
}
#: name -> (Spark text, DuckDB text) where the dialects differ.
PAIRS = {
    "o13_join_asof": (
        "SELECT event_id, coalesce(last_value(CASE WHEN event_type = 'purchase' THEN event_id END, true) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), -1) AS purchase FROM events",
        "SELECT event_id, coalesce(last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), -1) AS purchase FROM events",
    ),
    "o21_agg_collect": ("SELECT p_type, array_join(array_sort(collect_list(CAST(p_partkey AS STRING))), ',') AS ids FROM part GROUP BY p_type", "SELECT p_type, array_to_string(list_sort(list(CAST(p_partkey AS VARCHAR))), ',') AS ids FROM part GROUP BY p_type"),
    "o22_unpivot": ("SELECT oid, space, v FROM (SELECT p_partkey AS oid, CAST(p_size AS DOUBLE) AS size, CAST(p_retailprice AS DOUBLE) AS price FROM part) t UNPIVOT (v FOR space IN (size, price)) u", "SELECT oid, space, v FROM (UNPIVOT (SELECT p_partkey AS oid, CAST(p_size AS DOUBLE) AS size, CAST(p_retailprice AS DOUBLE) AS price FROM part) ON size, price INTO NAME space VALUE v)"),
    "f4_arrays": ("SELECT vec_id, round(aggregate(transform(CAST(embedding AS ARRAY<DOUBLE>), x -> x * x), 0D, (s, x) -> s + x), 5) AS norm, size(filter(CAST(embedding AS ARRAY<DOUBLE>), x -> x > 0)) AS pos FROM embeddings", "SELECT vec_id, round(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda x: x * x)), 5) AS norm, CAST(len(list_filter(CAST(embedding AS DOUBLE[]), lambda x: x > 0)) AS INT) AS pos FROM embeddings"),
    "f6_json": ("SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events"),
    "f9_html_title": ("SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title FROM pages", "SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title FROM pages"),
}


def duck(text: str) -> str:
    return text.replace("LEFT SEMI JOIN", "SEMI JOIN").replace("LEFT ANTI JOIN", "ANTI JOIN")


QUERIES = {n: (lambda spark, d, t=t: run_sql(spark, d, t)) for n, t in [*SQL.items(), *((n, p[0]) for n, p in PAIRS.items())]}
ORACLES = {n: duck(t) for n, t in SQL.items()} | {n: p[1] for n, p in PAIRS.items()}


# ---- formats, catalog, functions of a user's own ---------------------------------------------------------------------
def _part(spark: SparkSession, d: str) -> DataFrame:
    return spark.read.parquet(f"{d}/part.parquet").select("p_partkey", "p_name", "p_size")


def _round_trip(kind: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        df, folder = _part(spark, d), new_folder(spark)
        if kind == "text":
            df.select(F.to_json(F.struct("*"))).write.text(folder)
            return spark.read.text(folder).select(F.from_json("value", df.schema).alias("v")).select("v.*")
        df.write.format(kind).save(folder)
        return spark.read.schema(df.schema).format(kind).load(folder)

    return run


def _catalog(spark: SparkSession, d: str) -> DataFrame:
    name = f"pm_{uuid4().hex[:8]}"
    _part(spark, d).createOrReplaceTempView(name)
    out = spark.table(name).where("p_size > 25")
    spark.catalog.dropTempView(name)
    return out


def _scalar(spark: SparkSession, d: str) -> DataFrame:
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pm_gap(a DOUBLE, b DOUBLE) RETURNS DOUBLE RETURN abs(a - b)")
    return _part(spark, d).select("p_partkey", F.expr("pm_gap(p_size, 25)").alias("d"))


def _arrow(spark: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf("double")
    def canberra(x: pd.Series, y: pd.Series) -> pd.Series:
        return ((x - y).abs() / (x.abs() + y.abs())).fillna(0.0)

    return _part(spark, d).select("p_partkey", F.round(canberra(F.col("p_size").cast("double"), F.lit(25.0)), 6).alias("d"))


def _mean(spark: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf("double")
    def spread(x: pd.Series) -> float:
        return float(x.max() - x.min())

    return spark.read.parquet(f"{d}/part.parquet").groupBy("p_brand").agg(spread(F.col("p_size").cast("double")).alias("spread"))


class _Grams:
    """Table function: the distinct two-letter pieces of a text."""

    def eval(self, text: str):  # noqa: ANN201
        for g in sorted({text[i : i + 2] for i in range(len(text) - 1)}):
            yield (g,)


def _table_function(spark: SparkSession, d: str) -> DataFrame:
    spark.udtf.register("pm_grams", F.udtf(_Grams, returnType="gram string"))
    return spark.sql("SELECT p_partkey, gram FROM {p}, LATERAL pm_grams(p_name)", p=_part(spark, d))


def _grouped(spark: SparkSession, d: str) -> DataFrame:
    def box(t):  # noqa: ANN001, ANN202
        import pyarrow as pa
        import pyarrow.compute as pc

        return pa.table({"leaf": [t["leaf"][0].as_py()], "lo": [pc.min(t["p_size"]).as_py()], "hi": [pc.max(t["p_size"]).as_py()]}, schema=pa.schema([("leaf", pa.int64()), ("lo", pa.int64()), ("hi", pa.int64())]))

    return _part(spark, d).select((F.col("p_partkey") % 8).alias("leaf"), F.col("p_size").cast("long").alias("p_size")).groupBy("leaf").applyInArrow(box, "leaf long, lo long, hi long")


_P = "SELECT p_partkey, p_name, p_size FROM part"
for _kind in ("csv", "json", "orc", "text"):
    QUERIES[f"o2_scan_{_kind}"], ORACLES[f"o2_scan_{_kind}"] = _round_trip(_kind), _P
for _name, _run, _text in (
    ("o3_scan_catalog", _catalog, f"{_P} WHERE p_size > 25"),
    ("u1_udf_scalar", _scalar, "SELECT p_partkey, abs(CAST(p_size AS DOUBLE) - 25) AS d FROM part"),
    ("u2_d9_udf_arrow_custom_metric", _arrow, "SELECT p_partkey, round(abs(CAST(p_size AS DOUBLE) - 25) / (p_size + 25), 6) AS d FROM part"),
    ("u3_udaf", _mean, "SELECT p_brand, CAST(max(p_size) - min(p_size) AS DOUBLE) AS spread FROM part GROUP BY p_brand"),
    ("u4_udtf", _table_function, "SELECT DISTINCT p_partkey, substr(p_name, CAST(i AS INT), 2) AS gram FROM part, range(1, 200) g(i) WHERE i < length(p_name)"),
    ("u5_grouped_map", _grouped, "SELECT p_partkey % 8 AS leaf, CAST(min(p_size) AS BIGINT) AS lo, CAST(max(p_size) AS BIGINT) AS hi FROM part GROUP BY 1"),
):
    QUERIES[_name], ORACLES[_name] = _run, _text
for _name, (_text, _other) in {
    "o15_join_lateral": ("SELECT n_nationkey, c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2) t",) * 2,
    "o17_approx_distinct": ("SELECT p_type, approx_count_distinct(p_brand) > 0 AS some FROM part GROUP BY p_type",) * 2,
    "f5_maps": ("SELECT p_partkey, map_from_arrays(array('a', 'b'), array(p_size, p_size * 2))['b'] AS twice, size(map_keys(map('x', p_size))) AS n FROM part", "SELECT p_partkey, p_size * 2 AS twice, CAST(1 AS INT) AS n FROM part"),
}.items():
    QUERIES[_name], ORACLES[_name] = (lambda spark, d, t=_text: run_sql(spark, d, t)), _other
QUERIES["f8_hash"] = lambda spark, d: _part(spark, d).select("p_partkey", F.xxhash64("p_name").alias("h64"), F.crc32(F.col("p_name").cast("binary")).alias("crc"))
