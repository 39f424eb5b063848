"""Operators around the methods that Spark has no single call for, and entries for the rest of the relational kit."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def asof_join(left: DataFrame, right: DataFrame, by: list[str], left_on: str, right_on: str, values: list[str], slice_width: int | None = None) -> DataFrame:
    """Each left row with the values of the last right row at or before it, by one window over the union of both.

    With slice_width a key's rows are dealt to slices of that width, so that no window holds a whole hot key; the last right
    row of each slice is carried to the later slices through a window over one row per slice.
    """
    fields = F.struct(F.col(right_on).alias("__at"), *values)
    a = left.select("*", F.col(left_on).alias("__t"), F.lit(1).alias("__side"), F.lit(None).cast(right.select(fields.alias("x")).schema["x"].dataType).alias("__v"))
    b = right.select(*(F.col(c) if c in by else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns), F.col(right_on).alias("__t"), F.lit(0).alias("__side"), fields.alias("__v"))
    both = a.unionByName(b)
    order = ["__t", "__side", "__v"]
    if slice_width is None:
        over = W.partitionBy(*by).orderBy(*order).rowsBetween(W.unboundedPreceding, W.currentRow)
        out = both.withColumn("__v", F.last("__v", ignorenulls=True).over(over))
    else:
        both = both.withColumn("__slice", F.floor(F.col("__t") / slice_width))
        inside = W.partitionBy(*by, "__slice").orderBy(*order).rowsBetween(W.unboundedPreceding, W.currentRow)
        lasts = both.where("__side = 0").groupBy(*by, "__slice").agg(F.max("__v").alias("__last"))
        slices = both.select(*by, "__slice").distinct().join(lasts, [*by, "__slice"], "left")
        before = W.partitionBy(*by).orderBy("__slice").rowsBetween(W.unboundedPreceding, -1)
        carried = slices.select(*by, "__slice", F.last("__last", ignorenulls=True).over(before).alias("__carry"))
        out = both.withColumn("__in", F.last("__v", ignorenulls=True).over(inside)).join(carried, [*by, "__slice"]).withColumn("__v", F.coalesce("__in", "__carry"))
    return out.where("__side = 1").select(*left.columns, *(F.col(f"__v.{v}").alias(f"asof_{v}") for v in values))


def interval_join(left: DataFrame, right: DataFrame, on: list[str], left_at: str, right_at: str, width: int) -> DataFrame:
    """Pairs with equal keys and 0 <= right_at - left_at <= width: both sides are dealt to buckets of the width."""
    a = left.withColumn("__b", F.explode(F.array(F.floor(F.col(left_at) / width), F.floor(F.col(left_at) / width) + 1)))
    b = right.withColumn("__b", F.floor(F.col(right_at) / width))
    return a.join(b, [*on, "__b"]).where((F.col(right_at) >= F.col(left_at)) & (F.col(right_at) - F.col(left_at) <= width)).drop("__b")


def range_join(points: DataFrame, bands: DataFrame, at: str, low: str, high: str, width: int) -> DataFrame:
    """Points with the bands [low, high) that hold them; bands are dealt to every bucket they touch."""
    b = bands.withColumn("__b", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor((F.col(high) - 1) / width))))
    p = points.withColumn("__b", F.floor(F.col(at) / width))
    return p.join(b, "__b").where((F.col(at) >= F.col(low)) & (F.col(at) < F.col(high))).drop("__b")


def top_k_per_group(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group; partial ranking limits what is shuffled."""
    return df.withColumn("rank", F.row_number().over(W.partitionBy(*by).orderBy(*order))).where(F.col("rank") <= k)


C = "CAST(round({}*100) AS BIGINT)".format

#: Statements that mean the same in Spark and in the reference database, by entry name.
SAME = {
    "rk_scan_prune": "SELECT l_orderkey, l_partkey, l_suppkey FROM lineitem WHERE l_quantity < 5",
    "rk_project_expr": f"SELECT l_orderkey, l_linenumber, l_partkey, {C('l_extendedprice')} * (100 - {C('l_discount')}) AS revenue FROM lineitem",
    "rk_filter_between_in_like": "SELECT p_partkey, p_brand, p_size FROM part WHERE p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#13') AND p_name LIKE '%a%'",
    "rk_filter_null_safe": "SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality IS NOT DISTINCT FROM NULL OR l.quality = 1",
    "rk_case_when": "SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'large' WHEN o_totalprice > 50000 THEN 'medium' ELSE 'small' END AS class FROM orders",
    "rk_inner": "SELECT d.doc_id, d.lang, l.quality FROM documents d JOIN labels l ON d.doc_id = l.doc_id",
    "rk_left": "SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id",
    "rk_right": "SELECT l.doc_id, d.lang FROM documents d RIGHT JOIN labels l ON d.doc_id = l.doc_id",
    "rk_full": "SELECT d.doc_id AS d_id, l.doc_id AS l_id FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id",
    "rk_semi": "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 49)",
    "rk_anti": "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)",
    "rk_theta_nl": "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal < b.s_acctbal",
    "rk_self": "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey",
    "rk_natural": "SELECT n_name, r_name FROM nation JOIN (SELECT r_regionkey AS n_regionkey, r_name FROM region) r USING (n_regionkey)",
    "rk_group_basic": f"SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum({C('l_quantity')}) AS BIGINT) AS qty FROM lineitem GROUP BY l_returnflag, l_linestatus",
    "rk_count_distinct": "SELECT o_orderpriority, count(DISTINCT o_custkey) AS n FROM orders GROUP BY o_orderpriority",
    "rk_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "rk_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "rk_grouping_sets": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))",
    "rk_having": "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 12",
    "rk_avg_stddev": f"SELECT event_type, CAST(round(avg({C('value')})) AS BIGINT) AS mean, CAST(round(stddev_samp({C('value')})) AS BIGINT) AS sd FROM events GROUP BY event_type",
    "rk_pivot": "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(*) FILTER (WHERE event_type = 'purchase') AS purchases FROM events GROUP BY user_id",
    "rk_row_number": "SELECT o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS n FROM orders",
    "rk_rank_dense": "SELECT p_partkey, rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS r, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS d FROM part",
    "rk_ntile": "SELECT c_custkey, ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_custkey) AS quarter FROM customer",
    "rk_lag_lead": "SELECT o_orderkey, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS before, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS after FROM orders",
    "rk_running_sum": f"SELECT o_orderkey, CAST(sum({C('o_totalprice')}) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS BIGINT) AS total FROM orders",
    "rk_moving_rows": f"SELECT event_id, CAST(sum({C('value')}) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS total FROM events",
    "rk_range_frame": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS n FROM events",
    "rk_topk_per_group": "SELECT o_custkey, o_orderkey, n FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS n FROM orders) t WHERE n <= 3",
    "rk_topk": "SELECT o_orderkey, o_custkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20",
    "rk_union_all": "SELECT c_custkey AS k FROM customer UNION ALL SELECT user_id AS k FROM events",
    "rk_union_distinct": "SELECT c_custkey AS k FROM customer UNION SELECT user_id AS k FROM events",
    "rk_intersect": "SELECT c_custkey AS k FROM customer INTERSECT SELECT user_id AS k FROM events",
    "rk_except": "SELECT c_custkey AS k FROM customer EXCEPT SELECT user_id AS k FROM events",
    "rk_string_fns": "SELECT c_custkey, upper(c_name) AS u, substring(c_name, 1, 8) AS s, length(c_name) AS n, replace(c_name, '#', '-') AS r FROM customer",
    "rk_date_trunc_extract": "SELECT o_orderkey, CAST(extract(YEAR FROM o_orderdate) AS BIGINT) AS y, CAST(extract(MONTH FROM o_orderdate) AS BIGINT) AS m FROM orders",
    "rk_math_fns": f"SELECT c_custkey, abs({C('c_acctbal')}) AS a, CAST(round(sqrt(abs(c_acctbal))) AS BIGINT) AS r, CAST(sign(c_acctbal) AS BIGINT) AS s FROM customer",
    "rk_regexp_host": "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM pages",
    "docs_semijoin_labels": "SELECT doc_id, quality FROM labels WHERE doc_id IN (SELECT doc_id FROM documents)",
    "docs_distinct_text": "SELECT count(DISTINCT text) AS n FROM documents",
    "benchmark_in_documents": "SELECT item_id FROM benchmark WHERE text IN (SELECT text FROM documents)",
    "pages_by_host": "SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1",
    "embeddings_by_label": "SELECT label, count(*) AS n FROM embeddings GROUP BY label",
}


def statement(name: str):
    """Runs one of the shared statements over temporary views of the tables."""
    def run(spark, sf_dir: str) -> DataFrame:
        import re

        for t in set(re.findall(r"\b(region|nation|customer|supplier|part|orders|lineitem|events|documents|embeddings|pages|benchmark|labels|conversations)\b", SAME[name])):
            spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)
        return spark.sql(SAME[name])

    return run
