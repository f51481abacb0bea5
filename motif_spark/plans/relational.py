"""The relational operators around the methods, each on the given tables.

Where one statement says the same in both engines it is written once; tables enter as parameters, so no
view is left in the session.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

QUERIES, SQL = {}, {}


def _t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def same(name: str, sql: str, duck: str | None = None) -> None:
    """A query whose tables are written {table}."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.sql(sql, **{t: _t(spark, sf_dir, t) for t in set(re.findall(r"\{(\w+)\}", sql))})

    QUERIES[name], SQL[name] = run, re.sub(r"\{(\w+)\}", r"\1", duck or sql)


def frame(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


same("op_project_filter", "SELECT event_id, user_id, upper(event_type) AS label FROM {events} WHERE value > 10 AND event_type IN ('click', 'view')")
same("op_join_inner", "SELECT o_orderkey, c_mktsegment FROM {orders} JOIN {customer} ON o_custkey = c_custkey WHERE o_totalprice > 200000")
same("op_join_left", "SELECT c_custkey, count(o_orderkey) AS orders FROM {customer} LEFT JOIN {orders} ON o_custkey = c_custkey GROUP BY c_custkey")
same("op_join_full", "SELECT coalesce(c_nationkey, s_nationkey) AS nation, c, s FROM (SELECT c_nationkey, count(*) AS c FROM {customer} GROUP BY 1) a FULL JOIN (SELECT s_nationkey, count(*) AS s FROM {supplier} GROUP BY 1) b ON c_nationkey = s_nationkey")
same("op_join_range", "SELECT p_partkey, band FROM {part} JOIN (SELECT 1 AS band, 900 AS lo, 1100 AS hi UNION ALL SELECT 2, 1100, 1500 UNION ALL SELECT 3, 1500, 99999) t ON p_retailprice >= lo AND p_retailprice < hi")
same("op_join_cross", "SELECT a.r_name AS a, b.r_name AS b FROM {region} a CROSS JOIN {region} b")
same("op_cube", "SELECT event_type, user_id % 3 AS g, count(*) AS n, grouping(event_type) AS x, grouping(user_id % 3) AS y FROM {events} GROUP BY CUBE (event_type, user_id % 3)", "SELECT event_type, g, count(*) AS n, CAST(grouping(event_type) AS TINYINT) AS x, CAST(grouping(g) AS TINYINT) AS y FROM (SELECT *, user_id % 3 AS g FROM events) GROUP BY CUBE (event_type, g)")
same("op_rollup", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM {customer} GROUP BY ROLLUP (c_mktsegment, c_nationkey)")
same("op_grouping_sets", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM {customer} GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")
same("op_agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(*) AS n FROM {events} GROUP BY event_type")
same("op_agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, max(l_quantity) AS most FROM {lineitem} GROUP BY l_returnflag, l_linestatus")
same("op_percentile", "SELECT event_type, round(percentile(value, 0.5), 6) AS median, round(percentile(value, 0.9), 6) AS p90 FROM {events} GROUP BY 1", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY 1")
same("op_stats", "SELECT event_type, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS deviation, round(corr(value, user_id), 6) AS r FROM {events} GROUP BY 1")
same("op_win_rank", "SELECT event_id, rank() OVER (PARTITION BY user_id ORDER BY event_type) AS r FROM {events}", "SELECT event_id, CAST(rank() OVER (PARTITION BY user_id ORDER BY event_type) AS INT) AS r FROM events")
same("op_win_dense", "SELECT event_id, dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS r FROM {events}", "SELECT event_id, CAST(dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS INT) AS r FROM events")
same("op_win_ntile", "SELECT event_id, ntile(4) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS q FROM {events}", "SELECT event_id, CAST(ntile(4) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS INT) AS q FROM events")
same("op_win_lag_lead", "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, lead(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS after FROM {events}")
same("op_win_running", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS s FROM {events}")
same("op_win_range", "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY user_id RANGE BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS n FROM {events}")
same("op_win_first_last", "SELECT event_id, first_value(event_type) OVER w AS a, last_value(event_type) OVER w AS b FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
same("op_sort_limit", "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
same("op_topk_group", "SELECT user_id, event_id FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS r FROM {events}) WHERE r <= 3")
same("op_union", "SELECT c_nationkey AS nation FROM {customer} UNION SELECT s_nationkey FROM {supplier}")
same("op_union_all", "SELECT c_nationkey AS nation FROM {customer} UNION ALL SELECT s_nationkey FROM {supplier}")
same("op_intersect", "SELECT user_id FROM {events} WHERE event_type = 'error' INTERSECT SELECT user_id FROM {events} WHERE event_type = 'purchase'")
same("op_intersect_all", "SELECT user_id FROM {events} WHERE event_type = 'error' INTERSECT ALL SELECT user_id FROM {events} WHERE event_type = 'purchase'")
same("op_except", "SELECT c_custkey FROM {customer} EXCEPT SELECT o_custkey FROM {orders}")
same("op_except_all", "SELECT user_id FROM {events} WHERE event_type = 'view' EXCEPT ALL SELECT user_id FROM {events} WHERE event_type = 'click'")
same("op_str", "SELECT doc_id, lower(concat_ws(':', lang, source)) AS k, substring(source, 4) AS s, lpad(source, 8, '.') AS p FROM {documents}")
same("op_math", "SELECT event_id, round(1 / (1 + exp(-value / 10)), 6) AS s, round(sqrt(abs(value)), 6) AS r, greatest(user_id, 5) AS g FROM {events}")
same("op_date", "SELECT event_id, year(ts) AS y, dayofmonth(ts) AS d, hour(ts) AS h FROM {events}", "SELECT event_id, CAST(year(ts) AS INT) AS y, CAST(day(ts) AS INT) AS d, CAST(hour(ts) AS INT) AS h FROM events")
same("op_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS k FROM {events}", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
same("op_variant", "SELECT event_id, variant_get(try_parse_json(props), '$.k', 'int') AS k FROM {events}", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
same("op_array", "SELECT vec_id, size(embedding) AS n, round(array_max(embedding), 5) AS most, size(filter(embedding, x -> x > 0)) AS up FROM {embeddings}", "SELECT vec_id, CAST(len(embedding) AS INT) AS n, round(list_max(embedding), 5) AS most, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS up FROM embeddings")
same("op_map", "SELECT user_id, map_from_entries(collect_list(struct(event_type, n)))['click'] AS clicks FROM (SELECT user_id, event_type, count(*) AS n FROM {events} GROUP BY 1, 2) GROUP BY 1", "SELECT user_id, max(CASE WHEN event_type = 'click' THEN n END) AS clicks FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1")
same("op_recursive", "WITH RECURSIVE r(node, depth) AS (SELECT CAST(0 AS BIGINT), 0 UNION ALL SELECT CAST(node * 2 + 1 AS BIGINT), depth + 1 FROM r WHERE depth < 5) SELECT node, depth, c_custkey FROM r JOIN {customer} ON c_custkey = node")
same("s_tumbling", "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS events FROM {events} GROUP BY 1, 2")


@frame("SELECT window_start AS start, event_type, count(*) AS events FROM (SELECT event_type, unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS window_start FROM events) GROUP BY 1, 2")
def s_sliding(spark, sf_dir):
    e = _t(spark, sf_dir, "events").withColumn("ts", F.col("ts"))
    return e.groupBy(F.window("ts", "2 hours", "1 hour").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("events")).select(F.col("w.start").alias("start"), "event_type", "events")


@frame("""WITH x AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS new FROM events),
y AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM x) SELECT user_id, min(ts) AS start, count(*) AS events FROM y GROUP BY user_id, s""")
def s_session(spark, sf_dir):
    e = _t(spark, sf_dir, "events")
    return e.groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("events")).select("user_id", F.col("w.start").alias("start"), "events")


@frame("SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 1)")
def op_join_lateral(spark, sf_dir):
    """The dearest order of each customer. A window, since Spark turns a lateral ORDER BY with LIMIT into row numbers
    whose order is that of a sort before a shuffle, which does not last."""
    dearest = Window.partitionBy("o_custkey").orderBy(F.desc_nulls_last("o_totalprice"), F.asc_nulls_last("o_orderkey"))
    first = _t(spark, sf_dir, "orders").withColumn("_r", F.row_number().over(dearest)).filter("_r = 1")
    return _t(spark, sf_dir, "customer").join(first, F.col("o_custkey") == F.col("c_custkey")).select("c_custkey", "o_orderkey")


@frame("SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_type = b.p_type AND a.p_size < b.p_size AND a.p_retailprice > b.p_retailprice + 500")
def op_join_theta(spark, sf_dir):
    """Parts of a type, the smaller dearer by over 500. Rows that the type's ends of price and size rule out meet none."""
    p = _t(spark, sf_dir, "part").select("p_partkey", "p_type", "p_size", "p_retailprice")
    ends = p.groupBy("p_type").agg(F.min("p_retailprice").alias("low"), F.max("p_retailprice").alias("high"), F.min("p_size").alias("least"), F.max("p_size").alias("most"))
    held = p.join(ends, "p_type")
    a = held.filter("p_retailprice > low + 500 AND p_size < most").alias("a")
    b = held.filter("high > p_retailprice + 500 AND p_size > least").alias("b")
    return a.join(b, F.expr("a.p_type = b.p_type AND a.p_size < b.p_size AND a.p_retailprice > b.p_retailprice + 500")).select(F.col("a.p_partkey").alias("a"), F.col("b.p_partkey").alias("b"))


@frame("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def op_join_semi(spark, sf_dir):
    return _t(spark, sf_dir, "customer").join(_t(spark, sf_dir, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("c_custkey")


@frame("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def op_join_anti(spark, sf_dir):
    return _t(spark, sf_dir, "customer").join(_t(spark, sf_dir, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left_anti").select("c_custkey")


@frame("SELECT e.event_id, (SELECT max(p.ts) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND (p.ts, p.event_id) <= (e.ts, e.event_id)) AS bought FROM events e WHERE event_type = 'error'")
def op_join_asof(spark, sf_dir):
    """Latest purchase before each error: one window over the user's events instead of a join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("ts")), ignorenulls=True).over(w)
    return _t(spark, sf_dir, "events").withColumn("bought", last).filter("event_type = 'error'").select("event_id", "bought")


@frame("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def op_join_interval(spark, sf_dir):
    """Events of a user within an hour: rows meet by user and hour, the later also under the hour before."""
    e = _t(spark, sf_dir, "events").select("event_id", "user_id", "ts", F.date_trunc("hour", "ts").alias("h"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("t2"), F.explode(F.array("h", F.expr("h - interval 1 hour"))).alias("h"))
    return e.join(b, ["user_id", "h"]).filter("t2 > ts and t2 <= ts + interval 1 hour").select(F.col("event_id").alias("a"), "b")


@frame("WITH e AS (SELECT DISTINCT least(n_regionkey, n_nationkey) AS u, greatest(n_regionkey, n_nationkey) AS v FROM nation WHERE n_regionkey <> n_nationkey) SELECT x.u AS a, x.v AS b, y.v AS c FROM e x JOIN e y ON x.v = y.u JOIN e z ON z.u = x.u AND z.v = y.v")
def op_join_self_triangle(spark, sf_dir):
    e = _t(spark, sf_dir, "nation").filter("n_regionkey != n_nationkey").select(F.least("n_regionkey", "n_nationkey").alias("u"), F.greatest("n_regionkey", "n_nationkey").alias("v")).distinct()
    x, y, z = e.toDF("a", "b"), e.toDF("b", "c"), e.toDF("a", "c")
    return x.join(y, "b").join(z, ["a", "c"]).select("a", "b", "c")


@frame("SELECT user_id, sum(CASE WHEN event_type = 'click' THEN 1 END) AS click, sum(CASE WHEN event_type = 'view' THEN 1 END) AS view_ FROM events GROUP BY 1")
def op_pivot(spark, sf_dir):
    df = _t(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).count()
    return df.select("user_id", F.col("click").cast("decimal(38,0)").cast("double").alias("click"), F.col("view").cast("double").alias("view_"))


SQL["op_pivot"] = "SELECT user_id, CAST(sum(CASE WHEN event_type = 'click' THEN 1 END) AS DOUBLE) AS click, CAST(sum(CASE WHEN event_type = 'view' THEN 1 END) AS DOUBLE) AS view_ FROM events GROUP BY 1"


@frame("SELECT p_partkey, 'size' AS what, CAST(p_size AS DOUBLE) AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
def op_unpivot(spark, sf_dir):
    p = _t(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return p.unpivot(["p_partkey"], ["size", "price"], "what", "value")


@frame()
def op_agg_approx(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_orderkey", 0.02).alias("orders"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("parts"))


@frame("SELECT event_id FROM events WHERE CAST('0x' || substr(md5(CAST(user_id AS VARCHAR)), 1, 13) AS BIGINT) / 4503599627370496.0 < 0.1")
def op_sample(spark, sf_dir):
    """A tenth of the users, the same at any partitioning."""
    from ..operators.process import chance

    return _t(spark, sf_dir, "events").filter(chance("user_id") < 0.1).select("event_id")
