"""Relational and streaming surface around the sketches: one SQL text that both engines run, or a DataFrame with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def table(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def shared(name: str, sql: str) -> None:
    """A query whose text means the same in both engines; {t} stands for table t."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        used = {t: table(spark, d, t) for t in TABLES if "{" + t + "}" in sql}
        return spark.sql(sql, **used)

    QUERIES[name] = run
    ORACLE[name] = sql.replace("{", "").replace("}", "")


def both(name: str, sql: str):
    def add(f):
        QUERIES[name], ORACLE[name] = f, sql
        return f

    return add


# scans, projections, filters
shared("scan_parquet", "SELECT count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS s FROM {lineitem}")
shared("scan_pruned", "SELECT l_returnflag, count(*) AS n FROM {lineitem} WHERE l_quantity >= 45 GROUP BY l_returnflag")
shared("proj_expr", "SELECT o_orderkey, round(o_totalprice * 1.1e0, 4) AS gross, o_orderkey % 7 AS slot FROM {orders}")
shared("filter_conj", "SELECT l_orderkey, l_linenumber FROM {lineitem} WHERE l_quantity BETWEEN 10 AND 20 AND l_discount >= 0.05 AND l_returnflag = 'R'")
shared("filter_disj", "SELECT o_orderkey FROM {orders} WHERE o_orderstatus = 'F' OR (o_totalprice > 400000 AND o_orderkey % 2 = 0)")
shared("filter_range", "SELECT p_partkey FROM {part} WHERE p_size > 10 AND p_size <= 20")
shared("filter_in", "SELECT c_custkey FROM {customer} WHERE c_mktsegment IN ('BUILDING', 'MACHINERY')")
shared("filter_like", "SELECT p_partkey, p_type FROM {part} WHERE p_type LIKE '%E%'")
shared("filter_null", "SELECT d.doc_id FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id WHERE l.toxic IS NULL")
# joins
shared("join_chain7", """SELECT r_name, count(*) AS n FROM {region} JOIN {nation} ON n_regionkey = r_regionkey JOIN {customer} ON c_nationkey = n_nationkey
JOIN {orders} ON o_custkey = c_custkey JOIN {lineitem} ON l_orderkey = o_orderkey JOIN {part} ON p_partkey = l_partkey JOIN {supplier} ON s_suppkey = l_suppkey
WHERE p_size <= 25 GROUP BY r_name""")
shared("join_star", "SELECT c_mktsegment, count(*) AS n FROM {customer} JOIN {orders} ON o_custkey = c_custkey JOIN {events} ON user_id = c_custkey GROUP BY c_mktsegment")
shared("join_self", "SELECT a.conv_id, count(*) AS n FROM {conversations} a JOIN {conversations} b ON a.conv_id = b.conv_id WHERE a.role = 'system' AND b.turn >= 2 GROUP BY a.conv_id")
shared("join_left", "SELECT d.doc_id, l.quality FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id")
shared("join_full_outer", "SELECT coalesce(p.page_id, b.item_id) AS id, p.page_id IS NULL AS no_page, b.item_id IS NULL AS no_item FROM {pages} p FULL OUTER JOIN {benchmark} b ON p.page_id = b.item_id")
shared("join_semi", "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
shared("join_anti", "SELECT c_custkey FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
shared("join_cross", "SELECT r_name, n_name FROM {region} CROSS JOIN {nation} WHERE n_nationkey < 3")
shared("join_theta", "SELECT a.n_name AS a, b.n_name AS b FROM {nation} a JOIN {nation} b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey")
shared("join_null_safe", "SELECT count(*) AS n FROM {documents} d JOIN {labels} l ON d.doc_id IS NOT DISTINCT FROM l.doc_id")
# aggregation
shared("agg_basic", "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 4) AS q, round(avg(l_discount), 6) AS d, min(l_tax) AS lo, max(l_tax) AS hi FROM {lineitem} GROUP BY l_returnflag")
shared("agg_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS n FROM {orders} GROUP BY o_orderstatus")
shared("agg_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY ROLLUP (l_returnflag, l_linestatus)")
shared("agg_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM {orders} GROUP BY CUBE (o_orderstatus, o_orderpriority)")
shared("agg_grouping_sets", "SELECT lang, source, count(*) AS n FROM {documents} GROUP BY GROUPING SETS ((lang), (source), ())")
shared("agg_having", "SELECT user_id, count(*) AS n FROM {events} GROUP BY user_id HAVING count(*) > 70")
shared("agg_pivot", "SELECT user_id, count(*) FILTER (WHERE event_type = 'view') AS views, count(*) FILTER (WHERE event_type = 'purchase') AS purchases FROM {events} GROUP BY user_id")
shared("agg_corr", "SELECT round(corr(l_quantity, l_extendedprice), 6) AS c, round(stddev_samp(l_quantity), 6) AS s FROM {lineitem}")
shared("agg_two_level", "SELECT b, max(n) AS top FROM (SELECT o_custkey, o_custkey % 16 AS b, count(*) AS n FROM {orders} GROUP BY o_custkey) t GROUP BY b")
# windows, order, sets
shared("win_rank", "SELECT c_custkey, rank() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r, dense_rank() OVER (PARTITION BY c_mktsegment ORDER BY c_nationkey) AS dr FROM {customer}")
shared("win_percent_rank", "SELECT p_partkey, round(percent_rank() OVER (ORDER BY p_size), 9) AS pr, round(cume_dist() OVER (ORDER BY p_size), 9) AS cd FROM {part}")
shared("win_lag", "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prev FROM {events}")
shared("win_running_sum", "SELECT o_orderkey, sum(o_orderkey % 10) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS s FROM {orders}")
shared("win_moving_avg", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS m FROM {events}")
shared("win_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderpriority ORDER BY o_orderkey RANGE BETWEEN 50 PRECEDING AND CURRENT ROW) AS n FROM {orders}")
shared("sort_limit", "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
shared("topk_global", "SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey ORDER BY n DESC, o_custkey LIMIT 10")
shared("topk_per_group", "SELECT b, o_custkey, n FROM (SELECT o_custkey % 8 AS b, o_custkey, count(*) AS n, row_number() OVER (PARTITION BY o_custkey % 8 ORDER BY count(*) DESC, o_custkey) AS rn FROM {orders} GROUP BY o_custkey) t WHERE rn <= 3")
shared("set_union", "SELECT o_custkey AS k FROM {orders} UNION SELECT user_id FROM {events}")
shared("set_intersect", "SELECT o_custkey AS k FROM {orders} INTERSECT SELECT user_id FROM {events}")
shared("set_except", "SELECT c_custkey AS k FROM {customer} EXCEPT SELECT user_id FROM {events}")
# predicates of selections
for _op, _cond in {"eq": "o_orderstatus = 'F'", "ne": "o_orderstatus <> 'F'", "lt": "o_totalprice < 100000", "ge": "o_totalprice >= 100000", "between": "o_totalprice BETWEEN 50000 AND 150000", "in": "o_orderpriority IN ('1-URGENT', '2-HIGH')", "not": "NOT (o_orderstatus = 'F' OR o_totalprice > 200000)", "null": "o_orderstatus IS NULL"}.items():

    def _pred(spark: SparkSession, d: str, cond: str = _cond) -> DataFrame:
        from ..functions.predicates import parse, to_column

        return table(spark, d, "orders").where(to_column(parse(cond))).agg(F.count("*").alias("n"))

    both(f"pred_{_op}", f"SELECT count(*) AS n FROM orders WHERE {_cond}")(_pred)


@both("join_inner_broadcast", "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def join_inner_broadcast(spark, d):
    return table(spark, d, "customer").join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")  # nation has 25 rows


@both("join_smj", "SELECT o_orderkey, count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey")
def join_smj(spark, d):
    return table(spark, d, "orders").hint("merge").join(table(spark, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderkey").agg(F.count("*").alias("n"))


@both("join_shuffle_hash", "SELECT count(*) AS n FROM part JOIN lineitem ON l_partkey = p_partkey WHERE p_size < 10")
def join_shuffle_hash(spark, d):
    return table(spark, d, "part").where("p_size < 10").hint("shuffle_hash").join(table(spark, d, "lineitem"), F.col("l_partkey") == F.col("p_partkey")).agg(F.count("*").alias("n"))


@both("join_range", "SELECT p.user_id, p.event_id, count(q.event_id) AS n FROM events p JOIN events q ON p.user_id = q.user_id AND q.ts > p.ts - INTERVAL 1 DAY AND q.ts <= p.ts WHERE p.event_type = 'purchase' GROUP BY 1, 2")
def join_range(spark, d):
    """Events of the day before each purchase: rows meet on user and day, so the range costs two equal joins, not a product."""
    e = table(spark, d, "events").select("user_id", "event_id", "event_type", "ts").withColumn("day", F.to_date("ts"))
    p = e.where("event_type = 'purchase'").withColumn("day", F.explode(F.array("day", F.date_sub("day", 1))))
    p = p.select("user_id", "day", F.col("event_id").alias("p_id"), F.col("ts").alias("p_ts"))
    near = p.join(e, ["user_id", "day"]).where((F.col("ts") > F.col("p_ts") - F.expr("INTERVAL 1 DAY")) & (F.col("ts") <= F.col("p_ts")))
    return near.groupBy("user_id", F.col("p_id").alias("event_id")).agg(F.count("*").alias("n"))


@both("join_asof", "SELECT o_orderkey, event_id FROM (SELECT o_orderkey, event_id, row_number() OVER (PARTITION BY o_orderkey ORDER BY ts DESC, event_id DESC) AS rn FROM orders JOIN events ON user_id = o_custkey AND ts <= o_orderdate) t WHERE rn = 1")
def join_asof(spark, d):
    """Last event before each order: one union and one window, no join."""
    e = table(spark, d, "events").select(F.col("user_id").alias("k"), "ts", "event_id", F.lit(None).cast("long").alias("o_orderkey"))
    o = table(spark, d, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("ts"), F.lit(None).cast("long").alias("event_id"), "o_orderkey")
    w = Window.partitionBy("k").orderBy("ts", F.col("o_orderkey").isNotNull(), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    found = e.unionByName(o).withColumn("event_id", F.last("event_id", ignorenulls=True).over(w))
    return found.where("o_orderkey IS NOT NULL AND event_id IS NOT NULL").select("o_orderkey", "event_id")


@both("agg_percentile", "SELECT o_orderpriority, quantile_cont(o_totalprice, 0.75) AS q FROM orders GROUP BY 1")
def agg_percentile(spark, d):
    return table(spark, d, "orders").groupBy("o_orderpriority").agg(F.percentile("o_totalprice", 0.75).alias("q"))


@both("fn_string", "SELECT p_partkey, upper(substr(p_type, 1, 4)) AS a, length(p_type) AS n, p_brand || '/' || p_type AS c FROM part")
def fn_string(spark, d):
    return table(spark, d, "part").select("p_partkey", F.upper(F.substring("p_type", 1, 4)).alias("a"), F.length("p_type").alias("n"), F.concat("p_brand", F.lit("/"), "p_type").alias("c"))


@both("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS d FROM orders")
def fn_date(spark, d):
    return table(spark, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.datediff("o_orderdate", F.lit("1995-01-01")).alias("d"))


@both("fn_math_bits", "SELECT o_orderkey, o_orderkey >> 3 AS s, o_orderkey // 7 AS q, greatest(o_orderkey % 5, o_custkey % 5) AS g FROM orders")
def fn_math_bits(spark, d):
    return table(spark, d, "orders").select("o_orderkey", F.shiftright("o_orderkey", 3).alias("s"), F.expr("o_orderkey DIV 7").alias("q"), F.greatest(F.col("o_orderkey") % 5, F.col("o_custkey") % 5).alias("g"))


@both("fn_array", "SELECT r_regionkey, len(list(n_nationkey)) AS n, list_sum(list(n_nationkey))::BIGINT AS s FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def fn_array(spark, d):
    g = table(spark, d, "nation").groupBy(F.col("n_regionkey").alias("r_regionkey")).agg(F.collect_list("n_nationkey").alias("a"))
    return g.select("r_regionkey", F.size("a").alias("n"), F.aggregate("a", F.lit(0).cast("long"), lambda x, y: x + y).alias("s"))


@both("fn_map", "SELECT n_nationkey, n_name AS v FROM nation")
def fn_map(spark, d):
    return table(spark, d, "nation").select("n_nationkey", F.element_at(F.map_from_arrays(F.array("n_nationkey"), F.array("n_name")), F.col("n_nationkey")).alias("v"))


@both("fn_json", "SELECT event_id, json_extract_string(props, '$.k')::INTEGER AS k FROM events")
def fn_json(spark, d):
    return table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))
