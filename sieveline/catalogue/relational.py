"""The relational surface that users of the methods need, as plain plans with SQL twins."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..workloads.inputs import table
from .registry import QUERIES, SQL, query


def both(name: str, sql: str, spark_sql: str | None = None) -> None:
    """A query whose Spark plan comes from SQL over the same tables."""

    def run(spark, sf):
        import re

        text = spark_sql or sql
        for t in set(re.findall(r"\b(?:FROM|JOIN) ([a-z]+)\b", text)):
            table(spark, sf, t).createOrReplaceTempView(t)
        return spark.sql(text)

    run.__name__ = name
    QUERIES[name], SQL[name] = run, sql


both("rel_join_full", "SELECT c_custkey, s_suppkey FROM customer FULL JOIN supplier ON c_custkey = s_suppkey * 3")
both("rel_join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 100000)")
both("rel_join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM events WHERE user_id = c_custkey AND event_type = 'purchase')")
both("rel_join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey")
both("rel_join_lateral", "SELECT c_custkey, o.o_orderkey FROM customer, LATERAL (SELECT max(o_orderkey) AS o_orderkey FROM orders WHERE o_custkey = c_custkey) o")
both("rel_rollup", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
both("rel_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
both("rel_grouping_sets", "SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_type), ())")
both("rel_agg_filter", "SELECT event_type, count(*) FILTER (WHERE value > 50) AS high, count(*) AS n FROM events GROUP BY event_type")
both("rel_agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
both("rel_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey AS k FROM supplier")
both("rel_except", "SELECT c_nationkey, c_mktsegment FROM customer EXCEPT SELECT c_nationkey, c_mktsegment FROM customer JOIN orders ON c_custkey = o_custkey WHERE o_orderpriority = '1-URGENT' AND o_totalprice > 450000")
both("rel_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey AS k FROM supplier")
both("rel_win_rank", "SELECT o_custkey, o_orderkey, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC) AS r FROM orders")
both("rel_win_lag_lead", "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS after FROM events")
both("rel_win_sliding", "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS top FROM events")
both("rel_win_ntile", "SELECT o_orderkey, ntile(4) OVER (PARTITION BY o_orderstatus ORDER BY o_orderkey) AS q FROM orders")
both("rel_win_first_last", "SELECT DISTINCT user_id, first_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS first_id FROM events")
both("rel_topk", "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 10")
both("rel_offset", "SELECT p_partkey FROM part ORDER BY p_partkey LIMIT 10 OFFSET 5")
both("rel_str_functions", "SELECT p_partkey, upper(p_name) AS u, replace(p_name, ' ', '-') AS r, levenshtein(p_name, p_brand) AS d FROM part")
both("rel_math_functions", "SELECT s_suppkey, floor(s_acctbal) AS f, sign(s_acctbal) AS s, greatest(s_acctbal, 0) AS g FROM supplier", "SELECT s_suppkey, cast(floor(s_acctbal) AS double) AS f, cast(sign(s_acctbal) AS tinyint) AS s, greatest(s_acctbal, 0) AS g FROM supplier")


@query("SELECT event_id, value FROM events WHERE event_type = 'purchase' AND value > 50")
def rel_filter_pushdown(spark, sf):
    return table(spark, sf, "events").filter((F.col("event_type") == "purchase") & (F.col("value") > 50)).select("event_id", "value")


@query("SELECT event_id, (props::JSON->>'k')::BIGINT AS k FROM events")
def rel_json_props(spark, sf):
    return table(spark, sf, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@query("SELECT l_orderkey, count(*)::BIGINT AS n, max(l_quantity) AS top FROM lineitem GROUP BY 1")
def rel_nested_struct(spark, sf):
    nested = table(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.collect_list(F.struct("l_partkey", "l_quantity")).alias("lines"))
    return nested.select("l_orderkey", F.size("lines").cast("long").alias("n"), F.array_max("lines.l_quantity").alias("top"))


@query("SELECT e.event_id, (SELECT max(o.event_id) FROM events o WHERE o.user_id = e.user_id AND o.event_type = 'purchase' AND (o.ts, o.event_id) = (SELECT max((p.ts, p.event_id)) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND (p.ts, p.event_id) < (e.ts, e.event_id))) AS purchase FROM events e WHERE e.event_type = 'error'")
def rel_join_asof(spark, sf):
    """The latest purchase before each error of a user: one window over the union, no join."""
    e = table(spark, sf, "events").filter("event_type in ('error', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("purchase", last).filter("event_type = 'error'").select("event_id", "purchase")


@query("SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_type = 'purchase' AND a.event_type = 'click' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def rel_join_interval(spark, sf):
    """Range join in six-hour bins: each click looks into its own bin and the next."""
    e = table(spark, sf, "events")
    seconds = F.unix_seconds(F.col("ts").cast("timestamp"))
    a = e.filter("event_type = 'click'").select(F.col("event_id").alias("a_id"), "user_id", F.col("ts").alias("a_ts"), F.explode(F.array(F.floor(seconds / 21600), F.floor(seconds / 21600) + 1)).alias("bin"))
    b = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("b_id"), "user_id", F.col("ts").alias("b_ts"), F.floor(seconds / 21600).alias("bin"))
    hit = (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr("INTERVAL 6 HOURS"))
    return a.join(b, ["user_id", "bin"]).filter(hit).select("a_id", "b_id")


@query("SELECT c_mktsegment, count(*) FILTER (WHERE c_nationkey < 10)::BIGINT AS low, count(*) FILTER (WHERE c_nationkey >= 10)::BIGINT AS high FROM customer GROUP BY 1")
def rel_agg_pivot(spark, sf):
    c = table(spark, sf, "customer").withColumn("part", F.when(F.col("c_nationkey") < 10, "low").otherwise("high"))
    return c.groupBy("c_mktsegment").pivot("part", ["low", "high"]).count().fillna(0)


@query("SELECT o_custkey, string_agg(o_orderkey::VARCHAR, ',' ORDER BY o_orderkey) AS keys FROM orders GROUP BY 1")
def rel_listagg(spark, sf):
    rows = F.array_sort(F.collect_list("o_orderkey"))
    return table(spark, sf, "orders").groupBy("o_custkey").agg(F.array_join(F.transform(rows, lambda x: x.cast("string")), ",").alias("keys"))


@query()
def rel_approx_distinct(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"))


@query("SELECT n_name, c_custkey FROM customer JOIN nation ON c_nationkey = n_nationkey")
def rel_join_small_side(spark, sf):
    """Spark broadcasts the nation table because its files are small; nothing is forced."""
    return table(spark, sf, "customer").join(table(spark, sf, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).select("n_name", "c_custkey")


@query("SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*)::BIGINT AS n FROM orders GROUP BY 1")
def rel_date_functions(spark, sf):
    return table(spark, sf, "orders").groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("n"))
