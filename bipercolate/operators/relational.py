"""Relational building blocks around the methods, each as a query with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bipercolate.functions import sets
from bipercolate.operators import joins
from bipercolate.sources.workloads import GRAPHS, SQL, table


def _events(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"), "value")


def as_of(s: SparkSession, d: str) -> DataFrame:
    """Each purchase-like event with the latest view of its user before it."""
    seconds = _events(s, d).withColumn("at", F.unix_micros("ts"))
    kinds = seconds.agg(F.min("event_type").alias("k0"), F.max("event_type").alias("k1"))
    rows = seconds.join(F.broadcast(kinds), F.lit(True))
    left = rows.filter("event_type = k0").select("event_id", "user_id", "at")
    right = rows.filter("event_type = k1").select("user_id", "at", F.col("event_id").alias("latest"))
    return joins.as_of(left, right, "user_id", "at", ["latest"]).select("event_id", "latest")


def range_join(s: SparkSession, d: str) -> DataFrame:
    """Events in the hour after an event of the first type of the same user."""
    rows = _events(s, d).withColumn("at", F.unix_micros("ts") / F.lit(1e6))
    first = rows.join(F.broadcast(rows.agg(F.min("event_type").alias("k0"))), F.lit(True)).filter("event_type = k0").select("user_id", F.col("event_id").alias("opener"), F.col("at").alias("t0"))
    return joins.within(rows.select("event_id", "user_id", "at"), first, "user_id", "at", F.col("t0"), F.col("t0") + 3600.0, 3600.0).select("event_id", "opener")


def users_without_quarter(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "customer").select("c_custkey").join(GRAPHS["cust_quarter"](s, d), F.col("c_custkey") == F.col("u"), "left_anti")


def users_with_quarter(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "customer").select("c_custkey", "c_mktsegment").join(GRAPHS["cust_quarter"](s, d), F.col("c_custkey") == F.col("u"), "left_semi").groupBy("c_mktsegment").agg(F.count("*").alias("customers"))


def outer_counts(s: SparkSession, d: str) -> DataFrame:
    degree = GRAPHS["cust_brand"](s, d).groupBy("u").agg(F.count("*").alias("degree"))
    return table(s, d, "customer").join(degree, F.col("c_custkey") == F.col("u"), "left").select("c_custkey", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"))


def full_compare(s: SparkSession, d: str) -> DataFrame:
    g = GRAPHS["user_day"](s, d)
    return joins.compare(g.filter("u % 3 <> 0"), g.filter("u % 2 = 0"), ["u", "v"])


def cube_counts(s: SparkSession, d: str) -> DataFrame:
    rows = table(s, d, "documents").cube("lang", "source").agg(F.count("*").alias("documents"), F.grouping_id().cast("long").alias("level"))
    return rows


def rollup_counts(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("items"))


def pivoted(s: SparkSession, d: str) -> DataFrame:
    rows = table(s, d, "orders").groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "5-LOW"]).agg(F.count(F.lit(1)))
    return rows.select("o_orderstatus", F.coalesce(F.col("1-URGENT"), F.lit(0)).alias("urgent"), F.coalesce(F.col("5-LOW"), F.lit(0)).alias("low"))


def ranks(s: SparkSession, d: str) -> DataFrame:
    degree = GRAPHS["cust_quarter"](s, d).groupBy("v").agg(F.count("*").alias("degree"))
    w = Window.orderBy(F.desc("degree"), "v")  # one row per quarter
    return degree.select(F.col("v").cast("string").alias("v"), F.row_number().over(w).alias("place"), F.dense_rank().over(Window.orderBy(F.desc("degree"))).alias("dense"), F.ntile(4).over(w).alias("quartile"))


def changes(s: SparkSession, d: str) -> DataFrame:
    """Users of each day against the day before: temporal evolution of a graph."""
    daily = GRAPHS["user_day"](s, d).groupBy("v").agg(F.count("*").alias("users"))
    w = Window.orderBy("v")  # one row per day
    return daily.select(F.col("v").cast("string").alias("v"), "users", F.lag("users").over(w).alias("before"), F.sum("users").over(w.rowsBetween(-6, 0)).alias("week"))


def top_per_group(s: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return table(s, d, "part").withColumn("place", F.row_number().over(w)).filter("place <= 2").select("p_brand", "p_partkey", "place")


def set_algebra(s: SparkSession, d: str) -> DataFrame:
    a = GRAPHS["cust_priority"](s, d).select("u").distinct()
    b = GRAPHS["cust_brand"](s, d).select("u").distinct()
    one = lambda x, name: x.agg(F.count("*").alias("n")).select(F.lit(name).alias("what"), "n")
    return one(a.intersect(b), "both").union(one(a.exceptAll(b), "first only")).union(one(a.union(b), "all"))


def bitmaps(s: SparkSession, d: str) -> DataFrame:
    """Distinct users per event type as bitmaps over ids from 1."""
    rows = _events(s, d).select("event_type",  (F.col("user_id") + 1).alias("id"))
    parts = rows.groupBy("event_type", F.bitmap_bucket_number("id").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("id")).alias("bits"))
    return parts.groupBy("event_type").agg(F.sum(F.bitmap_count("bits")).alias("users"))


def json_edges(s: SparkSession, d: str) -> DataFrame:
    from bipercolate.sources.edges import json_key

    return json_key(table(s, d, "events"), "user_id", "props", "k").groupBy("v").agg(F.count("*").alias("users"))


def sessions(s: SparkSession, d: str) -> DataFrame:
    rows = _events(s, d).groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count("*").alias("n"))
    return rows.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


def tumbling(s: SparkSession, d: str) -> DataFrame:
    rows = _events(s, d).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.countDistinct("user_id").alias("users"))
    return rows.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "event_type", "users")


def k_subsets(s: SparkSession, d: str) -> DataFrame:
    lists = GRAPHS["nation_brand"](s, d).groupBy("u").agg(F.array_sort(F.collect_set("v")).alias("vs"))
    return sets.k_subsets(lists, "vs", 2).groupBy("subset").agg(F.count("*").alias("n")).select(F.array_join("subset", ",").alias("pair"), "n").filter("n >= 5")


_G = lambda name: f"({SQL[name]})"
CATALOGUE = {
    "as_of_join": (as_of, "WITH k AS (SELECT min(event_type) AS k0, max(event_type) AS k1 FROM events) SELECT l.event_id, (SELECT r.event_id FROM events r WHERE r.event_type = k1 AND r.user_id = l.user_id AND r.ts <= l.ts ORDER BY r.ts DESC, r.event_id DESC LIMIT 1) AS latest FROM events l, k WHERE l.event_type = k0"),
    "range_join": (range_join, "WITH k AS (SELECT min(event_type) AS k0 FROM events) SELECT e.event_id, o.event_id AS opener FROM events e JOIN events o ON e.user_id = o.user_id AND e.ts >= o.ts AND e.ts < o.ts + INTERVAL 1 HOUR, k WHERE o.event_type = k0"),
    "anti_join": (users_without_quarter, f"SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT u FROM {_G('cust_quarter')})"),
    "semi_join": (users_with_quarter, f"SELECT c_mktsegment, count(*) AS customers FROM customer WHERE c_custkey IN (SELECT u FROM {_G('cust_quarter')}) GROUP BY 1"),
    "left_outer": (outer_counts, f"SELECT c_custkey, coalesce(degree, 0) AS degree FROM customer LEFT JOIN (SELECT u, count(*) AS degree FROM {_G('cust_brand')} GROUP BY 1) ON c_custkey = u"),
    "full_compare": (full_compare, f"WITH g AS {_G('user_day')} SELECT count(*) FILTER (b IS NULL) AS only_a, count(*) FILTER (a IS NULL) AS only_b, count(*) FILTER (a IS NOT NULL AND b IS NOT NULL) AS both FROM (SELECT u, v, 1 AS a FROM g WHERE u % 3 <> 0) FULL JOIN (SELECT u, v, 1 AS b FROM g WHERE u % 2 = 0) USING (u, v)"),
    "cube": (cube_counts, "SELECT lang, source, count(*) AS documents, grouping_id(lang, source) AS level FROM documents GROUP BY CUBE (lang, source)"),
    "rollup": (rollup_counts, "SELECT l_returnflag, l_linestatus, count(*) AS items FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)"),
    "pivot": (pivoted, "SELECT o_orderstatus, count(*) FILTER (o_orderpriority = '1-URGENT') AS urgent, count(*) FILTER (o_orderpriority = '5-LOW') AS low FROM orders GROUP BY 1"),
    "ranks": (ranks, f"SELECT strftime(v, '%Y-%m-%d %H:%M:%S') AS v, row_number() OVER (ORDER BY degree DESC, v) AS place, dense_rank() OVER (ORDER BY degree DESC) AS dense, ntile(4) OVER (ORDER BY degree DESC, v) AS quartile FROM (SELECT v, count(*) AS degree FROM {_G('cust_quarter')} GROUP BY 1)"),
    "changes": (changes, f"SELECT CAST(v AS VARCHAR) AS v, users, lag(users) OVER (ORDER BY v) AS before, sum(users) OVER (ORDER BY v ROWS BETWEEN 6 PRECEDING AND CURRENT ROW)::BIGINT AS week FROM (SELECT v, count(*) AS users FROM {_G('user_day')} GROUP BY 1)"),
    "top_per_group": (top_per_group, "SELECT p_brand, p_partkey, place FROM (SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS place FROM part) WHERE place <= 2"),
    "set_algebra": (set_algebra, f"WITH a AS (SELECT DISTINCT u FROM {_G('cust_priority')}), b AS (SELECT DISTINCT u FROM {_G('cust_brand')}) SELECT 'both' AS what, count(*) AS n FROM (SELECT u FROM a INTERSECT SELECT u FROM b) UNION ALL SELECT 'first only', count(*) FROM (SELECT u FROM a EXCEPT SELECT u FROM b) UNION ALL SELECT 'all', count(*) FROM (SELECT u FROM a UNION ALL SELECT u FROM b)"),
    "bitmaps": (bitmaps, "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1"),
    "json_edges": (json_edges, "SELECT json_extract_string(props, '$.k') AS v, count(DISTINCT user_id) AS users FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY 1"),
    "session_windows": (sessions, "SELECT user_id, count(*) FILTER (fresh) AS sessions, count(*) AS events FROM (SELECT user_id, coalesce(ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE, true) AS fresh FROM events) GROUP BY 1"),
    "tumbling_windows": (tumbling, "SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1, 2"),
    "k_subsets": (k_subsets, f"WITH e AS {_G('nation_brand')} SELECT a.v || ',' || b.v AS pair, count(*) AS n FROM e a JOIN e b ON a.u = b.u AND a.v < b.v GROUP BY 1 HAVING count(*) >= 5"),
}
