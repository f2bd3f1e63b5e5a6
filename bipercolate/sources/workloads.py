"""Graphs over the given tables, by name."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bipercolate.sources import edges as source

DEFAULT_ALPHA = DEFAULT_BETA = 4
ALPHAS = BETAS = (2, 4, 6, 8)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def doc_line(spark: SparkSession, d: str, least_keys: int = 1) -> DataFrame:
    return source.lines(table(spark, d, "documents"), "doc_id", least_keys=least_keys)


def _bought(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").join(table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))


def cust_brand(spark: SparkSession, d: str) -> DataFrame:
    rows = _bought(spark, d).join(table(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey"))
    return source.edges(rows, "o_custkey", "p_brand", min_count=4)


def user_day(spark: SparkSession, d: str) -> DataFrame:
    return source.edges(table(spark, d, "events"), "user_id", F.to_date("ts"), min_count=4)


def cust_quarter(spark: SparkSession, d: str) -> DataFrame:
    return source.time_buckets(table(spark, d, "orders"), "o_custkey", "o_orderdate", "quarter", min_count=2)


def bench_word(spark: SparkSession, d: str) -> DataFrame:
    return source.words(table(spark, d, "benchmark"), "item_id")


def vec_dim(spark: SparkSession, d: str) -> DataFrame:
    return source.strong_dims(table(spark, d, "embeddings"), "vec_id", "embedding", 0.25)


def page_link(spark: SparkSession, d: str, least_keys: int = 1) -> DataFrame:
    return source.links(table(spark, d, "pages"), "page_id", least_keys=least_keys)


def order_part(spark: SparkSession, d: str) -> DataFrame:
    return source.edges(table(spark, d, "lineitem"), "l_orderkey", "l_partkey")


def nation_brand(spark: SparkSession, d: str) -> DataFrame:
    """Cells of nation and brand with more than 1.2 times the mean number of line items, compared in whole numbers."""
    rows = table(spark, d, "lineitem").join(table(spark, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    rows = rows.join(table(spark, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(table(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey"))
    cells = rows.groupBy(F.col("n_name").alias("u"), F.col("p_brand").alias("v")).agg(F.count("*").alias("k"))
    return _above_mean(cells)


def _above_mean(cells: DataFrame) -> DataFrame:
    """Cells [u, v, k] with more than 1.2 times the mean count, compared in whole numbers."""
    total = cells.agg(F.count("*").alias("cells"), F.sum("k").alias("total"))  # one row
    return cells.join(F.broadcast(total), F.lit(True)).filter(5 * F.col("k") * F.col("cells") > 6 * F.col("total")).select("u", "v")


def nation_segment(spark: SparkSession, d: str) -> DataFrame:
    """Cells of nation and market segment with more than 1.2 times the mean number of customers: small enough for the plain tree."""
    rows = table(spark, d, "customer").join(table(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    return _above_mean(rows.groupBy(F.col("n_name").alias("u"), F.col("c_mktsegment").alias("v")).agg(F.count("*").alias("k")))


def user_hour(spark: SparkSession, d: str) -> DataFrame:
    return source.time_buckets(table(spark, d, "events"), "user_id", "ts", "hour")


def cust_priority(spark: SparkSession, d: str) -> DataFrame:
    return source.edges(table(spark, d, "orders"), "o_custkey", "o_orderpriority")


def part_supp_returned(spark: SparkSession, d: str) -> DataFrame:
    return source.edges(table(spark, d, "lineitem"), "l_partkey", "l_suppkey", where="l_returnflag = 'R' and l_quantity >= 45")


def conv_word(spark: SparkSession, d: str) -> DataFrame:
    return source.words(table(spark, d, "conversations"), "conv_id", min_length=6, most_keys=10)


def doc_label(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id")
    values = F.array(F.concat(F.lit("q="), F.col("quality").cast("string")), F.concat(F.lit("t="), F.col("toxic").cast("string")), F.concat(F.lit("lang="), "lang"), F.concat(F.lit("src="), "source"))
    return source.edges(rows.select(F.col("doc_id").alias("u"), F.explode(values).alias("v")), "u", "v")


def cust_region(spark: SparkSession, d: str) -> DataFrame:
    rows = _bought(spark, d).join(table(spark, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(table(spark, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey"))
    return source.edges(rows.join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")), "o_custkey", "r_name")


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (doc_line, cust_brand, user_day, cust_quarter, bench_word, vec_dim, page_link, order_part, nation_brand, user_hour, cust_priority, part_supp_returned, conv_word, doc_label, cust_region, nation_segment)
}

#: Graphs most of whose right labels are long and belong to one left vertex; they take ``least_keys``.
SPARSE = ("doc_line", "page_link")

#: The same graphs in SQL, for the oracle.
SQL = {
    "doc_line": r"SELECT DISTINCT doc_id AS u, trim(line) AS v FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(trim(line)) >= 20",
    "cust_brand": "SELECT o_custkey AS u, p_brand AS v FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN part ON l_partkey = p_partkey GROUP BY ALL HAVING count(*) >= 4",
    "user_day": "SELECT user_id AS u, CAST(ts AS DATE) AS v FROM events GROUP BY ALL HAVING count(*) >= 4",
    "cust_quarter": "SELECT o_custkey AS u, CAST(date_trunc('quarter', o_orderdate) AS TIMESTAMP) AS v FROM orders GROUP BY ALL HAVING count(*) >= 2",
    "bench_word": "SELECT DISTINCT item_id AS u, v FROM (SELECT item_id, unnest(string_split(lower(text), ' ')) AS v FROM benchmark) WHERE length(v) >= 1",
    "vec_dim": "SELECT DISTINCT vec_id AS u, i AS v FROM (SELECT vec_id, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS i FROM embeddings) WHERE abs(x) > 0.25",
    "page_link": """SELECT DISTINCT page_id AS u, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS v FROM pages""",
    "order_part": "SELECT DISTINCT l_orderkey AS u, l_partkey AS v FROM lineitem",
    "nation_brand": "SELECT u, v FROM (SELECT n_name AS u, p_brand AS v, count(*) AS k, count(*) OVER () AS cells, sum(count(*)) OVER () AS total FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN part ON l_partkey = p_partkey GROUP BY ALL) WHERE 5 * k * cells > 6 * total",
    "user_hour": "SELECT DISTINCT user_id AS u, date_trunc('hour', ts) AS v FROM events",
    "cust_priority": "SELECT DISTINCT o_custkey AS u, o_orderpriority AS v FROM orders",
    "part_supp_returned": "SELECT DISTINCT l_partkey AS u, l_suppkey AS v FROM lineitem WHERE l_returnflag = 'R' AND l_quantity >= 45",
    "conv_word": "WITH w AS (SELECT DISTINCT conv_id AS u, v FROM (SELECT conv_id, unnest(string_split(lower(text), ' ')) AS v FROM conversations) WHERE length(v) >= 6) SELECT u, v FROM w WHERE v IN (SELECT v FROM w GROUP BY v HAVING count(*) <= 10)",
    "doc_label": "SELECT DISTINCT doc_id AS u, unnest(['q=' || quality, 't=' || toxic, 'lang=' || lang, 'src=' || source]) AS v FROM documents JOIN labels USING (doc_id)",
    "cust_region": "SELECT DISTINCT o_custkey AS u, r_name AS v FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
    "nation_segment": """SELECT u, v FROM (SELECT n_name AS u, c_mktsegment AS v, count(*) AS k, count(*) OVER () AS cells, sum(count(*)) OVER () AS total
        FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2) WHERE 5 * k * cells > 6 * total""",
}
