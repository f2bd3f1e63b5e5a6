"""Edge tables from ordinary tables, files and text."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from bipercolate.checkpoints import cut
from bipercolate.operators.joins import ids_semi

EDGE_SCHEMA = "u string, v string"


def edges(df: DataFrame, u: str | Column, v: str | Column, min_count: int = 1, where: str | Column | None = None, least_keys: int = 1) -> DataFrame:
    """Distinct ``[u, v]`` with no nulls; ``where`` filters rows first (and reaches the scan), ``min_count`` keeps pairs seen so often.

    ``least_keys`` drops values that fewer keys have, before any value is shuffled. They are counted by 64-bit hashes: where two clash, both may stay.
    """
    rows = df if where is None else df.filter(where)
    col = lambda x: F.col(x) if isinstance(x, str) else x
    pairs = rows.select(col(u).alias("u"), col(v).alias("v")).filter("u is not null and v is not null")
    if least_keys > 1:
        common = pairs.select("u", F.xxhash64("v").alias("h")).distinct().groupBy("h").agg(F.count("*").alias("n")).filter(F.col("n") >= least_keys)
        pairs = ids_semi(pairs.withColumn("h", F.xxhash64("v")), cut(common.select("h")), "h").select("u", "v")
    if min_count <= 1:
        return pairs.distinct()
    return pairs.groupBy("u", "v").agg(F.count("*").alias("n")).filter(F.col("n") >= min_count).select("u", "v")


def read_edges(spark: SparkSession, path: str, format: str = "csv", sep: str = "\t", comment: str = "%", schema: str = EDGE_SCHEMA) -> DataFrame:
    """Edge lists in csv, json, orc or parquet files, with a stated schema; text lists may have comment lines."""
    reader = spark.read.schema(schema).format(format)
    if format == "csv":
        reader = reader.option("sep", sep).option("comment", comment)
    return edges(reader.load(path), "u", "v")


def lines(df: DataFrame, key: str, text: str = "text", min_length: int = 20, least_keys: int = 1) -> DataFrame:
    """key - trimmed line of at least ``min_length`` characters."""
    rows = df.select(F.col(key).alias("u"), F.explode(F.split(text, "\n", -1)).alias("line")).select("u", F.trim("line").alias("v"))
    return edges(rows, "u", "v", where=F.length("v") >= min_length, least_keys=least_keys)


def words(df: DataFrame, key: str, text: str = "text", min_length: int = 1, most_keys: int | None = None) -> DataFrame:
    """key - lower-cased word between spaces; ``most_keys`` drops words that more keys have."""
    rows = edges(df.select(F.col(key).alias("u"), F.explode(F.split(F.lower(text), " ", -1)).alias("v")), "u", "v", where=F.length("v") >= min_length)
    if most_keys is None:
        return rows
    common = rows.groupBy("v").agg(F.count("*").alias("n")).filter(F.col("n") > most_keys).select("v")
    return rows.join(common, "v", "left_anti").select("u", "v")


def links(df: DataFrame, key: str, html: str = "html", least_keys: int = 1) -> DataFrame:
    """key - target of each href attribute."""
    found = F.regexp_extract_all(html, F.lit('href="([^"]*)"'), F.lit(1))
    return edges(df.select(F.col(key).alias("u"), F.explode(found).alias("v")), "u", "v", least_keys=least_keys)


def json_key(df: DataFrame, key: str, column: str, name: str) -> DataFrame:
    """key - value of a JSON field, as a string."""
    return edges(df, key, F.get_json_object(column, f"$.{name}"))


def strong_dims(df: DataFrame, key: str, vector: str, above: float) -> DataFrame:
    """key - position (from 1) of the vector's components beyond ``above`` in size."""
    rows = df.select(F.col(key).alias("u"), F.posexplode(vector).alias("at", "value"))
    return edges(rows, "u", (F.col("at") + 1).cast("int"), where=F.abs("value") > above)


def time_buckets(df: DataFrame, key: str, ts: str, unit: str, min_count: int = 1) -> DataFrame:
    """key - start of the day, hour, quarter ... with at least so many rows."""
    return edges(df, key, F.date_trunc(unit, ts), min_count)
