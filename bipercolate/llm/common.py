"""Helpers that several operators share: text batches, words, let-bindings, distributed prefix sums."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bipercolate.operators.joins import BROADCAST_IDS, ids_semi  # noqa: F401

#: Characters between words; the same set as bytes.split() uses.
BETWEEN_WORDS = r"\x09-\x0D\x20"
#: Rows and bytes of text that a Python worker handles at once.
ROWS_AT_ONCE, BYTES_AT_ONCE = 2048, 4 << 20


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def text_blocks(batch: pa.RecordBatch, column: str = "text") -> Iterator[tuple[int, list[bytes]]]:
    """``(first row, texts as UTF-8 bytes)`` for blocks of the batch of bounded size; null counts as empty."""
    texts = batch.column(column).cast(pa.large_binary())
    start = 0
    while start < len(texts):
        end, room = start, BYTES_AT_ONCE
        while end < len(texts) and end - start < ROWS_AT_ONCE and (room > 0 or end == start):
            value = texts[end]
            room -= len(value.as_buffer()) if value.is_valid else 0
            end += 1
        yield start, [x or b"" for x in texts.slice(start, end - start).to_pylist()]
        start = end


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)`` with ``value`` evaluated once, even where ``body`` uses it within lambdas."""
    return F.transform(F.array(value), body)[0]


def word_count(text: Column) -> Column:
    """Number of words ``[^\\x20\\x09-\\x0D]+``; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(rf"[^{BETWEEN_WORDS}]+")).cast("long"), F.lit(0).cast("long"))


def running_total(
    rows: DataFrame, group: list[str], order: list[Column], value: str, bucket: Column, out: str,
    light: DataFrame | None = None, light_value: str | None = None,
) -> DataFrame:
    """Add ``out``: the sum of ``value`` over the rows of the same group before this one, without one task per group.

    ``bucket`` is an integer that doesn't decrease along ``order``, and cuts a group into pieces of bounded size. Sums
    per (group, bucket) are made map-side, their prefix sums come from a table of one row per bucket, and the only
    windows over rows lie within a bucket. Group columns are never null. ``light`` has the same rows without their wide columns,
    for the sums.
    """
    keys = [*group, "__bucket"]
    sums = (rows if light is None else light).withColumn("__bucket", bucket).groupBy(*keys).agg(F.sum(light_value or value).alias("__sum"))
    earlier = Window.partitionBy(*group).orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select(*keys, F.coalesce(F.sum("__sum").over(earlier), F.lit(0)).alias("__earlier"))
    within = Window.partitionBy(*keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    inside = rows.withColumn("__bucket", bucket).withColumn("__within", F.coalesce(F.sum(value).over(within), F.lit(0)))
    return inside.join(sums, keys).withColumn(out, (F.col("__earlier") + F.col("__within")).cast("long")).drop("__bucket", "__within", "__earlier")
