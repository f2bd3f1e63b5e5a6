"""Joins that the methods' users need and Spark has no operator for: as-of and range joins, by equality on buckets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Ids that a semi-join may send to every executor (16 bytes each); more are shuffled.
BROADCAST_IDS = 1_000_000


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, columns: list[str]) -> DataFrame:
    """Each left row with ``columns`` of the latest right row of the same key at or before it (null if none).

    Both sides are sorted once by key and time; no pairs are made. Among right rows of one time the greatest values win.
    """
    sides = left.columns
    a = left.select(F.col(key), F.col(at), F.lit(1).alias("__left"), F.struct(*sides).alias("__row"), *[F.lit(None).cast(right.schema[c].dataType).alias(f"__{c}") for c in columns])
    b = right.select(F.col(key), F.col(at), F.lit(0).alias("__left"), F.lit(None).cast(left.select(F.struct(*sides).alias("s")).schema["s"].dataType).alias("__row"), *[F.col(c).alias(f"__{c}") for c in columns])
    seen = F.when(F.col("__left") == 0, F.struct(*[F.col(f"__{c}").alias(c) for c in columns]))
    order = Window.partitionBy(key).orderBy(at, "__left", *[f"__{c}" for c in columns]).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return a.unionByName(b).withColumn("__last", F.last(seen, ignorenulls=True).over(order)).filter("__left = 1").select("__row.*", *[F.col(f"__last.{c}").alias(c) for c in columns])


def within(points: DataFrame, spans: DataFrame, key: str, at: str, start: Column, end: Column, width: float) -> DataFrame:
    """Points joined with spans of the same key that hold them (start <= at < end; numbers).

    Spans are cut into buckets of ``width``, so the join is an equality on (key, bucket) with the range as a residual; a
    point lies in one bucket, hence each pair comes once.
    """
    cut = spans.withColumn("__lo", start).withColumn("__hi", end).filter("__hi > __lo").withColumnRenamed(key, "__key")
    cut = cut.withColumn("__bucket", F.explode(F.sequence(F.floor(F.col("__lo") / width), F.floor(F.col("__hi") / width))))
    rows = points.withColumn("__b", F.floor(F.col(at) / width))
    return rows.join(cut, (F.col(key) == F.col("__key")) & (F.col("__b") == F.col("__bucket")) & (F.col(at) >= F.col("__lo")) & (F.col(at) < F.col("__hi"))).drop("__b", "__bucket", "__key", "__lo", "__hi")


def compare(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """One row: how many key rows only a has, only b has, and both have (method against method)."""
    x, y = a.select(*keys).distinct().withColumn("__a", F.lit(1)), b.select(*keys).distinct().withColumn("__b", F.lit(1))
    both = x.join(y, keys, "full")
    one = lambda c: F.count(F.when(c, 1))
    return both.agg(one(F.col("__b").isNull()).alias("only_a"), one(F.col("__a").isNull()).alias("only_b"), one(F.col("__a").isNotNull() & F.col("__b").isNotNull()).alias("both"))


def ids_semi(df: DataFrame, ids: DataFrame, key: str, bound: int = BROADCAST_IDS) -> DataFrame:
    """Rows of ``df`` whose ``key`` is in ``ids``: broadcast while a count proves the ids few, else shuffled."""
    few = ids.limit(bound + 1).count() <= bound
    return df.join(F.broadcast(ids) if few else ids, key, "left_semi")
