"""Set expressions and their table forms."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def contains_all(outer: Column | str, inner: Column | str) -> Column:
    return F.size(F.array_except(inner, outer)) == 0


def share_at_least(a: Column | str, b: Column | str, n: int) -> Column:
    return F.size(F.array_intersect(a, b)) >= n


def canonical(x: Column | str) -> Column:
    """A set as one string, whatever the order of the array."""
    return F.array_join(F.array_sort(F.transform(x, lambda v: v.cast("string"))), ",")


def k_subsets(df: DataFrame, column: str, k: int, out: str = "subset") -> DataFrame:
    """``df`` without ``column``, once for each subset of k elements of it, in ascending array order."""
    others = [c for c in df.columns if c != column]
    kind = df.schema[column].dataType.simpleString()
    rows = df.select(*others, F.array().cast(kind).alias(out), F.col(column).alias("__rest"))
    for done in range(k):
        rows = rows.select(*others, out, "__rest", F.posexplode("__rest").alias("__at", "__v")).select(*others, F.concat(out, F.array("__v")).alias(out), F.expr("slice(__rest, __at + 2, greatest(size(__rest) - __at - 1, 0))").alias("__rest")).filter(F.size("__rest") >= k - done - 1)
    return rows.drop("__rest")
