"""Where results go: partitioned or bucketed Parquet, and nothing (for timing)."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write(df: DataFrame, path: str, partition_by: tuple[str, ...] = (), mode: str = "error", format: str = "parquet") -> None:
    df.write.format(format).mode(mode).partitionBy(*partition_by).save(path)


def write_bucketed(df: DataFrame, table: str, by: str, buckets: int) -> None:
    """A table whose joins on ``by`` need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def consume(df: DataFrame) -> None:
    """Compute every row and column, and keep nothing."""
    df.write.format("noop").mode("overwrite").save()
