"""Token ids as Parquet list columns: sorted files, controlled row groups and pages, selective reads.

``write`` deals documents out by range of doc_id and sorts them, encodes them where they land, and writes one file per
range with Spark's Parquet writer: ids dictionary-encoded (delta-encoded with ``delta``), row groups and pages of set
sizes, page indexes and checksums. ``metadata`` reads doc_id and n_tokens only, never the ids; ``slices`` reads the ids
of a range of documents, which row-group and page statistics on doc_id narrow down.

Null texts are empty documents (the end id alone); a null doc_id sorts first; rows that repeat a doc_id are each a
document, in no set order among themselves; no rows make no files, and reads then return no rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bipercolate.checkpoints import shared_path
from bipercolate.llm.common import text_blocks
from bipercolate.llm.tokens import byte_encoder, vocabulary

SCHEMA = "doc_id long, n_tokens int, ids array<int>"
CRC_SCHEMA = "doc_id long, file string, row long, n_tokens long, ids_crc32 long"


def encoder(vocabulary_path: str, end_id: int):
    """For mapInArrow: ``doc_id, text`` to ``doc_id, n_tokens, ids``."""
    end = end_id.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = byte_encoder(vocabulary_path).encode
        for batch in batches:
            for start, texts in text_blocks(batch):
                packed = [x + end for x in encode(texts)]
                sizes = pa.array([len(x) // 4 for x in packed], pa.int32())
                offsets = [0]
                for x in packed:
                    offsets.append(offsets[-1] + len(x) // 4)
                values = pa.Array.from_buffers(pa.int32(), offsets[-1], [None, pa.py_buffer(b"".join(packed))])
                ids = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), values)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(start, len(texts)), sizes, ids], ["doc_id", "n_tokens", "ids"])

    return run


def write(docs: DataFrame, path: str, vocabulary_path: str | None = None, end_id: int = 0, files: int | None = None, row_group_bytes: int = 64 << 20, page_bytes: int = 256 << 10, delta: bool = False) -> None:
    """Encode ``docs`` (doc_id, text) and write them to ``path`` in ascending doc_id order, file after file."""
    spark = docs.sparkSession
    n = files or int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).repartitionByRange(n, "doc_id").sortWithinPartitions("doc_id")
    (
        rows.mapInArrow(encoder(vocabulary_path or vocabulary("byte_bpe_50k.json"), end_id), SCHEMA)
        .write.option("parquet.block.size", row_group_bytes)
        .option("parquet.page.size", page_bytes)
        .option("parquet.enable.dictionary", str(not delta).lower())
        .option("parquet.writer.version", "PARQUET_2_0" if delta else "PARQUET_1_0")
        .option("parquet.page.write-checksum.enabled", "true")
        .option("compression", "zstd")
        .parquet(path)
    )


def read(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(SCHEMA).parquet(path)


def metadata(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, n_tokens, and start: the ids of all documents before. Reads no ids."""
    rows = read(spark, path).select("doc_id", F.col("n_tokens").cast("long"), F.col("_metadata.file_name").alias("file"), F.col("_metadata.row_index").alias("row"))
    return _starts(rows, rows)


def slices(spark: SparkSession, path: str, first: int, last: int) -> DataFrame:
    """Documents with first <= doc_id <= last; other row groups and pages are skipped by their statistics."""
    return read(spark, path).filter(F.col("doc_id").between(first, last))


def _starts(rows: DataFrame, sizes: DataFrame) -> DataFrame:
    """Add ``start`` to rows(doc_id, n_tokens, file, row). Files follow doc_id by the number in their names, rows by their index.

    One row per file is summed, running-summed and broadcast: as many rows as there are files, whatever the data.
    """
    number = F.regexp_extract("f", r"^part-(\d+)", 1).cast("long")  # names have five digits or more, so they don't sort as text
    before = Window.orderBy(number, "f").rowsBetween(Window.unboundedPreceding, -1)
    files = sizes.groupBy(F.col("file").alias("f")).agg(F.sum("n_tokens").alias("s")).select("f", F.coalesce(F.sum("s").over(before), F.lit(0)).alias("before"))
    within = Window.partitionBy("file").orderBy("row").rowsBetween(Window.unboundedPreceding, -1)
    return (
        rows.withColumn("within", F.coalesce(F.sum("n_tokens").over(within), F.lit(0)))
        .join(F.broadcast(files), F.col("file") == F.col("f"))
        .withColumn("start", (F.col("before") + F.col("within")).cast("long"))
        .drop("f", "before", "within", "file", "row")
    )


def _checksums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids = batch.column("ids")
        offsets = ids.offsets.to_numpy()
        values = memoryview(ids.values.to_numpy().view("u1"))
        crc = [zlib.crc32(values[4 * a : 4 * b]) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
        sizes = pa.array(offsets[1:] - offsets[:-1], pa.int64())
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("file"), batch.column("row"), sizes, pa.array(crc, pa.int64())], ["doc_id", "file", "row", "n_tokens", "ids_crc32"])


def verified(spark: SparkSession, path: str) -> DataFrame:
    """Read every id back: doc_id, start, n_tokens, ids_crc32 (of the ids as little-endian unsigned 32-bit integers)."""
    back = read(spark, path).select("doc_id", "ids", F.col("_metadata.file_name").alias("file"), F.col("_metadata.row_index").alias("row"))
    sizes = read(spark, path).select("n_tokens", F.col("_metadata.file_name").alias("file"))
    return _starts(back.mapInArrow(_checksums, CRC_SCHEMA), sizes)


def round_trip(docs: DataFrame, **options) -> DataFrame:
    """Write ``docs`` to a new shared folder and read them back."""
    path = shared_path(docs.sparkSession, "token-files")
    write(docs, path, **options)
    return verified(docs.sparkSession, path)
