"""Graphs from streams: windows, late rows, duplicates, vertex state, incremental communities."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from bipercolate.checkpoints import cut
from bipercolate.cohesive import vertex_components


def read_events(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    """A file stream in order of arrival; the schema is stated, never inferred."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def windowed_edges(events: DataFrame, u: str, v: str, ts: str = "ts", width: str = "7 days", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """``[start, u, v, n]``: one graph per window; rows later than the watermark are dropped."""
    rows = events.filter(F.col(u).isNotNull() & F.col(v).isNotNull()).withWatermark(ts, late)
    w = F.window(ts, width, slide) if slide else F.window(ts, width)
    return rows.groupBy(w.alias("w"), F.col(u).alias("u"), F.col(v).alias("v")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "u", "v", "n")


def session_edges(events: DataFrame, u: str, ts: str = "ts", gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    """``[u, start, end, n]``: a user's sessions as right vertices."""
    rows = events.filter(F.col(u).isNotNull()).withWatermark(ts, late)
    return rows.groupBy(F.session_window(ts, gap).alias("w"), F.col(u).alias("u")).agg(F.count("*").alias("n")).select("u", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def distinct_edges(events: DataFrame, u: str, v: str, ts: str = "ts", late: str = "1 day") -> DataFrame:
    """Each (u, v) once within the watermark; state is dropped with it."""
    return events.select(F.col(u).alias("u"), F.col(v).alias("v"), ts).withWatermark(ts, late).dropDuplicatesWithinWatermark(["u", "v"])


def close_pairs(a: DataFrame, b: DataFrame, key: str, ts: str = "ts", within: str = "1 hour", late: str = "1 day") -> DataFrame:
    """Stream-stream join: rows of b up to ``within`` after a row of a with the same key."""
    x = a.withWatermark(ts, late).select(F.col(key).alias("xk"), F.col(ts).alias("xt"))
    y = b.withWatermark(ts, late).select(F.col(key).alias("yk"), F.col(ts).alias("yt"))
    return x.join(y, F.expr(f"xk = yk AND yt >= xt AND yt <= xt + interval {within}")).select(F.col("xk").alias(key), "xt", "yt")


def _degrees(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    degree, first = state.get if state.exists else (0, None)
    for frame in frames:
        degree += len(frame)
        least = frame["ts"].min()
        first = least.value // 1000 if first is None else min(first, least.value // 1000)
    state.update((degree, first))
    yield pd.DataFrame({"u": [key[0]], "degree": [degree], "first_us": [first]})


def vertex_state(edges: DataFrame) -> DataFrame:
    """``[u, degree, first_us]`` per left vertex, updated with each batch of ``[u: long, ts]``."""
    return edges.select("u", "ts").groupBy("u").applyInPandasWithState(_degrees, "u long, degree long, first_us long", "degree long, first_us long", "update", "NoTimeout")


def enriched(events: DataFrame, table: DataFrame, key: str) -> DataFrame:
    """Stream-static join: events with the columns of a table (one row per key) read anew for each batch; unmatched events stay."""
    return events.join(table, key, "left")


def start(frame: DataFrame, name: str, checkpoint: str, mode: str) -> StreamingQuery:
    """A query into a memory table for one replay of what is there. ``mode``: append, update or complete."""
    if mode not in ("append", "update", "complete"):
        raise ValueError(f"unknown output mode {mode!r}")
    return frame.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", checkpoint).start()


def incremental(known_path: str, detect: Callable[[DataFrame], DataFrame], out_path: str) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: add new edges to the table at ``known_path`` and find communities anew only where they matter.

    A biclique never crosses a connected component of the graph, so only components that hold new edges go through
    ``detect`` (edges u, v of strings to a table with a column ``component``, see ``current``). Each batch writes three folders named by its number:
    its edges, labels of the vertices that changed component, and communities of the components it touched; a repeated batch
    overwrites its own. Only edges and labels of touched components are read again: labels say which those are.
    """

    def run(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        new = batch.select(F.col("u").cast("string").alias("u"), F.col("v").cast("string").alias("v")).distinct()
        new.write.mode("overwrite").parquet(f"{known_path}/edges/batch={batch_id}")
        new = spark.read.parquet(f"{known_path}/edges/batch={batch_id}")
        labels = latest(_before(spark, f"{known_path}/labels", LABELS, batch_id), ["side", "vertex"]).select("side", "vertex", "component")
        ends = new.select(F.lit("u").alias("side"), F.col("u").alias("vertex")).union(new.select(F.lit("v"), F.col("v"))).distinct()
        touched = ends.join(labels, ["side", "vertex"]).select("component").distinct()
        old = labels.join(touched, "component", "left_semi").filter("side = 'u'").select(F.col("vertex").alias("u"))
        edges = _before(spark, f"{known_path}/edges", "u string, v string, batch int", batch_id).select("u", "v").join(old, "u", "left_semi").union(new).distinct()
        affected = cut(edges)
        fresh = vertex_components(affected).withColumnRenamed("label", "component")
        fresh.write.mode("overwrite").parquet(f"{known_path}/labels/batch={batch_id}")
        retired = touched.select("component", F.lit(True).alias("retired"))
        placed = spark.read.parquet(f"{known_path}/labels/batch={batch_id}").filter("side = 'u'").select(F.col("vertex").alias("u"), "component")
        found = detect(affected.join(placed, "u"))
        found.withColumn("retired", F.lit(False)).unionByName(retired, allowMissingColumns=True).write.mode("overwrite").parquet(f"{out_path}/batch={batch_id}")

    return run


LABELS = "side string, vertex string, component string, batch int"


def _before(spark: SparkSession, path: str, schema: str, batch_id: int) -> DataFrame:
    """What earlier batches wrote to ``path``; nothing before the first."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    if not where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where):
        return spark.createDataFrame([], schema)
    return spark.read.schema(schema).option("basePath", path).parquet(path).filter(F.col("batch") < batch_id)


def latest(rows: DataFrame, keys: list[str]) -> DataFrame:
    """The row of the last batch for each key."""
    rest = [c for c in rows.columns if c not in (*keys, "batch")]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest, "batch"), "batch").alias("r")).select(*keys, "r.*")


def current(spark: SparkSession, out_path: str) -> DataFrame:
    """The communities after all batches: of each component those of the last batch that wrote it, unless it was merged into another."""
    rows = spark.read.option("basePath", out_path).option("mergeSchema", "true").parquet(out_path)
    last = rows.groupBy("component").agg(F.max("batch").alias("batch"))
    return rows.join(last, ["component", "batch"]).filter("not retired").drop("batch", "retired")
