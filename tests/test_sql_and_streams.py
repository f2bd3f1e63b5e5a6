import datetime
import time

import pytest
from pyspark.sql import functions as F

from bipercolate import sql
from bipercolate.streaming import edges as stream

CHAIN = {(1, 1), (1, 2), (1, 3), (2, 1), (2, 2), (2, 3), (2, 4), (3, 2), (3, 3), (3, 4)}


def test_small_communities():
    rows = sql.small_communities(CHAIN, 2, 2)
    assert len({c for c, _, _ in rows}) == 1
    assert {v for _, s, v in rows if s == "u"} == {1, 2, 3} and {v for _, s, v in rows if s == "v"} == {1, 2, 3, 4}
    assert sql.small_communities(set(), 1, 1) == []
    assert len({c for c, _, _ in sql.small_communities(CHAIN | {(u + 9, v + 9) for u, v in CHAIN}, 2, 2)}) == 2


def test_table_function(spark):
    sql.register(spark)
    spark.createDataFrame(sorted(CHAIN), "u long, v long").withColumn("snapshot", F.lit(1)).createOrReplaceTempView("edges")
    rows = spark.sql("SELECT * FROM percolation_communities(TABLE(edges) PARTITION BY (snapshot), 2, 2)").collect()
    assert len(rows) == 7


def test_windowed_stream_equals_batch(spark, tmp_path):
    rows = spark.createDataFrame([(u, v, 86400 * u) for u, v in sorted(CHAIN)], "u long, v long, s long").select("u", "v", F.timestamp_seconds("s").alias("ts"))
    rows.coalesce(1).write.parquet(str(tmp_path / "in"))
    events = stream.read_events(spark, str(tmp_path / "in"), "u long, v long, ts timestamp")
    query = stream.windowed_edges(events, "u", "v").writeStream.format("memory").queryName("windows").outputMode("complete").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
    query.awaitTermination(120)
    assert {(r.u, r.v) for r in spark.table("windows").collect()} == CHAIN


def replay(spark, tmp_path, name, batches, schema, build, mode="append"):
    """Rows of a stream over files written one after another, each its own batch."""
    at = tmp_path / name
    for k, rows in enumerate(batches):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(str(at / "in"))
        if k + 1 < len(batches):
            time.sleep(1.1)  # files are taken in the order of their times
    given = stream.read_events(spark, str(at / "in"), schema)
    query = stream.start(build(given), name, str(at / "c"), mode)
    assert query.awaitTermination(180)
    return [tuple(r) for r in spark.table(name).collect()]


def at(text):
    return datetime.datetime.fromisoformat(text)


EVENTS = "u long, v long, ts timestamp"


def test_late_rows_and_output_modes(spark, tmp_path):
    batches = [[(1, 1, at("2024-01-01")), (1, 2, at("2024-01-02"))], [(2, 1, at("2024-03-01"))], [(2, 2, at("2024-03-01"))], [(9, 9, at("2024-01-01")), (3, 1, at("2024-03-02"))]]
    build = lambda e: stream.windowed_edges(e, "u", "v").select("u", "v", "n")
    done = replay(spark, tmp_path, "appended", batches, EVENTS, build)
    assert sorted(done) == [(1, 1, 1), (1, 2, 1)]  # the windows that the watermark has closed
    assert (9, 9, 1) not in replay(spark, tmp_path, "updated", batches, EVENTS, build, "update")
    with pytest.raises(ValueError):
        stream.start(spark.readStream.format("rate").load(), "x", str(tmp_path / "x"), "other")


def test_sessions_distinct_edges_and_vertex_state(spark, tmp_path):
    rows = [(1, 1, at("2024-01-01T00:00:00")), (1, 1, at("2024-01-01T00:10:00")), (1, 2, at("2024-01-01T02:00:00")), (None, 2, at("2024-01-01T02:00:00"))]
    end = [(5, 5, at("2024-02-01"))]
    sessions = replay(spark, tmp_path, "sessions", [rows, end], EVENTS, lambda e: stream.session_edges(e, "u"))
    assert sorted((r[0], r[3]) for r in sessions) == [(1, 1), (1, 2)]
    distinct = replay(spark, tmp_path, "distinct_edges", [rows[:3], rows[:1]], EVENTS, lambda e: stream.distinct_edges(e, "u", "v"))
    assert sorted(r[:2] for r in distinct) == [(1, 1), (1, 2)]
    states = replay(spark, tmp_path, "states", [rows[:2], rows[2:3]], EVENTS, lambda e: stream.vertex_state(e.select("u", "ts")), "update")
    assert sorted((r[0], r[1]) for r in states) == [(1, 2), (1, 3)]


def test_joins_of_streams(spark, tmp_path):
    rows = [(1, 1, at("2024-01-01T00:00:00")), (2, 1, at("2024-01-01T00:30:00")), (1, 1, at("2024-01-01T03:00:00"))]
    pairs = replay(spark, tmp_path, "close_pairs", [rows], EVENTS, lambda e: stream.close_pairs(e, stream.read_events(spark, str(tmp_path / "close_pairs" / "in"), EVENTS), "v"))
    assert sorted((a.hour, b.minute, b.hour) for _, a, b in pairs) == [(0, 0, 0), (0, 30, 0), (0, 30, 0), (3, 0, 3)]
    names = spark.createDataFrame([(1, "one")], "u long, name string")
    named = replay(spark, tmp_path, "named", [rows], EVENTS, lambda e: stream.enriched(e, names, "u").select("u", "name"))
    assert sorted(named, key=str) == [(1, "one"), (1, "one"), (2, None)]


def test_incremental_communities_retire_old_ones(spark, tmp_path):
    known, out = str(tmp_path / "known"), str(tmp_path / "out")
    step = stream.incremental(known, lambda e: e.groupBy("component").agg(F.count("*").alias("edges")), out)
    edges = lambda pairs: spark.createDataFrame(pairs, "u string, v string")
    now = lambda: sorted(r.edges for r in stream.current(spark, out).collect())
    step(edges([("a", "x"), ("b", "x"), ("c", "y")]), 0)
    assert now() == [1, 2]
    step(edges([("d", "z")]), 1)
    assert now() == [1, 1, 2]
    step(edges([("a", "y")]), 2)  # joins two components
    assert now() == [1, 4]
    step(edges([("a", "y")]), 2)  # the same batch again
    assert now() == [1, 4]
