import os
import time

from bipercolate.checkpoints import cut, release, scratch, shared_folder
from bipercolate.components import connected


def checkpoints(spark):
    shared_folder(spark)
    top = spark.sparkContext._jsc.sc().getCheckpointDir().get().removeprefix("file:")
    return {x for x in os.listdir(top) if x.startswith("rdd-")} if os.path.isdir(top) else set()


def shuffle_files(spark):
    files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    names = (files.apply(i).getName() for i in range(files.size()))
    return {x for x in names if x.startswith("shuffle_") and x.endswith(".data")}


def test_a_finished_job_leaves_no_shuffle_files(spark):
    before = shuffle_files(spark)
    kept = cut(spark.range(1000).groupBy("id").count().repartition(3, "id"))
    for _ in range(50):
        left = shuffle_files(spark) - before
        if not left:
            break
        time.sleep(0.2)
    assert not left
    assert kept.count() == 1000


def test_rounds_of_contraction_keep_one_checkpoint(spark):
    before = checkpoints(spark)
    chain = spark.range(200).selectExpr("id as a", "id + 1 as b")
    found = connected(chain)
    assert len(checkpoints(spark) - before) == 1
    assert found.filter("label = 0").count() == 201


def test_scratch_deletes_all_but_what_is_kept(spark):
    before = checkpoints(spark)
    with scratch() as keep:
        a = cut(spark.range(5))
        with scratch() as inner:
            b, c = cut(a.filter("id > 1")), inner(cut(a.filter("id > 2")))
            assert b.count() == 3
        assert len(checkpoints(spark) - before) == 2
        d = keep(cut(c.union(a)))
        release(a)
    assert len(checkpoints(spark) - before) == 1 and d.count() == 7


def test_labels_of_one_key_are_left_out_before_any_is_shuffled(spark):
    from bipercolate.sources import edges as source

    docs = spark.createDataFrame([(1, "a line that two documents hold\nonly here, in the first one\nonly here, in the first one"), (2, "a line that two documents hold\nonly here, in the second one"), (3, None)], "doc_id long, text string")
    every, shared = source.lines(docs, "doc_id"), source.lines(docs, "doc_id", least_keys=2)
    assert every.count() == 4
    assert {tuple(r) for r in shared.collect()} == {(1, "a line that two documents hold"), (2, "a line that two documents hold")}


def test_encoding_leaves_its_edges_and_dictionaries_only(spark):
    from bipercolate.graph import encode

    before = checkpoints(spark)
    e = encode(spark.createDataFrame([("a", "x"), ("a", "y"), ("b", "y"), ("c", "z")], "u string, v string"))
    assert len(checkpoints(spark) - before) == 3
    assert (e.edges.count(), e.u.count(), e.v.count()) == (4, 3, 3)


def test_detection_leaves_bicliques_labels_groups_and_twins_only(spark):
    from bipercolate.communities import detect
    from bipercolate.graph import encode

    graph = encode(spark.createDataFrame([(f"u{i}", f"v{k}") for i in range(6) for k in range(i % 3 + 2)], "u string, v string"))
    before = checkpoints(spark)
    found = detect(graph, 2, 2, "seed_merge")
    assert len(checkpoints(spark) - before) == 5
    assert {(r.community_id, r.biclique) for r in found.keyed().collect()} == {("u0,u1,u2,u3,u4,u5|v0,v1", b) for b in ("u0,u1,u2,u3,u4,u5|v0,v1", "u1,u2,u4,u5|v0,v1,v2", "u2,u5|v0,v1,v2,v3")}
