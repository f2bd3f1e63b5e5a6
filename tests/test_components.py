import random

import pytest

from bipercolate.components import connected, merge


@pytest.mark.parametrize("limit", [0, 1000])
def test_components(spark, limit):
    rnd = random.Random(4)
    links = [(rnd.randrange(60), rnd.randrange(60)) for _ in range(45)] + [(70, 70), (None, 3)] + [(80, k) for k in range(81, 120)]
    label = {x: x for p in links if None not in p for x in p}
    for _ in label:
        for a, b in (p for p in links if None not in p):
            label[a] = label[b] = min(label[a], label[b])
    got = {r.item: r.label for r in connected(spark.createDataFrame(links, "a long, b long"), driver_limit=limit).collect()}
    assert got == label


def test_merge_and_empty(spark):
    labels = spark.createDataFrame([(1, 1), (2, 1), (3, 3), (4, 4)], "item long, label long")
    links = spark.createDataFrame([(2, 3)], "a long, b long")
    assert {tuple(r) for r in merge(labels, links).collect()} == {(1, 1), (2, 1), (3, 1), (4, 4)}
    assert connected(links.filter("false")).count() == 0
