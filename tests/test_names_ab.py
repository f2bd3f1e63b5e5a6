import itertools

import pytest

from bipercolate.graph import encode
from bipercolate.listing import names_ab


@pytest.fixture(scope="module")
def copies(spark):
    """Nine keys of five sets, two labels for each value: twins on both sides."""
    sets = ("pqs", "p", "qrst", "st", "prs")
    edges = {(f"u{i}", v + twin) for i in range(9) for v in sets[i % 5] for twin in ("", "2")}
    return edges, encode(spark.createDataFrame(sorted(edges), "u string, v string"), "id")


@pytest.mark.parametrize(("a", "b", "side", "at_once", "bound"), [(2, 2, "u", 1_000_000, 1_000_000), (2, 2, "v", 2, 0), (3, 2, "u", 2, 0), (1, 2, "v", 1, 1_000_000)])
def test_names_over_classes_of_twins_are_those_of_all_small_bicliques(copies, a, b, side, at_once, bound):
    edges, graph = copies
    us, vs = (sorted({e[k] for e in edges}) for k in (0, 1))
    want = [f"{','.join(x)}|{','.join(y)}" for x in itertools.combinations(us, a) for y in itertools.combinations(vs, b) if all(e in edges for e in itertools.product(x, y))]
    assert want and sorted(r[0] for r in names_ab(graph, a, b, side, at_once, bound).collect()) == sorted(want)


def test_small_bicliques_are_written_where_they_are_found(spark):
    """No exchange moves bicliques: the plan has none above the explosion of common neighbours, and no checkpoint holds them."""
    edges = [(f"u{i}", f"v{k}") for i in range(40) for k in range(5)]
    names = names_ab(encode(spark.createDataFrame(edges, "u string, v string"), "id"), 2, 2)
    plan = names._jdf.queryExecution().executedPlan().toString().split("posexplode")[0]
    assert "Exchange" not in plan and names.count() == 780 * 10


def test_labels_of_few_vertices_are_not_shuffled(spark):
    edges = spark.createDataFrame([(f"u{i}", f"v{k}") for i in range(6) for k in range(i + 1)], "u string, v string")
    graph = encode(edges, "id")
    sets = spark.createDataFrame([(7, [1, 3, 2], [1]), (9, [4], [2, 1])], "biclique_id long, x array<long>, y array<long>")
    few, many = graph.labels(sets), graph.labels(sets, bound=0)
    want = [(7, ["u0", "u1", "u2"], ["v0"]), (9, ["u3"], ["v0", "v1"])]
    for names in (few, many):
        assert [tuple(r) for r in names.orderBy("biclique_id").collect()] == want
    moved = [x for x in few._jdf.queryExecution().executedPlan().toString().splitlines() if "Exchange hashpartitioning" in x]
    assert moved and all("REPARTITION_BY_COL" in x for x in moved)
