"""Spark queries against their SQL on the smallest tables."""

import pytest

import verify
from bipercolate import catalogue

SF = "/root/testdata/sf0.001"
FEW = [n for n in catalogue.ORACLE_SQL if n.startswith(("rel_", "graph_stats_doc", "graph_stats_vec", "degree_", "two_hop", "edge_sample_20", "ab_biclique_count", "core_user", "butterfl", "overlap_degree", "communities_listing_seeded_user", "communities_seed_merge_user", "partial_counts_chain_nation"))]


@pytest.fixture(scope="module")
def con():
    return verify.connect(SF)


@pytest.mark.parametrize("name", FEW)
def test_query(spark, con, name):
    assert verify.compare(spark, con, SF, catalogue.QUERIES[name], catalogue.ORACLE_SQL[name]) == ""


def test_entry(spark):
    assert catalogue.entry(spark, SF).count() > 0


def test_plans_have_no_cartesian_product(spark):
    from bipercolate import overlap

    b = spark.createDataFrame([(1, [1, 2], [1, 2], 2, 2)], "biclique_id long, x array<long>, y array<long>, n_x int, n_y int")
    plan = overlap.edges(b, 2, 2)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "NestedLoop" not in plan
