"""Sizes of the canonical graphs and of hash partitions that are known beforehand."""

import pytest

from edgeblocks.operators import baselines, batching, linegraph, metrics
from edgeblocks.operators.canonical import summary
from edgeblocks.plans.graphs import graph

SIZES = {
    "part_order": (1673, 5942, 47), "supp_part": (210, 1905, 195), "supp_cust": (160, 1444, 147), "cust_part": (350, 5382, 66), "copurchase": (200, 8899, 138),
    "trade_region": (160, 275, 34), "trade_nation": (69, 59, 12), "geo": (190, 185, 15), "user_prop": (115, 739, 59), "user_next": (15, 105, 14),
    "page_link": (305, 279, 6), "doc_token": (27982, 54737, 1764), "turn_path": (87, 67, 2), "knn": (500, 2924, 19), "order_iso": (1700, 5942, 47),
}


@pytest.mark.parametrize("name", sorted(SIZES))
def test_graph(spark, small, name):
    r = summary(graph(spark, small, name)).first()
    assert (r.n, r.m, r.max_degree) == SIZES[name]


def test_hash_and_degree_hash(spark, small):
    g = graph(spark, small, "part_order")
    for run, replicas, rf, most in ((baselines.hash_edges, 6329, 3.783025, 789), (baselines.dbh, 3039, 1.816497, 781)):
        a = run(g, 8)
        r, b = metrics.replication(a, g).first(), metrics.balance(a, 8).first()
        assert (r.replicas, r.rf, b.max_load, b.l_max, b.feasible) == (replicas, rf, most, 766, False)


@pytest.mark.parametrize("name, delta, batches, links", [("part_order", 1024, 2, 10011), ("copurchase", 256, 1, 17598), ("doc_token", 4096, 7, 80384)])
def test_batches_and_links(spark, small, name, delta, batches, links):
    own = batching.own_edges(graph(spark, small, name).edges, delta)
    assert own.select("batch").distinct().count() == batches
    assert linegraph.contracted(own).count() == links


def test_block_cap():
    assert [metrics.block_cap(59945, k) for k in (2, 8, 64)] == [30872, 7718, 965]
    assert metrics.block_cap(1, 16) == 1
