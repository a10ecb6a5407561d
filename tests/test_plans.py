"""What the optimiser makes of the relational stages."""

import re

from pyspark.sql import functions as F

from edgeblocks.operators import baselines, batching, linegraph, metrics
from edgeblocks.plans.graphs import graph, pairs_of


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_scans_are_pruned(spark, small):
    text = plan(pairs_of(spark, small, "part_order"))
    assert re.search(r"ReadSchema: struct<l_partkey:bigint>|ReadSchema: struct<l_partkey:bigint,l_orderkey:bigint>|ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint>", text)
    assert "l_extendedprice" not in text


def test_ownership_and_hashing_do_not_shuffle(spark, small):
    g = graph(spark, small, "part_order")
    assert "Exchange" not in plan(batching.own_edges(g.edges, 64)) and "Exchange" not in plan(baselines.hash_edges(g, 8))


def test_line_graph_takes_one_shuffle(spark, small):
    text = plan(linegraph.contracted(batching.own_edges(graph(spark, small, "part_order").edges, 64)))
    assert text.count("Exchange") == 1 and "Join" not in text


def test_replication_combines_before_it_shuffles(spark, small):
    g = graph(spark, small, "part_order")
    text = plan(metrics.replicas(baselines.hash_edges(g, 8)))
    assert text.count("HashAggregate") == 2 and text.count("Exchange") == 1 and "Python" not in text


def test_relational_stages_stay_in_the_jvm(spark, small):
    g = graph(spark, small, "part_order")
    own = batching.own_edges(g.edges, 64)
    for df in (linegraph.size_law(own), batching.batch_vertices(own, 64), baselines.dbh(g, 8), metrics.lambda_histogram(baselines.dbh(g, 8))):
        assert not re.search("Python|Arrow|CartesianProduct|BroadcastNestedLoopJoin", plan(df))


def test_neighbours_are_found_in_slices(spark, tmp_path, monkeypatch):
    """A task compares a slice of vectors with a pack, never a whole Arrow batch; ties go to the smaller id."""
    import numpy as np

    from edgeblocks.plans import graphs

    r = np.arange(6.0) % 2
    assert graphs._largest(r, 4).tolist() == [1, 3, 5, 0] and graphs._largest(r, 9).tolist() == [1, 3, 5, 0, 2, 4]
    x = np.random.default_rng(3).integers(-2, 3, (70, 4)) + np.array([0.5, 0, 0, 0])
    spark.createDataFrame([(i * 3 % 70, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>").write.parquet(str(tmp_path / "embeddings.parquet"))
    whole = sorted(map(tuple, graphs._knn(spark, str(tmp_path), 5).collect()))
    monkeypatch.setattr(graphs, "SLICE", 7)
    assert whole == sorted(map(tuple, graphs._knn(spark, str(tmp_path), 5).collect())) and len(whole) == 350


def test_trials_leave_edges_off_the_driver(spark, small, monkeypatch):
    """The driver collects no edges; a run is the same however its graph's trials fall to tasks."""
    from edgeblocks.plans import trials

    graphs = {n: graph(spark, small, n) for n in ("trade_region", "geo")}
    monkeypatch.setattr(type(graphs["geo"].edges), "toArrow", lambda self: (_ for _ in ()).throw(AssertionError("edges on the driver")))
    runs = [trials.Trial(alg, n, k, alg) for n in graphs for alg in ("hash", "onthefly") for k in (2, 4)]
    got = []
    for tasks in (1, 8):
        monkeypatch.setattr(trials, "GRAPH_TASKS", tasks, raising=False)
        done = trials.run_all(spark, graphs, runs).collect()
        got.append({(r.alg, r.graph, r.k): (r.edges, r.blocks, r.error) for r in done})
    assert got[0] == got[1] and len(got[0]) == 8
    assert all(len(b) == m == graphs[n].m and e is None for (_, n, _), (m, b, e) in got[0].items())


def test_blocks_of_trials_are_not_broadcast(spark, small):
    """Blocks meet their edges by a shuffle whatever their files' size, a row for some hundred edges; every edge is there once for each trial."""
    from edgeblocks.plans import trials

    graphs = {n: graph(spark, small, n) for n in ("part_order", "geo")}
    done = trials.run_all(spark, graphs, [trials.Trial("hash", n, k, "hash") for n in graphs for k in (2, 4)])
    both = trials._joined(graphs, done.withColumn("trial", F.col("k") + F.length("graph")))
    assert "Broadcast" not in plan(both) and both.count() == 2 * sum(g.m for g in graphs.values())
    wrong = both.where(F.col("block") != F.pmod(F.col("u") * 31 + F.col("v") * 17, F.col("k"))).count()
    assert not wrong
    for r in trials.measured(spark, graphs, done).collect():
        whole = metrics.replication(baselines.hash_edges(graphs[r.graph], r.k), graphs[r.graph]).first()
        assert (r.replicas, r.placed, r.bad_blocks) == (whole.replicas, graphs[r.graph].m, 0)
