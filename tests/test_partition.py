"""What must hold for every partition, on small graphs made by hand and at random."""

import itertools

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from edgeblocks.operators import baselines, buffered, fennel, linegraph, metrics, multilevel, onthefly, sequential
from edgeblocks.operators.canonical import from_pairs

EDGES = {
    "tri_tail": [(0, 1), (0, 2), (1, 2), (2, 3), (3, 4)], "star9": [(0, i) for i in range(1, 9)], "matching": [(0, 1), (2, 3), (4, 5)],
    "two_k4_bridge": [*itertools.combinations(range(4), 2), *itertools.combinations(range(4, 8), 2), (3, 4)], "path10": [(i, i + 1) for i in range(9)], "single": [(0, 1)],
}


def made(spark, edges, name=""):
    return from_pairs(spark.createDataFrame(edges, "a long, b long"), name=name)


def cut_of(edges, blocks, k):
    return sum(len({b for e, b in zip(edges, blocks) if x in e}) for x in {y for e in edges for y in e})


def best(edges, k):
    cap = metrics.block_cap(len(edges), k)
    return min(cut_of(edges, bs, k) for bs in itertools.product(range(k), repeat=len(edges)) if max(bs.count(b) for b in set(bs)) <= cap)


@pytest.mark.parametrize("name", sorted(EDGES))
@pytest.mark.parametrize("method", ["buffered", "maximal", "onthefly", "hdrf", "two_phase", "linear"])
def test_small_graphs(spark, name, method):
    g = made(spark, EDGES[name], name)
    run = {
        "buffered": lambda: buffered.partition(g, 2, delta=3), "maximal": lambda: buffered.partition(g, 2, delta=3, mode="maximal"), "onthefly": lambda: onthefly.partition(g, 2),
        "hdrf": lambda: baselines.hdrf(g, 2), "two_phase": lambda: baselines.two_phase(g, 2), "linear": lambda: baselines.two_phase(g, 2, "linear"),
    }[method]
    a = run().assign
    assert tuple(metrics.certificate(a, g, 2).first()) == (g.m, g.m, 0, 0, 0)
    rows = a.orderBy("eid").collect()
    total = metrics.replication(a, g).first().replicas
    assert total == cut_of([(r.u, r.v) for r in rows], [r.block for r in rows], 2)
    if g.m <= 9:
        assert total >= best([(r.u, r.v) for r in rows], 2)


def test_canonical_form(spark):
    g = made(spark, [(0, 1), (1, 0), (0, 1), (2, 2)])
    assert [tuple(r) for r in g.edges.collect()] == [(0, 0, 1)] and g.n == 2
    empty = made(spark, [])
    assert (empty.n, empty.m) == (0, 0)


def test_more_blocks_than_edges(spark):
    g = made(spark, EDGES["tri_tail"])
    for p in (buffered.partition(g, 16, delta=3), onthefly.partition(g, 16)):
        assert tuple(metrics.certificate(p.assign, g, 16).first()) == (5, 5, 0, 0, 0)


def test_one_block_copies_nothing(spark):
    g = made(spark, EDGES["two_k4_bridge"])
    assert metrics.replication(buffered.partition(g, 1, delta=3).assign, g).first().rf == 1.0


def communities(count, size, inner, outer, seed=1):
    """Groups of neighbouring ids with many edges inside and few between."""
    rng = np.random.default_rng(seed)
    n, edges = count * size, set()
    for c in range(count):
        for x, y in rng.integers(c * size, (c + 1) * size, (inner * size, 2)).tolist():
            edges.add((min(x, y), max(x, y)))
    for x, y in rng.integers(0, n, (int(outer * n), 2)).tolist():
        edges.add((min(x, y), max(x, y)))
    return sorted(e for e in edges if e[0] != e[1])


def test_communities(spark):
    """Where there is locality, the buffered method copies far less than greedy ones, more so with a larger buffer."""
    g = made(spark, communities(40, 50, 5, 0.3))
    rf = lambda p: metrics.replication(p.assign, g).first().rf
    small, large = rf(buffered.partition(g, 8, delta=g.n // 16)), rf(buffered.partition(g, 8, delta=g.n // 2))
    greedy = rf(baselines.hdrf(g, 8))
    assert large <= small < 0.7 * greedy
    assert rf(onthefly.partition(g, 32)) < rf(baselines.hdrf(g, 32))


def test_star_copies_only_the_centre(spark):
    g = made(spark, EDGES["star9"])
    r = metrics.replication(buffered.partition(g, 4, delta=100).assign, g).first()
    assert r.replicas <= 8 + 4


@settings(max_examples=40, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 14), st.integers(0, 14)), min_size=1, max_size=60), st.integers(1, 5), st.integers(1, 8), st.sampled_from(["minimal", "maximal", "subset", "none"]), st.sampled_from(["eid", "nbr", "random"]))
def test_kernel_invariants(pairs, k, delta, mode, order):
    edges = sorted({(min(p), max(p)) for p in pairs if p[0] != p[1]})
    if not edges:
        return
    u, v = (np.array([e[i] for e in edges]) for i in (0, 1))
    import pyarrow as pa

    l_max = metrics.block_cap(len(edges), k)
    o = buffered.Options(k, delta, l_max, len(edges), mode, order=order, r=2)
    out = buffered._all_batches(o)(pa.table({"eid": np.arange(len(edges)), "u": u, "v": v})).to_pandas()
    placed, stats = out[out.eid.notna()], out[out.eid.isna()]
    assert sorted(placed.eid) == list(range(len(edges)))
    assert placed.block.between(0, k - 1).all() and placed.block.value_counts().max() <= l_max
    if mode != "none":
        assert (stats.s_gamma <= stats.s_cut).all()
    ends = [(x, int(b)) for e, b in zip(placed.eid.astype(int), placed.block) for x in edges[e]]
    assert stats.s_gamma.sum() == len(set(ends)) - len({x for x, _ in ends})
    assert (stats.s_links == [2 * n - len({x for e, b in zip(edges, np.array([y // delta for _, y in edges])) if b == t for x in e}) for n, t in zip(stats.s_items, stats.s_batch)]).all()


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 30), min_size=2, max_size=8), st.lists(st.tuples(st.integers(0, 5), st.integers(0, 5)), max_size=12), st.floats(0, 2), st.integers(0, 9))
def test_two_sets_choose_like_all_blocks(loads, links, alpha, slack):
    k, n = len(loads), 6
    limits = np.full(k, max(loads) + slack + n)
    out = []
    for strategy in ("all_k", "two_set", "two_set_bucket"):
        blocks, now = np.full(n, -1), np.array(loads)
        near = [[y for x, y in links if x == i] + [x for x, y in links if y == i] for i in range(n)]
        fennel.place_items(range(n), np.ones(n, int), lambda i: (near[i], [1.0] * len(near[i])), lambda i: ([i % k], [1.0]) if i % 2 else ((), ()), blocks, now, limits, alpha, strategy=strategy)
        out.append(blocks.tolist())
    assert out[0] == out[1] == out[2]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 9), st.integers(0, 9)), min_size=1, max_size=30), st.integers(1, 4), st.randoms(use_true_random=False))
def test_contraction_keeps_cut_and_gain(links, k, rnd):
    n = 10
    a, b = (np.array([x[i] for x in links if x[0] != x[1]], np.int64) for i in (0, 1))
    level = multilevel.Level(np.ones(n, np.int64), a, b, np.ones(len(a)), np.array([0, 3], np.int64), np.array([0, k - 1], np.int64), np.ones(2))
    clusters = np.unique([rnd.randrange(4) for _ in range(n)], return_inverse=True)[1]
    small = multilevel.contract(level, clusters)
    coarse = np.array([rnd.randrange(k) for _ in range(small.size)])
    fine = multilevel.project(coarse, clusters)
    cut = lambda lv, bl: lv.w[bl[lv.a] != bl[lv.b]].sum() + lv.fw[bl[lv.items] != lv.fixed].sum()
    assert cut(level, fine) == cut(small, coarse)
    assert small.weights.sum() == n
    f = fennel.penalty([7], 0.3)[0]
    gain = lambda w_in, c: w_in - c * f
    inside = np.zeros(small.size)
    np.add.at(inside, clusters[level.items], level.fw)
    assert np.isclose(sum(gain((level.items == i).sum(), 1) for i in range(n)), sum(gain(x, c) for x, c in zip(inside, small.weights)))


def test_clusters_respect_the_cap():
    rng = np.random.default_rng(0)
    a, b = rng.integers(0, 200, 800), rng.integers(0, 200, 800)
    keep = a != b
    level = multilevel.Level(rng.integers(1, 4, 200), a[keep], b[keep], np.ones(keep.sum()), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
    c = multilevel.cluster(level, 9)
    assert np.bincount(c, weights=level.weights).max() <= 9


@settings(max_examples=80, deadline=None)
@given(st.lists(st.integers(0, 40), min_size=1, max_size=6), st.lists(st.integers(0, 30), min_size=1, max_size=5))
def test_quotas(loads, owned):
    loads, owned = np.array(loads), np.array(owned)
    l_max = max(int(loads.max()), -(-int(loads.sum() + owned.sum()) // len(loads)))
    q = buffered.quotas(loads, l_max, owned)
    assert (q >= 0).all() and (q.sum(axis=0) <= l_max - loads).all() and (q.sum(axis=1) >= owned).all()


def test_lane_limits():
    assert sum(sequential.lane_limits([10, 20, 30], 4, 20)) <= 20
    with pytest.raises(ValueError):
        sequential.lane_limits([1] * 10, 4, 3)


def test_alphas():
    assert fennel.alpha_batch(4, 0, 0) == 0.0
    assert np.isclose(fennel.alpha_batch(2, 3, 3), 0.81649658) and np.isclose(fennel.alpha_batch(2, 2, 1), 0.5)
    assert fennel.alpha_static(4, 100, 2.0) == fennel.alpha_dynamic(4, 100, 50, 100)


def test_any_order_bounds_the_copies(spark):
    g = made(spark, EDGES["two_k4_bridge"])
    a = baselines.random_blocks(g, 3)
    extra = metrics.replication(a, g).first().extra_copies
    for order in ("eid", "nbr", "random"):
        assert metrics.edge_cut(linegraph.contracted(g.edges, order), a).first()[0] >= extra
    assert metrics.edge_cut(linegraph.tight_order(g.edges, a), a).first()[0] == extra


@pytest.mark.parametrize("policy", ["first", "lighter", "heavier_aux"])
def test_split_copies_come_together(spark, policy):
    g = made(spark, EDGES["two_k4_bridge"])
    split = linegraph.split_vertices(g.edges).withColumn("block", F.pmod(F.xxhash64("v", "pos"), F.lit(3)).cast("int"))
    got = linegraph.spac_to_edges(split, policy)
    assert got.count() == g.m == got.select("eid").distinct().count()


def test_quality_follows_the_reported_order(spark, small):
    """Greedy beats hashing; remembering all blocks is no worse than remembering none; one batch is best."""
    from edgeblocks.plans.graphs import graph

    g = graph(spark, "/root/testdata/sf0.01", "trade_region")
    rf = lambda p: metrics.replication(getattr(p, "assign", p), g).first().rf
    small_buffer, whole = rf(buffered.partition(g, 8, delta=g.n // 16)), rf(buffered.partition(g, 8, delta=g.n))
    maximal, none = rf(buffered.partition(g, 8, delta=g.n // 16, mode="maximal")), rf(buffered.partition(g, 8, delta=g.n // 16, mode="none"))
    assert whole <= small_buffer <= none and maximal <= none
    assert max(small_buffer, rf(onthefly.partition(g, 8))) < rf(baselines.hash_edges(g, 8))


@pytest.mark.parametrize("mode,alpha,lanes", [("minimal", "dynamic_low", 1), ("maximal", "dynamic", 1), ("subset", "batch", 3)])
def test_jobs_take_many_rounds(spark, small, mode, alpha, lanes, monkeypatch):
    """A job per chunk of rounds, not per round; the blocks do not depend on how rounds fall into chunks."""
    from edgeblocks.plans.graphs import graph

    g, got, merges = graph(spark, small, "trade_region"), [], []
    add = buffered.RoundMemory.add
    monkeypatch.setattr(buffered.RoundMemory, "add", lambda self, placed: (merges.append(1), add(self, placed)))
    for edges in (10**9, 150, 60):
        monkeypatch.setattr(buffered, "CHUNK_EDGES", edges)
        merges.clear()
        p = buffered.partition(g, 4, delta=16, mode=mode, alpha=alpha, lanes=lanes, exec="jobs", r=2)
        got.append((len(merges), sorted(map(tuple, p.assign.select("eid", "block").collect()))))
    assert got[0][1] == got[1][1] == got[2][1]
    assert got[0][0] == 0 < got[1][0] < got[2][0]
    if lanes == 1:
        one = buffered.partition(g, 4, delta=16, mode=mode, alpha=alpha, r=2)
        assert got[0][1] == sorted(map(tuple, one.assign.select("eid", "block").collect()))


@pytest.mark.parametrize("seed", range(6))
def test_refinement_by_table_makes_the_moves_of_the_plain_one(seed):
    rng = np.random.default_rng(seed)
    n, k, links = 300, (2, 8, 40)[seed % 3], 900
    a, b = rng.integers(0, n, links), rng.integers(0, n, links)
    a, b = a[a != b], b[a != b]
    items = rng.integers(0, n, 200)
    level = multilevel.Level(rng.integers(1, 5, n), a, b, rng.integers(1, 4, len(a)).astype(float), items, rng.integers(0, k, 200), np.ones(200))
    first = rng.integers(0, k, n)
    loads = np.bincount(first, weights=level.weights, minlength=k).astype(np.int64)
    limits = np.full(k, int(loads.max()) + 3)
    got = []
    for run in (multilevel._refine_dense, multilevel._refine_sparse):
        blocks, held = first.copy(), loads.copy()
        moves = run(level, blocks, held, limits, 0.05, 0.5, 20, seed)
        assert (np.bincount(blocks, weights=level.weights, minlength=k) == held).all()
        got.append((moves, blocks.tolist(), held.tolist()))
    assert got[0] == got[1] and got[0][0] > 0


@pytest.mark.parametrize("mode, alpha", [("minimal", "batch"), ("minimal", "dynamic_low"), ("maximal", "dynamic"), ("subset", "static"), ("none", "batch")])
def test_streamed_batches_give_the_blocks_of_one_task(spark, small, mode, alpha, monkeypatch):
    from edgeblocks.plans.graphs import graph

    g = graph(spark, small, "part_order")
    monkeypatch.setattr(buffered, "_rounds", None)  # a graph above the bound of one task must not need a job per chunk
    rows = []
    for bound in (1 << 30, 10):
        monkeypatch.setattr(buffered, "SINGLE_TASK_EDGES", bound)
        p = buffered.partition(g, 12, delta=64, mode=mode, alpha=alpha, r=2)
        figures = ["batch", "items", "links", "block_links", "cut", "scores", "moves", "gamma"]
        rows.append((sorted(map(tuple, p.assign.collect())), sorted(map(tuple, p.stats.select(*figures).collect()))))
    assert rows[0] == rows[1] and len(rows[0][0]) == g.m and len(rows[0][1]) > 10


@pytest.mark.parametrize("order, alpha", [("eid", "batch"), ("nbr", "dynamic_low"), ("random", "dynamic")])
def test_streams_take_clusters_made_before(order, alpha, monkeypatch):
    """Batches are clustered apart, in any tasks; the task that carries the state clusters nothing and gives the same blocks."""
    rng = np.random.default_rng(7)
    pairs = np.unique(np.sort(rng.integers(0, 600, (9000, 2)), axis=1), axis=0)
    u, v = pairs[pairs[:, 0] < pairs[:, 1]].T
    eid = np.arange(len(u)) * 3
    o = buffered.Options(6, 50, -(-len(u) * 103 // 600), len(u), alpha=alpha, order=order, measure=False)
    want, batch, stats, _ = buffered.run_batches(eid, u, v, o)
    parts = []
    for task in range(3):
        own = np.flatnonzero(batch % 3 == task)
        own = own[np.lexsort((eid[own], batch[own]))]
        rows = pa.table({"batch": batch[own], "eid": eid[own], "u": u[own], "v": v[own]})
        parts += buffered._clustered(o)(iter(rows.to_batches(max_chunksize=700)))
    assert max(len(r) for p in parts for r in p.column("eid").to_pylist()) <= buffered.PIECE and len(parts) == len(stats)
    assert any(len(r) > e for p in parts for r, e in zip(p.column("labels").to_pylist(), map(len, p.column("eid").to_pylist())))  # more than one level
    pieces = pa.Table.from_batches(parts).sort_by([("batch", "ascending"), ("piece", "ascending")]).combine_chunks()
    monkeypatch.setattr(multilevel, "cluster", None)
    got = pa.Table.from_batches(list(buffered._streamed(o, 600)(iter(pieces.to_batches(max_chunksize=5)))))
    placed = got.filter(pa.compute.is_valid(got.column("eid")))
    assert dict(zip(placed.column("eid").to_pylist(), placed.column("block").to_pylist())) == dict(zip(eid.tolist(), want.tolist()))
    assert [x for x in got.column("s_moves").to_pylist() if x is not None] == [s["moves"] for s in stats]
