"""Every method against a plain row-by-row version of it, block for block, on random graphs."""

import math
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from edgeblocks.operators import baselines, buffered, fennel, metrics, multilevel, onthefly

GRAPHS = st.lists(st.tuples(st.integers(0, 24), st.integers(0, 24)), min_size=1, max_size=90).map(lambda pairs: sorted({(min(p), max(p)) for p in pairs if p[0] != p[1]})).filter(bool)


def half(i, seed):
    """Whether an item may move in a round: the drawing is part of the method's definition here, not of what is tested."""
    return int(multilevel._hash(np.array([i]), seed)[0]) % 2 == 0


# ---- the multilevel cut, on dictionaries

def admitted(wishes, size, weight, cap):
    """wishes: (target, better, item). Those that fit, taken by target and falling gain; what did not fit still counts before the next."""
    taken, queue = [], defaultdict(list)
    for target, better, item in wishes:
        queue[target].append((-better, item))
    for target, rows in queue.items():
        total = 0
        for _, item in sorted(rows):
            total += weight[item]
            if size[target] + total <= cap(target):
                taken.append((item, target))
    return taken


def plain_cluster(weight, links, cap, rounds, seed):
    label, size = {i: i for i in weight}, dict(weight)
    for r in range(rounds):
        near = defaultdict(lambda: defaultdict(float))
        for a, b, w in links:
            near[a][label[b]] += w
            near[b][label[a]] += w
        wishes = []
        for i, found in near.items():
            own = found.get(label[i], 0.0)
            open_ = [(-w, x) for x, w in found.items() if x != label[i] and w > own and size[x] + weight[i] <= cap]
            if open_ and half(i, seed + r):
                w, x = min(open_)
                wishes.append((x, -w - own, i))
        if not wishes:
            if r % 2:
                break
            continue
        for i, x in admitted(wishes, dict(size), weight, lambda _: cap):
            size[label[i]] -= weight[i]
            size[x] += weight[i]
            label[i] = x
    names = {x: n for n, x in enumerate(sorted(set(label.values())))}
    return {i: names[x] for i, x in label.items()}


def plain_contract(weight, links, fixed, part):
    w2, l2, f2 = defaultdict(int), defaultdict(float), defaultdict(float)
    for i, c in part.items():
        w2[c] += weight[i]
    for a, b, w in links:
        if part[a] != part[b]:
            l2[min(part[a], part[b]), max(part[a], part[b])] += w
    for i, block, w in fixed:
        f2[part[i], block] += w
    return dict(w2), [(a, b, w) for (a, b), w in sorted(l2.items())], [(i, b, w) for (i, b), w in sorted(f2.items())]


def plain_place(weight, links, fixed, blocks, loads, limits, alpha, gamma):
    near = defaultdict(list)
    for a, b, w in links:
        near[a].append((b, w))
        near[b].append((a, w))
    for i in sorted(weight, key=lambda i: (-weight[i], i)):
        if blocks.get(i, -1) >= 0:
            continue
        inside = defaultdict(float)
        for j, w in near[i]:
            if blocks.get(j, -1) >= 0:
                inside[blocks[j]] += w
        for j, block, w in fixed:
            if j == i:
                inside[block] += w
        open_ = [(-(inside[b] - weight[i] * (alpha * gamma * float(loads[b]) ** (gamma - 1))), loads[b], b) for b in range(len(loads)) if loads[b] + weight[i] <= limits[b]]
        blocks[i] = min(open_)[2] if open_ else -1
        if open_:
            loads[blocks[i]] += weight[i]


def plain_refine(weight, links, fixed, blocks, loads, limits, alpha, gamma, rounds, seed):
    n, idle = len(weight), 0
    for r in range(rounds):
        inside = defaultdict(lambda: defaultdict(float))
        for a, b, w in links:
            inside[a][blocks[b]] += w
            inside[b][blocks[a]] += w
        for i, block, w in fixed:
            inside[i][block] += w
        price = lambda load: alpha * gamma * float(load) ** (gamma - 1)
        wishes = []
        for i, found in inside.items():
            if not half(i, seed + r):
                continue
            home, c = blocks[i], weight[i]
            now = found.get(home, 0.0) - c * price(max(loads[home] - c, 0))
            open_ = [(-(w - c * price(loads[b])), loads[b], b) for b, w in found.items() if b != home and w - c * price(loads[b]) > now + 1e-12 and loads[b] + c <= limits[b]]
            if open_:
                value, _, b = min(open_)
                wishes.append((b, -value - now, i))
        if not wishes:
            idle += 1
            if idle == 2:
                return
            continue
        moved = admitted(wishes, list(loads), weight, lambda b: limits[b])
        for i, b in moved:
            loads[blocks[i]] -= weight[i]
            loads[b] += weight[i]
            blocks[i] = b
        idle = idle + 1 if len(moved) * multilevel.STALLED < n else 0
        if idle == 2:
            return


def plain_cut(n, links, fixed, loads, limits, alpha, l_max, gamma=1.5, seed=0):
    levels, maps = [({i: 1 for i in range(n)}, links, fixed)], []
    while len(levels[-1][0]) > max(n // (2 * len(loads)), 4 * len(loads)):
        part = plain_cluster(levels[-1][0], levels[-1][1], max(1, l_max // 2), multilevel.CLUSTER_ROUNDS, seed + 17 * len(maps))
        small = plain_contract(*levels[-1], part)
        if len(small[0]) > 0.95 * len(levels[-1][0]):
            break
        levels.append(small)
        maps.append(part)
    blocks: dict = {}
    plain_place(*levels[-1], blocks, loads, limits, alpha, gamma)
    for at in range(len(levels) - 1, -1, -1):
        if at < len(maps):
            blocks = {i: blocks[c] for i, c in maps[at].items()}
            if min(blocks.values()) < 0:
                plain_place(*levels[at], blocks, loads, limits, alpha, gamma)
        if min(blocks.values()) >= 0:
            plain_refine(*levels[at], blocks, loads, limits, alpha, gamma, multilevel.REFINE_ROUNDS, seed + 31 * at)
    return [blocks[i] for i in range(n)]


@settings(max_examples=60, deadline=None)
@given(st.integers(4, 70), st.integers(1, 4), st.lists(st.tuples(st.integers(0, 69), st.integers(0, 69)), max_size=150), st.lists(st.tuples(st.integers(0, 69), st.integers(0, 3)), max_size=30), st.floats(0.01, 1.5), st.integers(0, 5))
def test_multilevel_cut(n, k, pairs, held, alpha, seed):
    links = [(a % n, b % n, 1.0) for a, b in pairs if a % n != b % n]
    fixed = [(i % n, b % k, 1.0) for i, b in held]
    l_max = metrics.block_cap(n, k, "0.1") + 2
    level = multilevel.Level(np.ones(n, np.int64), *(np.array([x[j] for x in links], t) for j, t in ((0, np.int64), (1, np.int64), (2, float))), *(np.array([x[j] for x in fixed], t) for j, t in ((0, np.int64), (1, np.int64), (2, float))))
    mine, plain = np.zeros(k, np.int64), [0] * k
    got = multilevel.cut(level, mine, np.full(k, l_max), alpha, l_max, seed=seed)
    assert got.blocks.tolist() == plain_cut(n, links, fixed, plain, [l_max] * k, alpha, l_max, seed=seed) and mine.tolist() == plain


# ---- the buffered method

def plain_buffered(edges, k, delta, mode, alpha_kind, r=2):
    m, cap = len(edges), metrics.block_cap(len(edges), k)
    loads, met, last, out = [0] * k, defaultdict(set), {}, {}
    seen = [0, 0, 0]
    for batch in sorted({v // delta for _, v in edges}):
        own = [e for e, (_, v) in enumerate(edges) if v // delta == batch]
        at = {e: i for i, e in enumerate(own)}
        paths = defaultdict(list)
        for e in own:
            for x in edges[e]:
                paths[x].append(at[e])
        links = [(a, b, 1.0) for p in paths.values() for a, b in zip(p, p[1:])]
        fixed = []
        for e in own:
            u = edges[e][0]
            if u // delta < batch and mode != "none":
                known = [last[u]] if mode == "minimal" and u in last else sorted(met[u]) if mode != "minimal" else []
                if mode == "subset":
                    known = sorted(known, key=lambda b: ((e * 7919 + b * 104729) % 1_000_003, b))[:r]
                fixed += [(at[e], b, 1.0) for b in known]
        seen = [seen[0] + len(own), seen[1] + len(links), seen[2] + sum(len(p) <= 2 for p in paths.values())]
        guess = {"batch": None, "static": 2.0 * m, "dynamic": seen[1] / seen[0] * m, "dynamic_low": (2 * seen[0] - seen[2]) / seen[0] * m}[alpha_kind]
        alpha = math.sqrt(k) * (len(links) / len(own) ** 1.5 if guess is None else guess / m**1.5)
        blocks = plain_cut(len(own), links, fixed, loads, [cap] * k, alpha, cap)
        for e, b in zip(own, blocks):
            out[e] = b
            for x in edges[e]:
                met[x].add(b)
                last[x] = b
    return [out[e] for e in range(m)]


@settings(max_examples=40, deadline=None)
@given(GRAPHS, st.integers(1, 4), st.integers(2, 26), st.sampled_from(["minimal", "maximal", "subset", "none"]), st.sampled_from(["batch", "static", "dynamic", "dynamic_low"]))
def test_buffered(edges, k, delta, mode, alpha):
    u, v = (np.array([e[i] for e in edges]) for i in (0, 1))
    o = buffered.Options(k, delta, metrics.block_cap(len(edges), k), len(edges), mode, alpha, r=2)
    block, batch, stats, _ = buffered.run_batches(np.arange(len(edges)), u, v, o)
    assert block.tolist() == plain_buffered(edges, k, delta, mode, alpha)
    assert batch.tolist() == [y // delta for _, y in edges]


@settings(max_examples=30, deadline=None)
@given(GRAPHS, st.integers(1, 4), st.integers(1, 30))
def test_edge_budgets(edges, k, budget):
    """A batch of an edge budget begins where so many edges are owned before, and no vertex is split."""
    u, v = (np.array([e[i] for e in edges]) for i in (0, 1))
    o = buffered.Options(k, 1, metrics.block_cap(len(edges), k), len(edges), budget=budget)
    block, batch, _, _ = buffered.run_batches(np.arange(len(edges)), u, v, o)
    assert batch.tolist() == [sum(y < x for _, y in edges) // budget for _, x in edges]
    assert np.bincount(block, minlength=k).max() <= o.l_max


@settings(max_examples=30, deadline=None)
@given(GRAPHS, st.integers(2, 4), st.integers(3, 26))
def test_split_graph_keeps_edges_whole(edges, k, delta):
    """The split graph has twice the items and a heavy link more for each edge; every edge ends in one block with room."""
    u, v = (np.array([e[i] for e in edges]) for i in (0, 1))
    runs = []
    for line in ("contracted", "split"):
        o = buffered.Options(k, delta, metrics.block_cap(len(edges), k), len(edges), line=line)
        block, _, stats, _ = buffered.run_batches(np.arange(len(edges)), u, v, o)
        assert len(block) == len(edges) and np.bincount(block, minlength=k).max() <= o.l_max and (block >= 0).all()
        runs.append(stats)
    for one, two in zip(*runs):
        assert two["items"] == 2 * one["items"] and two["links"] == one["links"] + one["items"]


# ---- one-pass methods

def stream(edges):
    return sorted(edges, key=lambda e: (e[1], e[0]))


def plain_hdrf(order, k, cap, degree=None, copies=None, loads=None):
    copies, loads, seen, out = copies if copies is not None else defaultdict(set), loads if loads is not None else [0] * k, defaultdict(int), []
    for a, b in order:
        seen[a] += 1
        seen[b] += 1
        d = degree or seen
        share = d[a] / (d[a] + d[b])
        hi, lo = max(loads), min(loads)
        score = lambda i: (i in copies[a]) * (2 - share) + (i in copies[b]) * (1 + share) + 1.1 * (hi - loads[i]) / (1e-9 + hi - lo)  # noqa: B023, E731
        best = max((i for i in range(k) if loads[i] < cap), key=lambda i: (score(i), -i))
        out.append(best)
        loads[best] += 1
        copies[a].add(best)
        copies[b].add(best)
    return out


def plain_one_pass(order, k, cap, n, every):
    alpha, loads, nets, out = math.sqrt(k) * n / len(order) ** 1.5, [0] * k, defaultdict(set), []
    for e in order:
        hits = lambda i: sum(i in nets[x] for x in e)  # noqa: B023, E731
        best = min((alpha * 1.5 * loads[i] ** 0.5 - hits(i), loads[i], i) for i in range(k) if loads[i] < cap)[2]
        out.append(best)
        loads[best] += 1
        for x in e:
            nets[x] = nets[x] | {best} if every else {best}
    return out


def plain_two_phase(order, k, cap, linear):
    degree = defaultdict(int)
    for e in order:
        for x in e:
            degree[x] += 1
    own, volume, most = {x: x for x in degree}, dict(degree), 2 * len(order) / k
    for a, b in order:
        ca, cb = own[a], own[b]
        if ca != cb and max(volume[ca], volume[cb]) <= most:
            x, small, large = (a, ca, cb) if volume[ca] <= volume[cb] else (b, cb, ca)
            if volume[large] + degree[x] <= most:
                volume[large] += degree[x]
                volume[small] -= degree[x]
                own[x] = large
    full, home = [0] * k, {}
    for c in sorted(volume, key=lambda c: (-volume[c], c)):
        home[c] = full.index(min(full))
        full[home[c]] += volume[c]
    loads, copies, out = [0] * k, defaultdict(set), {}

    def put(e, i):
        out[e] = i
        loads[i] += 1
        for x in e:
            copies[x].add(i)

    for e in order:
        i, j = (home[own[x]] for x in e)
        if i == j and loads[i] < cap:
            put(e, i)
    for e in [e for e in order if e not in out]:
        if not linear:
            out[e] = plain_hdrf([e], k, cap, degree, copies, loads)[0]
            continue
        a, b = e
        share, total = degree[a] / (degree[a] + degree[b]), max(1, volume[own[a]] + volume[own[b]])
        scores = [(-((home[own[x]] in copies[a]) * (2 - share) + (home[own[x]] in copies[b]) * (1 + share) + volume[own[x]] / total), home[own[x]]) for x in e if loads[home[own[x]]] < cap]
        fall = (a if degree[a] >= degree[b] else b) % k
        put(e, min(scores)[1] if scores else fall if loads[fall] < cap else min((loads[i], i) for i in range(k) if loads[i] < cap)[1])
    return [out[e] for e in order]


def dense(edges):
    """Edges with vertices numbered without gaps, as a graph has them."""
    names = {x: i for i, x in enumerate(sorted({x for e in edges for x in e}))}
    return [(names[a], names[b]) for a, b in edges], len(names)


@settings(max_examples=60, deadline=None)
@given(GRAPHS, st.integers(1, 7), st.sampled_from(["hdrf", "hdrf_seen", "hdrf_exact", "fly", "fly_all", "two_phase", "two_phase_seen", "linear"]))
def test_one_pass(edges, k, method):
    edges, n = dense(edges)
    order, cap = stream(edges), metrics.block_cap(len(edges), k)
    degree = {x: sum(x in e for e in edges) for x in range(n)}
    kernel, plain = {
        "hdrf": (baselines.hdrf_kernel(), lambda: plain_hdrf(order, k, cap)), "hdrf_seen": (baselines.hdrf_kernel(scan="seen"), lambda: plain_hdrf(order, k, cap)),
        "hdrf_exact": (baselines.hdrf_kernel(degrees="exact"), lambda: plain_hdrf(order, k, cap, degree)),
        "fly": (onthefly.kernel(), lambda: plain_one_pass(order, k, cap, n, False)), "fly_all": (onthefly.kernel(net_memory="all"), lambda: plain_one_pass(order, k, cap, n, True)),
        "two_phase": (baselines.two_phase_kernel(), lambda: plain_two_phase(order, k, cap, False)), "two_phase_seen": (baselines.two_phase_kernel(scan="seen"), lambda: plain_two_phase(order, k, cap, False)),
        "linear": (baselines.two_phase_kernel("linear"), lambda: plain_two_phase(order, k, cap, True)),
    }[method]
    u, v = (np.array([e[i] for e in order]) for i in (0, 1))
    info: dict = {}
    assert list(kernel(u, v, n, k, np.full(k, cap), info)) == plain() and info["cells"] > 0


@settings(max_examples=40, deadline=None)
@given(GRAPHS, st.integers(1, 5))
def test_fennel_stream(edges, k):
    edges, n = dense(edges)
    near = defaultdict(list)
    for a, b in edges:
        near[a].append(b)
        near[b].append(a)
    alpha, cap, loads, plain = math.sqrt(k) * len(edges) / n**1.5, math.ceil(1.03 * n / k), [0] * k, []
    for x in range(n):
        inside = lambda i: sum(y < x and plain[y] == i for y in near[x])  # noqa: B023, E731
        best = min((-(inside(i) - alpha * 1.5 * loads[i] ** 0.5), loads[i], i) for i in range(k) if loads[i] < cap)[2]
        plain.append(best)
        loads[best] += 1
    starts = np.concatenate([[0], np.cumsum([len(near[x]) for x in range(n)])])
    flat = np.array([y for x in range(n) for y in sorted(near[x])])
    assert fennel.stream_vertices(n, starts, flat, k).tolist() == plain


def test_default_lanes():
    from edgeblocks.operators import sequential

    assert sequential.default_lanes(1000, 8) == 1
    assert sequential.default_lanes(10**12, 1024) == 50_000
    m, k = 10**9, 10**7  # balance leaves three edges a block
    assert sequential.default_lanes(m, k) == 3


def test_tables_of_trials():
    from edgeblocks.plans import trials

    assert {f.name: str(f.type) for f in trials._ARROW}["blocks"] == "list<item: int32>"
    with pytest.raises(MemoryError):
        trials._room(trials.CELLS_LIMIT + 1)
    assert pa.list_(pa.int32()) == trials._TYPES["array<int>"]


@pytest.mark.parametrize("mode", ["maximal", "subset"])
def test_pairs_met_in_the_place_of_a_table(mode, monkeypatch):
    """The same blocks from the pairs; a study's run with more cells than a table may have is no failure (it was one, and SQL expects its edges)."""
    from edgeblocks.plans import trials

    rnd = np.random.default_rng(5)
    key = np.unique(rnd.integers(0, 300 * 300, 3000))
    u, v = key // 300, 300 + key % 300
    a = trials.Arrays(u, v, 600, np.lexsort((u, v)))
    runs = []
    for cells in (1 << 26, 0):
        monkeypatch.setattr(buffered, "TABLE_CELLS", cells)
        monkeypatch.setattr(trials, "CELLS_LIMIT", 100)
        info = {}
        runs.append(trials._buffered(a, 32, metrics.block_cap(len(u), 32), info, 50, mode=mode))
    assert (runs[0] == runs[1]).all()
    assert 600 < info["cells"] - 32 < 600 * 32


def test_kernels_hold_arrays_of_edges(monkeypatch):
    """Edges are Python numbers only a slice at a time, and a vertex is no list of blocks."""
    import tracemalloc

    from edgeblocks.operators import sequential

    rnd = np.random.default_rng(2)
    key = np.unique(rnd.integers(0, 4000 * 4000, 40000))
    u, v = (key // 4000).astype(np.int32), (4000 + key % 4000).astype(np.int32)
    kept = {}
    monkeypatch.setattr(sequential, "SLICE", 256, raising=False)
    monkeypatch.setattr(sequential, "run", lambda g, k, kernel, *a: kept.setdefault(len(kept), kernel))
    baselines.neighbour_expansion(None, 8, sample=0.01)
    baselines.restricted_buffer(None, 8, 64)
    for kernel in (*kept.values(), baselines.hdrf_kernel(scan="seen"), baselines.hdrf_kernel(degrees="exact", scan="seen"), baselines.two_phase_kernel(scan="seen"), baselines.two_phase_kernel("linear", scan="seen")):
        tracemalloc.start()
        kernel(u, v, 8000, 8, np.full(8, metrics.block_cap(len(u), 8)))
        peak = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        assert peak < 90 * len(u)


def test_one_lane_at_every_size(spark, small, monkeypatch):
    """The stream order does not hang on the number of edges: no method takes lanes unasked, and a lane in a file gives the same blocks."""
    from edgeblocks.operators import sequential
    from edgeblocks.plans.graphs import graph

    g = graph(spark, small, "part_order")
    for run in (lambda: baselines.hdrf(g, 4, degrees="exact"), lambda: baselines.two_phase(g, 4), lambda: baselines.two_phase(g, 4, "linear"), lambda: baselines.restricted_buffer(g, 4)):
        got = []
        for edges, task in ((20_000_000, 1 << 20), (100, 200)):
            monkeypatch.setattr(sequential, "LANE_EDGES", edges)
            monkeypatch.setattr(sequential, "SORTED_EDGES", task, raising=False)
            got.append(sorted(tuple(r) for r in run().assign.select("eid", "block", "batch").collect()))
        assert got[0] == got[1] and len(got[0]) == g.m > 200


@settings(max_examples=40, deadline=None)
@given(GRAPHS, st.integers(1, 7), st.integers(1, 6))
def test_restricted_buffer(edges, k, buffer):
    """Edges without a met end wait; the buffer is emptied by degree; blocks are scored as in HDRF, without a table of vertices times blocks."""
    edges, n = dense(edges)
    order, cap = stream(edges), metrics.block_cap(len(edges), k)
    degree = {x: sum(x in e for e in edges) for x in range(n)}
    copies, loads, held, plain = defaultdict(set), [0] * k, [], {}

    def put(e):
        plain[e] = plain_hdrf([e], k, cap, degree, copies, loads)[0]

    def flush():
        for e in sorted(held, key=lambda e: (degree[e[0]] + degree[e[1]], order.index(e))):
            put(e)
        held.clear()

    for e in order:
        if copies[e[0]] or copies[e[1]] or not any(loads):
            put(e)
        else:
            held.append(e)
            if len(held) >= buffer:
                flush()
    flush()
    u, v = (np.array([e[i] for e in order]) for i in (0, 1))
    kept = []
    with pytest.MonkeyPatch.context() as m:
        m.setattr(baselines.sequential, "run", lambda g, k, kernel, *a: kept.append(kernel))
        m.setattr(baselines, "_Greedy", None)
        baselines.restricted_buffer(None, k, buffer)
        assert list(kept[0](u, v, n, k, np.full(k, cap))) == [plain[e] for e in order]
