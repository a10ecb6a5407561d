"""The buffered multilevel edge partitioner.

Vertices come in batches; each batch owns the edges whose later end it holds, turns them into a path-linked graph whose items
are edges, adds links to the blocks that its earlier ends met, and cuts that graph. Placements are final. A batch holds delta
vertices or, with budget, as many as own that many edges, which evens out batches where hubs are heavy.

exec="single_task" runs all batches in one grouped-map task and carries the state in the worker. exec="stream" does the same over edges sorted by
batch, of which the task holds one batch at a time; clusters, which depend on a batch alone, are made before by as many tasks as there are. Its state is the memory alone (4 bytes a vertex, and a bit per vertex and block in maximal and
subset mode), so it serves graphs of any number of edges whose vertices are few enough. exec="jobs" keeps
the state in tables: a Spark job takes a chunk of consecutive rounds of up to CHUNK_EDGES edges and appends its rows to the shared folder. A round cuts one batch
in each of the lanes against the state after the last round. Rounds of a chunk run in one task, which carries their state on; a round above the bound is a
chunk of its own with a task per lane. What a chunk changes in the memory is appended too, and merged every COMPACT chunks, so a chunk costs what it
touches. With one lane both give the same blocks, however rounds fall into chunks. With more, a lane may fill a block only up to its quota, so balance stays strict, and what lanes
of one round do not see of each other is the price. Neither holds a table of vertices times blocks in minimal mode; new replicas per
batch are counted afterwards from the assignment, at every size.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import fresh_dir, materialise, remove_dir
from . import batching, fennel, metrics, multilevel, state
from .canonical import Graph
from .metrics import block_cap

MODES, ALPHAS, INITS = ("minimal", "maximal", "subset", "none"), ("batch", "static", "dynamic", "dynamic_low"), ("two_set", "two_set_bucket", "all_k")
#: Edges that one task may carry through all batches; chunks after which the memory's changes are merged.
SINGLE_TASK_EDGES, COMPACT = 1_000_000, 8
#: Edges of the rounds that one job cuts, and of the batches that one task clusters ahead of a stream.
CHUNK_EDGES = 1_000_000
#: Bytes of a task's table of cells, vertices times blocks (a bit each), above which it holds the pairs that were met instead; vertices whose memory a streaming task holds.
TABLE_CELLS, STREAM_VERTICES = 1 << 26, 1 << 26
#: Edges that a streaming task hands over at a time.
HANDED = 1 << 16
#: Weight of the link between the two copies of an edge in the split graph.
HEAVY = 1e6


@dataclass(frozen=True)
class Options:
    k: int
    delta: int
    l_max: int
    m: int
    mode: str = "minimal"
    alpha: str = "batch"
    init: str = "two_set"
    r: int = 5
    y: float = 2.0
    gamma: float = fennel.GAMMA
    order: str = "eid"
    line: str = "contracted"
    cluster_rounds: int = multilevel.CLUSTER_ROUNDS
    refine_rounds: int = multilevel.REFINE_ROUNDS
    seed: int = 0
    measure: bool = True
    budget: int | None = None


@dataclass
class Partition:
    """assign (eid, u, v, block, batch) and, per batch, stats (batch, items, links, block_links, gamma, cut, scores, moves, apart, seconds, peak_kb)."""

    assign: DataFrame
    stats: DataFrame
    graph: Graph
    k: int
    eps: float | str
    passes: int = 1
    notes: dict = field(default_factory=dict)


def path_links(u: np.ndarray, v: np.ndarray, eid: np.ndarray, order: str = "eid", seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Links between positions of edges: along each vertex, from one of its edges to the next."""
    end = np.concatenate([u, v])
    at = np.concatenate([np.arange(len(u))] * 2)
    bits = len(u).bit_length()
    if order == "eid" and len(eid) and (eid[1:] > eid[:-1]).all() and not int(end.max()) >> (62 - bits):  # positions stand by eid: end and position are one number
        both = np.sort(end.astype(np.int64) << bits | at)
        end, at = both >> bits, both & ((1 << bits) - 1)
        same = end[:-1] == end[1:]
        return at[:-1][same], at[1:][same]
    rank = {"eid": lambda: eid[at], "nbr": lambda: np.concatenate([v, u]), "random": lambda: multilevel._hash(eid[at] * 2 + (np.arange(len(at)) >= len(u)), seed)}[order]()
    o = np.lexsort((eid[at], rank, end))
    same = end[o][:-1] == end[o][1:]
    return at[o][:-1][same], at[o][1:][same]


class Pairs:
    """A growing set of (vertex, block) as sorted runs of vertex x k + block, each more than twice as long as the next: what is met, not n x k cells."""

    def __init__(self, k: int):
        self.k = k
        self.runs: list[np.ndarray] = []

    def add(self, keys: np.ndarray) -> None:
        self.runs.append(np.unique(keys))
        while len(self.runs) > 1 and len(self.runs[-2]) <= 2 * len(self.runs[-1]):
            self.runs[-2:] = [np.union1d(self.runs[-2], self.runs[-1])]

    def of(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(positions in v, blocks) of what each vertex of v met, in order of both."""
        found = [np.zeros(0, np.int64)]
        for run in self.runs:
            lo, hi = np.searchsorted(run, v * self.k), np.searchsorted(run, (v + 1) * self.k)
            row = np.repeat(np.arange(len(v)), hi - lo)
            at = np.arange(len(row)) + np.repeat(lo - (np.cumsum(hi - lo) - (hi - lo)), hi - lo)
            found.append(row * self.k + run[at] % self.k)
        keys = np.unique(np.concatenate(found))
        return keys // self.k, keys % self.k

    @property
    def size(self) -> int:
        return len(np.unique(np.concatenate(self.runs))) if self.runs else 0


class Memory:
    """Blocks met by vertices: the latest of each, and in maximal and subset mode all of them, as a table of n x k bits while that is small and
    as the pairs met beyond TABLE_CELLS. With measure, the pairs met so far are kept beside it, for counting new replicas only."""

    def __init__(self, mode: str, n: int, k: int, measure: bool = False):
        self.mode, self.k = mode, k
        self.last = np.full(n, -1, np.int32)
        every = mode in ("maximal", "subset")
        self.width = -(-k // 8)
        self.table = np.zeros(n * self.width, np.uint8) if every and n * self.width <= TABLE_CELLS else None
        self.pairs = Pairs(k) if every and self.table is None else None
        self.met = np.zeros(0, np.int64) if measure else None

    def cells(self) -> int:
        """Entries that the mode needs."""
        if self.table is not None:
            return len(self.last) * self.k
        return 0 if self.mode == "none" else (self.last if self.pairs is None else self.pairs).size

    def links(self, past: np.ndarray, r: int, seed: int, eid: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(positions of edges, blocks) that the past ends (-1: none) met; subset draws r of them by hash."""
        items = np.flatnonzero(past >= 0)
        if self.mode == "none" or not len(items):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        if self.mode == "minimal":
            items = items[self.last[past[items]] >= 0]
            return items, self.last[past[items]].astype(np.int64)
        if self.pairs is None:
            row, block = np.nonzero(np.unpackbits(self.table.reshape(-1, self.width)[past[items]], axis=1, count=self.k, bitorder="little"))
        else:
            row, block = self.pairs.of(past[items])
        if self.mode == "subset":
            o = np.lexsort((block, (eid[items[row]] * 7919 + block * 104729 + seed) % 1_000_003, row))
            row, block = row[o], block[o]
            first = np.searchsorted(row, row)
            keep = np.arange(len(row)) - first < r
            row, block = row[keep], block[keep]
        return items[row], block

    def gained(self, u: np.ndarray, v: np.ndarray, block: np.ndarray) -> int | None:
        """New replicas of a batch; known only where they are measured."""
        if self.met is None:
            return None
        keys = np.unique(np.concatenate([u * self.k + block, v * self.k + block]))
        new = keys[~np.isin(keys, self.met, assume_unique=True)]
        fresh = np.unique(new // self.k)
        at = np.minimum(np.searchsorted(self.met, fresh * self.k), max(len(self.met) - 1, 0))
        known = (self.met[at] // self.k == fresh) if len(self.met) else np.zeros(len(fresh), bool)
        return len(new) - int((~known).sum())

    def take(self, v: np.ndarray, block: np.ndarray) -> None:
        """What was met before, latest last."""
        self.last[v] = block
        if self.table is not None:
            np.bitwise_or.at(self.table, v * self.width + (block >> 3), np.left_shift(1, block & 7).astype(np.uint8))
        if self.pairs is not None:
            self.pairs.add(v * self.k + block)

    def add(self, u: np.ndarray, v: np.ndarray, eid: np.ndarray, block: np.ndarray) -> None:
        o = np.argsort(np.concatenate([eid, eid]), kind="stable")
        ends, blocks = np.concatenate([u, v])[o], np.concatenate([block, block])[o]
        self.take(ends, blocks)  # of repeated vertices the last stays
        if self.met is not None:
            self.met = np.union1d(self.met, ends * self.k + blocks)


def _low_degrees(u: np.ndarray, v: np.ndarray) -> int:
    """Vertices with one or two edges of a batch."""
    return int((np.unique(np.concatenate([u, v]), return_counts=True)[1] <= 2).sum())


def cut_batch(u, v, eid, past, block_items, block_ids, loads, limits, o: Options, seen: list[int], maps: list[np.ndarray] | None = None) -> tuple[np.ndarray, dict]:
    """Blocks of a batch's edges (arrays sorted by eid); loads are raised in place. seen: edges, links and low degrees of the batches so far;
    maps: clusters that were made before."""
    a, b = path_links(u, v, eid, o.order, o.seed) if o.line == "contracted" else _copy_links(u, v, eid, o)
    seen[0] += len(eid)
    seen[1] += len(a)
    if o.alpha == "dynamic_low":
        seen[2] += _low_degrees(u, v)
    alpha = {
        "batch": lambda: fennel.alpha_batch(o.k, len(eid), len(a)), "static": lambda: fennel.alpha_static(o.k, o.m, o.y),
        "dynamic": lambda: fennel.alpha_dynamic(o.k, o.m, seen[0], seen[1], o.y), "dynamic_low": lambda: fennel.alpha_dynamic(o.k, o.m, seen[0], 2 * seen[0] - seen[2], o.y),
    }[o.alpha]()
    if o.line == "split":
        return _cut_copies(u, eid, past, block_items, block_ids, loads, limits, o, a, b, alpha)
    level = multilevel.Level(np.ones(len(eid), np.int64), a, b, np.ones(len(a)), np.array(block_items, np.int64), np.array(block_ids, np.int64), np.ones(len(block_items)))
    got = multilevel.cut(level, loads, limits, alpha, o.l_max, o.gamma, o.init, o.cluster_rounds, o.refine_rounds, o.seed, maps)
    blocks = got.blocks
    cut = int((blocks[a] != blocks[b]).sum() + (blocks[level.items] != level.fixed).sum())
    return blocks, {"items": len(eid), "links": len(a), "block_links": len(block_items), "cut": cut, "scores": got.scores, "moves": got.moves, "apart": 0}


def _copy_links(u, v, eid, o: Options) -> tuple[np.ndarray, np.ndarray]:
    """Auxiliary links of the split graph: copy i is the u end of edge i, copy n + i its v end; a path through the copies of each vertex."""
    n = len(u)
    at, end = np.concatenate([np.arange(n)] * 2), np.concatenate([u, v])
    rank = {"eid": lambda: eid[at], "nbr": lambda: np.concatenate([v, u]), "random": lambda: multilevel._hash(eid[at] * 2 + (np.arange(2 * n) >= n), o.seed)}[o.order]()
    order = np.lexsort((eid[at], rank, end))
    same = end[order][:-1] == end[order][1:]
    return order[:-1][same], order[1:][same]


def _cut_copies(u, eid, past, block_items, block_ids, loads, limits, o: Options, a, b, alpha: float) -> tuple[np.ndarray, dict]:
    """Cuts the split graph itself: twice as many items, heavy links between the two copies of an edge. An edge whose copies end up apart
    goes to the block of its first copy if that has room, else to that of the second, else to the lightest.

    Loads count copies here, so limits double; the penalty of a pair of copies is that of an edge if alpha shrinks by 2 ** gamma."""
    n, twins = len(eid), np.arange(len(eid))
    items = np.array(block_items, np.int64)
    if past is not None and len(items):
        items = np.where(past[items] == u[items], items, items + n)
    level = multilevel.Level(np.ones(2 * n, np.int64), np.concatenate([twins, a]), np.concatenate([twins + n, b]), np.concatenate([np.full(n, HEAVY), np.ones(len(a))]), items, np.array(block_ids, np.int64), np.ones(len(items)))
    got = multilevel.cut(level, 2 * loads, 2 * limits, alpha / 2**o.gamma, 2 * o.l_max, o.gamma, o.init, o.cluster_rounds, o.refine_rounds, o.seed)
    first, second = got.blocks[:n], got.blocks[n:]
    blocks = np.where(first == second, first, -1)
    loads += np.bincount(blocks[blocks >= 0], minlength=o.k)
    for e in np.flatnonzero(blocks < 0).tolist():
        choice = [i for i in (int(first[e]), int(second[e])) if loads[i] < limits[i]]
        blocks[e] = choice[0] if choice else int(np.where(loads < limits, loads, 1 << 62).argmin())
        loads[blocks[e]] += 1
    cut = int((blocks[a % n] != blocks[b % n]).sum() + (blocks[items % n] != level.fixed).sum()) if n else 0
    return blocks, {"items": 2 * n, "links": n + len(a), "block_links": len(items), "cut": cut, "scores": got.scores, "moves": got.moves, "apart": int((first != second).sum())}


STATS = [("batch", pa.int64()), ("items", pa.int64()), ("links", pa.int64()), ("block_links", pa.int64()), ("gamma", pa.int64()), ("cut", pa.int64()), ("scores", pa.int64()), ("moves", pa.int64()), ("apart", pa.int64()), ("seconds", pa.float64()), ("peak_kb", pa.int64())]
_ASSIGN_DDL = "eid bigint, u bigint, v bigint, block int, batch bigint"
_OUT_DDL = _ASSIGN_DDL + ", " + ", ".join(f"s_{n} {'double' if t == pa.float64() else 'bigint'}" for n, t in STATS)


def _out_table(eid, u, v, block, batch, stats: list[dict]) -> pa.Table:
    """Placed edges, then a row per batch with its figures (eid null)."""
    n = len(stats)
    cols = [pa.array(np.asarray(x)) for x in (eid, u, v)] + [pa.array(np.asarray(block, np.int32)), pa.array(np.asarray(batch))]
    cols = [pa.concat_arrays([c, pa.nulls(n, c.type)]) for c in cols]
    more = [pa.concat_arrays([pa.nulls(len(eid), t), pa.array([s[name] for s in stats], t)]) for name, t in STATS]
    return pa.Table.from_arrays(cols + more, names=["eid", "u", "v", "block", "batch", *(f"s_{n}" for n, _ in STATS)])


def _measured(run, *args):
    import resource
    import time

    began = time.perf_counter()
    out = run(*args)
    return out, time.perf_counter() - began, resource.getrusage(resource.RUSAGE_SELF).ru_maxrss


def vertex_batches(v: np.ndarray, n: int, o: Options) -> np.ndarray:
    """Batch of each vertex, from the later ends of all edges."""
    if o.budget is None:
        return np.arange(n) // o.delta
    own = np.bincount(v, minlength=n)
    return (np.cumsum(own) - own) // o.budget


def run_batches(eid: np.ndarray, u: np.ndarray, v: np.ndarray, o: Options) -> tuple[np.ndarray, np.ndarray, list[dict], Memory]:
    """Blocks and batches of edges (sorted by eid), figures of each batch, and the memory at the end."""
    n = int(v.max(initial=-1)) + 1
    of = vertex_batches(v, n, o)
    order = np.lexsort((eid, of[v]))
    batch = of[v][order]
    starts = np.flatnonzero(np.diff(batch, prepend=-1)) if len(eid) else np.zeros(0, np.int64)
    block = np.empty(len(eid), np.int64)
    loads, limits, memory, seen, stats = np.zeros(o.k, np.int64), np.full(o.k, o.l_max), Memory(o.mode, n, o.k, o.measure), [0, 0, 0], []
    for lo, hi in zip(starts, np.append(starts[1:], len(eid))):
        own = order[lo:hi]
        past = np.where(of[u[own]] < batch[lo], u[own], -1)
        links = memory.links(past, o.r, o.seed, eid[own])
        (block[own], s), seconds, peak = _measured(cut_batch, u[own], v[own], eid[own], past, *links, loads, limits, o, seen)
        stats.append({**s, "batch": int(batch[lo]), "gamma": memory.gained(u[own], v[own], block[own]), "seconds": seconds, "peak_kb": peak})
        memory.add(u[own], v[own], eid[own], block[own])
    return block, of[v], stats, memory


def _all_batches(o: Options):
    def run(table: pa.Table) -> pa.Table:
        eid, u, v = (table.column(c).to_numpy() for c in ("eid", "u", "v"))
        order = np.argsort(eid, kind="stable")
        eid, u, v = eid[order], u[order], v[order]
        block, batch, stats, _ = run_batches(eid, u, v, o)
        return _out_table(eid, u, v, block, batch, stats)

    return run


#: Edges in a row that a clustering task hands on.
PIECE = 256
_PIECES_DDL = "batch bigint, piece int, eid array<bigint>, u array<bigint>, v array<bigint>, labels array<int>"


def _batches_of(it: Iterator[pa.RecordBatch], read) -> Iterator[tuple]:
    """(batch, arrays) of rows sorted by batch; read(rows) gives the arrays of some rows of one batch."""
    parts, last = [], -1
    for b in it:
        batch = b.column("batch").to_numpy()
        cuts = np.flatnonzero(np.diff(batch, prepend=-1)).tolist()
        for lo, hi in zip(cuts, [*cuts[1:], len(batch)]):
            if parts and batch[lo] != last:
                yield last, [np.concatenate(x) for x in zip(*parts)]
                parts = []
            last = int(batch[lo])
            parts.append(read(b.slice(lo, hi - lo)))
    if parts:
        yield last, [np.concatenate(x) for x in zip(*parts)]


def _clustered(o: Options):
    """Rows (batch, eid, u, v), sorted by batch and eid, in pieces of PIECE edges with the clusters of their batch on every level, edge by edge."""

    def lists(x: np.ndarray, ends: np.ndarray) -> pa.Array:
        return pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(x))

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, (eid, u, v) in _batches_of(it, lambda rows: [rows.column(c).to_numpy() for c in ("eid", "u", "v")]):
            labels = []
            if o.line == "contracted":
                for m in multilevel.clusters(len(eid), *path_links(u, v, eid, o.order, o.seed), o.k, o.l_max, o.cluster_rounds, o.seed):
                    labels.append(m[labels[-1]] if labels else m)
            flat = np.array(labels, np.int32).reshape(len(labels), len(eid)).T.ravel()
            for lo in range(0, len(eid), HANDED):
                hi = min(lo + HANDED, len(eid))
                ends = np.append(np.arange(0, hi - lo, PIECE), hi - lo)
                pieces = np.arange(len(ends) - 1, dtype=np.int32) + lo // PIECE
                some = [lists(x[lo:hi], ends) for x in (eid, u, v)] + [lists(flat[lo * len(labels) : hi * len(labels)], ends * len(labels))]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(pieces), batch)), pa.array(pieces), *some], names=["batch", "piece", "eid", "u", "v", "labels"])

    return run


def _maps_of(labels: np.ndarray, n: int) -> list[np.ndarray]:
    """Clusters between the levels, from those of each edge."""
    maps = []
    for of in labels.reshape(n, -1).T.astype(np.int64):
        if maps:
            m = np.zeros(int(below.max()) + 1, np.int64)
            m[below] = of
        maps.append(m if maps else of)
        below = of
    return maps


def _streamed(o: Options, n: int):
    """All batches over the pieces of _clustered, sorted by batch and piece; the state is carried on, a batch is held at a time."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        loads, limits, memory, seen = np.zeros(o.k, np.int64), np.full(o.k, o.l_max), Memory(o.mode, n, o.k), [0, 0, 0]
        out, stats, held = [], [], 0

        def handed() -> list[pa.RecordBatch]:
            table = _out_table(*(np.concatenate(x) for x in zip(*out)), stats)
            out.clear()
            stats.clear()
            return table.combine_chunks().to_batches(max_chunksize=HANDED)

        for batch, (eid, u, v, labels) in _batches_of(it, lambda rows: [rows.column(c).flatten().to_numpy() for c in ("eid", "u", "v", "labels")]):
            maps = _maps_of(labels, len(eid)) if o.line == "contracted" else None
            past = np.where(u // o.delta < batch, u, -1)
            links = memory.links(past, o.r, o.seed, eid)
            (block, s), seconds, peak = _measured(cut_batch, u, v, eid, past, *links, loads, limits, o, seen, maps)
            memory.add(u, v, eid, block)
            out.append((eid, u, v, block, np.full(len(eid), batch)))
            stats.append({**s, "batch": batch, "gamma": None, "seconds": seconds, "peak_kb": peak})
            held += len(eid)
            if held >= HANDED:
                yield from handed()
                held = 0
        if out:
            yield from handed()

    return run


def _split_out(g: Graph, raw: DataFrame, k: int, eps, rounds: int | None = None, **notes) -> Partition:
    """rounds: batches of one round share what number modulo rounds; without it every batch is a round of its own."""
    assign = raw.where("eid IS NOT NULL").select("eid", "u", "v", "block", "batch")
    stats = raw.where("eid IS NULL").select(*(F.col(f"s_{n}").alias(n) for n, _ in STATS if n != "gamma"))
    gained = metrics.new_replicas(assign, None if rounds is None else F.col("batch") % rounds)
    return Partition(assign, stats.join(gained, "batch", "left"), g, k, eps, notes=notes)


def partition(g: Graph, k: int, eps: float | str = "0.03", delta: int = 32 * 1024, mode: str = "minimal", alpha: str = "batch", init: str = "two_set", seed: int = 0, lanes: int = 1, exec: str | None = None, **more) -> Partition:  # noqa: A002
    """Blocks for all edges of g; see the module text. delta >= n makes the whole graph one batch."""
    if mode not in MODES or alpha not in ALPHAS or init not in INITS:
        raise ValueError((mode, alpha, init))
    o = Options(k, delta, block_cap(g.m, k, eps), g.m, mode, alpha, init, seed=seed, **{"measure": False, **more})
    if exec is None:
        streams = lanes == 1 and o.budget is None and g.n <= STREAM_VERTICES and (mode not in ("maximal", "subset") or g.n * -(-k // 8) <= TABLE_CELLS) and g.n > delta
        exec = "single_task" if lanes == 1 and g.m <= SINGLE_TASK_EDGES else "stream" if streams else "jobs"  # noqa: A001
    if exec == "stream":
        tasks = max(g.edges.sparkSession.sparkContext.defaultParallelism, -(-g.m // CHUNK_EDGES))
        rows = g.edges.select(F.floor(F.col("v") / F.lit(delta)).alias("batch"), "eid", "u", "v").repartition(tasks, "batch").sortWithinPartitions("batch", "eid")
        rows = rows.mapInArrow(_clustered(o), _PIECES_DDL).repartition(1).sortWithinPartitions("batch", "piece")
        return _split_out(g, materialise(rows.mapInArrow(_streamed(o, g.n), _OUT_DDL), "buffered"), k, eps, mode=mode)
    if exec == "single_task":
        raw = materialise(g.edges.withColumn("lane", F.lit(0)).groupBy("lane").applyInArrow(_all_batches(o), _OUT_DDL), "buffered")
        return _split_out(g, raw, k, eps, mode=mode)
    return _rounds(g, o, lanes, eps)


def quotas(loads: np.ndarray, l_max: int, owned: np.ndarray) -> np.ndarray:
    """Per lane and block, how many edges a lane may add: within the block's room in sum, and enough for what each lane owns."""
    room = np.maximum(l_max - loads, 0)
    total = max(int(owned.sum()), 1)
    q = room[None, :] * owned[:, None] // total
    left = room - q.sum(axis=0)
    need = np.maximum(owned - q.sum(axis=1), 0)
    for lane in np.argsort(-need, kind="stable"):
        for block in np.argsort(-left, kind="stable"):
            take = min(int(need[lane]), int(left[block]))
            q[lane, block] += take
            left[block] -= take
            need[lane] -= take
            if not need[lane]:
                break
    for lane in np.flatnonzero(need):  # surplus of other lanes
        for other in np.argsort(owned - q.sum(axis=1), kind="stable"):
            spare = int(q[other].sum() - owned[other])
            for block in np.argsort(-q[other], kind="stable"):
                take = min(int(need[lane]), spare, int(q[other, block]))
                if take > 0:
                    q[other, block] -= take
                    q[lane, block] += take
                    need[lane] -= take
                    spare -= take
    return q


#: What the batches of a chunk add to seen: edges, links and vertices of low degree.
_CHUNK_DDL = _OUT_DDL + ", seen_edges bigint, seen_links bigint, seen_low bigint"


def _chunk_kernel(o: Options, rounds: int, loads: np.ndarray, seen: list[int], owned: dict[int, np.ndarray]):
    """Cuts the batches of some rounds in order, against the state after the round before; the second table is what earlier chunks left of the
    vertices that the batches meet again. A task sees all lanes of its rounds, or one lane of the only round."""

    def run(table: pa.Table, held: pa.Table) -> pa.Table:
        table = table.sort_by([("round", "ascending"), ("lane", "ascending"), ("eid", "ascending")])
        eid, u, v, past, rnd, lane, batch = (table.column(c).to_numpy() for c in ("eid", "u", "v", "past", "round", "lane", "batch"))
        del table
        ids, local = np.unique(np.concatenate([u, v]), return_inverse=True)
        a, b = local[: len(eid)], local[len(eid) :]
        before = np.where(past < 0, -1, np.where(past == u, a, b))
        del local, past
        memory = Memory(o.mode, len(ids), o.k)
        if held.num_rows:
            known = held.sort_by([("seq", "ascending"), ("at", "ascending")])
            memory.take(np.searchsorted(ids, known.column("v").to_numpy()), known.column("block").to_numpy())
        now, told, block, stats = loads.copy(), list(seen), np.empty(len(eid), np.int64), []
        starts = np.flatnonzero(np.diff(rnd, prepend=-1))
        for lo, hi in zip(starts, np.append(starts[1:], len(eid))):
            own = owned[int(rnd[lo])]
            q, after = quotas(now, o.l_max, own), list(told)
            cuts = np.flatnonzero(np.diff(lane[lo:hi], prepend=-1)) + lo
            for x, y in zip(cuts, np.append(cuts[1:], hi)):
                s, mine, theirs = slice(x, y), now.copy(), list(told)
                links = memory.links(before[s], o.r, o.seed, eid[s])
                (block[s], figures), seconds, peak = _measured(cut_batch, u[s], v[s], eid[s], np.where(before[s] < 0, -1, ids[before[s]]), *links, mine, now + q[lane[x]], o, theirs)
                added = [n - m for n, m in zip(theirs, told)]
                after = [n + m for n, m in zip(after, added)]
                stats.append({**figures, "batch": int(batch[x]), "gamma": None, "seconds": seconds, "peak_kb": peak, "seen": added})
            told = after
            memory.add(a[lo:hi], b[lo:hi], eid[lo:hi], block[lo:hi])
            now += np.bincount(block[lo:hi], minlength=o.k)
        out = _out_table(eid, u, v, block, batch, stats)
        for i, name in enumerate(("seen_edges", "seen_links", "seen_low")):
            out = out.append_column(name, pa.concat_arrays([pa.nulls(len(eid), pa.int64()), pa.array([s["seen"][i] for s in stats], pa.int64())]))
        return out

    return run


class RoundMemory:
    """Memory as a base table and what the chunks since added; merged every COMPACT chunks, after which the older files go."""

    def __init__(self, spark, mode: str):
        self.spark, self.kind = spark, "minimal" if mode == "minimal" else "maximal"
        self.parts: list[str] = []
        self.schema = None

    def add(self, placed: DataFrame) -> None:
        new = state.update(None, placed, self.kind)
        self.schema = new.schema
        self._write(new)
        if len(self.parts) > COMPACT:
            old, self.parts = self.parts, []
            self._write(state.merge(self.spark.read.schema(self.schema).parquet(*old), self.kind))
            for path in old:
                remove_dir(self.spark, path)

    def _write(self, rows: DataFrame) -> None:
        path = fresh_dir(self.spark, "memory")
        rows.write.parquet(path)
        self.parts.append(path)

    def of(self, wanted: DataFrame) -> DataFrame:
        """(slot, v, block, seq, at) of what the wanted (task, past) met; in minimal mode the latest only."""
        held = self.spark.read.schema(self.schema).parquet(*self.parts)
        wanted = wanted.select(F.col("task").alias("slot"), "past")
        met = wanted.join(held.select(F.col("v").alias("past"), F.col("block").cast("long").alias("block"), "seq", F.col("eid").alias("at")), "past")
        if self.kind == "minimal":
            return met.groupBy("slot", "past").agg(F.max_by(F.struct("block", "seq", "at"), F.struct("seq", "at")).alias("x")).select("slot", F.col("past").alias("v"), "x.*")
        return met.groupBy("slot", "past", "block").agg(F.max("seq").alias("seq")).select("slot", F.col("past").alias("v"), "block", "seq", F.lit(0).cast("long").alias("at"))


def _rounds(g: Graph, o: Options, lanes: int, eps) -> Partition:
    """A job per chunk of rounds. The driver holds the loads of the blocks and the sizes of the batches, nothing else."""
    spark = g.edges.sparkSession
    edges = g.edges
    if o.budget is None:
        n_batches = max(1, -(-g.n // o.delta))
        edges = edges.withColumns({"bu": F.floor(F.col("u") / F.lit(o.delta)), "bv": F.floor(F.col("v") / F.lit(o.delta))})
    else:
        of = batching.budget_batches(g.edges, o.budget)
        edges = edges.join(of.select(F.col("v").alias("u"), F.col("batch").alias("bu")), "u").join(of.select("v", F.col("batch").alias("bv")), "v")
        n_batches = max(1, -(-g.m // o.budget))
    rounds = -(-n_batches // lanes)
    time_of = lambda b: (b % rounds) * lanes + F.floor(b / rounds)
    tu, tv = time_of(F.col("bu")), time_of(F.col("bv"))
    later = tu > tv
    plan = edges.withColumns({"time": F.greatest(tu, tv), "past": F.when(tu != tv, F.when(later, F.col("v")).otherwise(F.col("u"))).otherwise(-1), "batch": F.when(later, F.col("bu")).otherwise(F.col("bv"))}).drop("bu", "bv")
    plan = plan.withColumns({"round": F.floor(F.col("time") / lanes).cast("int"), "lane": (F.col("time") % lanes).cast("int")}).drop("time")
    plan = materialise(plan, "plan") if o.budget is not None else plan
    owned: dict[int, np.ndarray] = {}
    for r in plan.groupBy("round", "lane").count().collect():
        owned.setdefault(r["round"], np.zeros(lanes, np.int64))[r["lane"]] = r["count"]
    if not owned:
        return _split_out(g, spark.createDataFrame([], _OUT_DDL), o.k, eps)
    chunks = chunks_of(owned)
    out = fresh_dir(spark, "placed")
    ends = [c[-1] for c in chunks[:-1]]
    if ends:  # the edges of a chunk side by side
        folder = fresh_dir(spark, "rounds")
        cuts = spark.createDataFrame([(r, i) for i, c in enumerate(chunks) for r in c], "round int, chunk int")
        plan.join(F.broadcast(cuts), "round").repartition("chunk", "lane").write.partitionBy("chunk").parquet(folder)
        plan = spark.read.parquet(folder)
    else:
        plan = plan.withColumn("chunk", F.lit(0))
    loads, seen, memory = np.zeros(o.k, np.int64), [0, 0, 0], RoundMemory(spark, o.mode)
    for i, chunk in enumerate(chunks):
        task = F.col("lane") if len(chunk) == 1 else F.lit(0)
        rows = plan.where(F.col("chunk") == i).select("eid", "u", "v", "past", "round", "lane", "batch", task.alias("task"))
        if not memory.parts or o.mode == "none":
            known = spark.createDataFrame([], "slot int, v long, block long, seq long, at long")
        else:
            known = memory.of(rows.where("past >= 0").select("task", "past").distinct())
        kernel = _chunk_kernel(o, rounds, loads, seen, {r: owned[r] for r in chunk})
        rows.groupBy("task").cogroup(known.groupBy("slot")).applyInArrow(kernel, _CHUNK_DDL).write.parquet(f"{out}/chunk={i}")
        raw = spark.read.schema(_CHUNK_DDL).parquet(f"{out}/chunk={i}")
        placed = raw.where("eid IS NOT NULL").select("eid", "u", "v", "block", (F.col("batch") % rounds).alias("batch"))
        if i + 1 < len(chunks):
            loads = loads.copy()
            for r in placed.groupBy("block").count().collect():
                loads[r["block"]] += r["count"]
            more = raw.where("eid IS NULL").agg(*(F.sum(c) for c in ("seen_edges", "seen_links", "seen_low"))).first()
            seen = [n + m for n, m in zip(seen, more)]
            if o.mode != "none":
                memory.add(placed)
    raw = spark.read.schema(_OUT_DDL).parquet(*(f"{out}/chunk={i}" for i in range(len(chunks))))
    return _split_out(g, raw, o.k, eps, rounds, lanes=lanes, mode=o.mode)


def chunks_of(owned: dict[int, np.ndarray]) -> list[list[int]]:
    """Consecutive rounds that own CHUNK_EDGES in sum, each chunk a job; a round above that is a chunk of its own, with a task for each lane."""
    chunks, held = [], 0
    for r in sorted(owned):
        size = int(owned[r].sum())
        if not chunks or held + size > CHUNK_EDGES:
            chunks.append([])
            held = 0
        chunks[-1].append(r)
        held += size
    return chunks


def vertex_partition(g: Graph, k: int, eps: float | str = "0.03", delta: int = 32 * 1024, init: str = "two_set", seed: int = 0) -> DataFrame:
    """(v, block): buffered vertex partitioning with the same cut, what the edge method grew from. One task carries all batches."""
    cap, n, m = block_cap(g.n, k, eps), g.n, g.m

    def run(table: pa.Table) -> pa.Table:
        u, v = table.column("u").to_numpy(), table.column("v").to_numpy()
        blocks, loads, limits = np.full(n, -1, np.int64), np.zeros(k, np.int64), np.full(k, cap)
        order = np.argsort(v, kind="stable")
        u, v = u[order], v[order]
        for lo in range(0, n, delta):
            hi = min(lo + delta, n)
            a, b = np.searchsorted(v, [lo, hi])
            x, y = u[a:b], v[a:b]
            inner = x >= lo
            fixed = ~inner
            level = multilevel.Level(np.ones(hi - lo, np.int64), x[inner] - lo, y[inner] - lo, np.ones(int(inner.sum())), y[fixed] - lo, blocks[x[fixed]], np.ones(int(fixed.sum())))
            blocks[lo:hi] = multilevel.cut(level, loads, limits, fennel.alpha_vertex(k, n, m), cap, strategy=init, seed=seed).blocks
        return pa.table({"v": np.arange(n), "block": blocks.astype(np.int32)})

    rows = g.edges.select("u", "v").withColumn("lane", F.lit(0))
    return rows.groupBy("lane").applyInArrow(run, "v bigint, block int")


__all__ = ["Memory", "Options", "Partition", "cut_batch", "partition", "path_links", "quotas", "run_batches", "vertex_partition"]
