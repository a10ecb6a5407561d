"""Many runs of many methods on stored graphs in one job, each in a process of its own with the same clock.

The edges of a graph, at most BROADCAST_EDGES, are dealt in pieces to up to GRAPH_TASKS tasks or two a core, which share its trials, one at a time; the driver holds no
edges. Blocks come back as an array per trial and
are stored; replicas and loads are counted from there by SQL. A graph above the bound is run through the methods' own partition().
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, buffered, onthefly
from ..operators.apart import run_apart
from ..operators.canonical import Graph
from ..operators.metrics import block_cap
from ..storage import materialise

#: Edges of a graph in one task, and tasks that share the trials of a graph at least, two a core where there are more cores; cells of a table of vertices times blocks above which a run counts as failed for memory (a byte each).
BROADCAST_EDGES, GRAPH_TASKS, CELLS_LIMIT = 20_000_000, 8, 1 << 28
#: Edges in a row that goes to a task, or in which blocks meet their edges.
PIECE = 256
EPS = "0.03"


@dataclass(frozen=True)
class Trial:
    """One run: a label, a graph, k, the kind of method and its options."""

    alg: str
    graph: str
    k: int
    kind: str = "buffered"
    options: dict = field(default_factory=dict, hash=False)


@dataclass
class Arrays:
    """A graph as arrays, edges by number, with the stream order (by later end, then the other)."""

    u: np.ndarray
    v: np.ndarray
    n: int
    order: np.ndarray


def _buffered(a: Arrays, k: int, limit: int, info: dict, delta: int, **options) -> np.ndarray:
    o = buffered.Options(k, delta, limit, len(a.u), **{"measure": False, **options})
    block, _, stats, memory = buffered.run_batches(np.arange(len(a.u)), a.u, a.v, o)
    info |= {c: sum(s[c] for s in stats) for c in ("scores", "links", "block_links", "items")} | {"cells": memory.cells() + k}
    return block


def _room(cells: int) -> None:
    if cells > CELLS_LIMIT:
        raise MemoryError(f"a table of {cells} cells")


def _stream(make: Callable[..., Callable], table: bool) -> Callable:
    def run(a: Arrays, k: int, limit: int, info: dict, **options) -> np.ndarray:
        if table:
            _room(a.n * k)
        out = np.empty(len(a.u), np.int64)
        out[a.order] = make(**options)(a.u[a.order], a.v[a.order], a.n, k, np.full(k, limit), info)
        return out

    return run


def _hash(a: Arrays, k: int, limit: int, info: dict) -> np.ndarray:
    info["cells"] = 0
    return (a.u * 31 + a.v * 17) % k


def _dbh(a: Arrays, k: int, limit: int, info: dict) -> np.ndarray:
    d = np.bincount(np.concatenate([a.u, a.v]), minlength=a.n)
    info["cells"] = d.size
    return np.where(d[a.v] < d[a.u], a.v, a.u) % k


#: How each kind of method is run, and how often it reads the edges.
KINDS: dict[str, tuple[Callable, int]] = {
    "buffered": (_buffered, 1), "onthefly": (_stream(onthefly.kernel, False), 1), "hdrf": (_stream(baselines.hdrf_kernel, True), 1),
    "two_phase": (_stream(baselines.two_phase_kernel, True), 3), "dbh": (_dbh, 2), "hash": (_hash, 1),
}
_SCHEMA = "alg string, graph string, k int, edges bigint, blocks array<int>, seconds double, peak_bytes bigint, cells bigint, scores bigint, items bigint, links bigint, block_links bigint, passes int, error string"
_NUMBERS = ["cells", "scores", "items", "links", "block_links"]


_PACKED = "eid array<bigint>, u array<bigint>, v array<bigint>"


def _packed(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges in rows of PIECE, so that a copy for each task is cheap to deal out."""
    for b in it:
        ends = pa.array(np.append(np.arange(0, b.num_rows, PIECE), b.num_rows).astype(np.int32))
        yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(ends, pa.array(b.column(c).to_numpy())) for c in ("eid", "u", "v")], names=["eid", "u", "v"])


def _runner(trials: list[Trial], tasks: list[tuple[str, list[int]]], sizes: dict[str, tuple[int, int]]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, u, v = None, np.zeros(0, np.int64), np.zeros(0, np.int64)
        for b in batches:
            own = b.column("task").to_numpy()
            cuts = np.flatnonzero(np.diff(own, prepend=own[0] - 1)) if len(own) else []
            for lo, hi in zip(cuts, [*cuts[1:], len(own)]):
                if own[lo] != task:
                    if task is not None:
                        yield from results(task, u, v)
                    task = int(own[lo])
                    u, v = (np.empty(sizes[tasks[task][0]][1], np.int64) for _ in range(2))
                eid, *both = (b.column(c).slice(lo, hi - lo).flatten().to_numpy() for c in ("eid", "u", "v"))
                u[eid], v[eid] = both
        if task is not None:
            yield from results(task, u, v)

    def results(task: int, u: np.ndarray, v: np.ndarray) -> Iterator[pa.RecordBatch]:
        name, own = tasks[task]
        a = Arrays(u, v, sizes[name][0], np.lexsort((u, v)))
        for t in (trials[i] for i in own):
            kernel, passes = KINDS[t.kind]
            blocks, got = run_apart(len(u), lambda info, t=t, kernel=kernel: kernel(a, t.k, block_cap(len(u), t.k, EPS), info, **t.options))
            row = {"alg": t.alg, "graph": t.graph, "k": t.k, "edges": len(u), "seconds": got.get("seconds"), "peak_bytes": got.get("peak_bytes"), "passes": passes, "error": got.get("error")}
            row |= {c: None if got.get(c) is None else int(got[c]) for c in _NUMBERS}
            flat = pa.nulls(1, _TYPES["array<int>"]) if blocks is None else pa.ListArray.from_arrays(pa.array([0, len(blocks)], pa.int32()), pa.array(blocks, pa.int32()))
            yield pa.RecordBatch.from_arrays([flat if f.name == "blocks" else pa.array([row[f.name]], f.type) for f in _ARROW], schema=_ARROW)

    return run


_TYPES = {"string": pa.string(), "int": pa.int32(), "bigint": pa.int64(), "double": pa.float64(), "array<int>": pa.list_(pa.int32())}
_ARROW = pa.schema([(c.split(" ", 1)[0], _TYPES[c.split(" ", 1)[1]]) for c in _SCHEMA.split(", ")])


def run_all(spark: SparkSession, graphs: dict[str, Graph], trials: Iterable[Trial]) -> DataFrame:
    """A stored row per trial: blocks (null if it failed, see error), seconds, peak_bytes, cells, scores, items, links, block_links, passes."""
    trials = sorted(trials, key=lambda t: (-graphs[t.graph].m * (8 if t.kind in ("hdrf", "two_phase") else 1), -t.k))  # long ones first
    large = [n for n, g in graphs.items() if g.m > BROADCAST_EDGES]
    if large:
        raise ValueError(f"too many edges for a trial in one task, use partition(): {large}")
    tasks, rows, most = [], None, max(GRAPH_TASKS, 2 * spark.sparkContext.defaultParallelism)
    for name, g in graphs.items():
        own = [i for i, t in enumerate(trials) if t.graph == name]
        parts = min(len(own), most)
        if parts:
            numbers = F.sequence(F.lit(len(tasks)), F.lit(len(tasks) + parts - 1))
            tasks += [(name, own[p::parts]) for p in range(parts)]
            packed = g.edges.select("eid", "u", "v").mapInArrow(_packed, _PACKED)
            one = packed.select(F.explode(numbers).alias("task"), "eid", "u", "v")
            rows = one if rows is None else rows.unionByName(one)
    starts = spark.createDataFrame([(i, [], [], []) for i in range(len(tasks))], "task int, " + _PACKED)  # a graph without edges has a task too
    rows = starts if rows is None else rows.unionByName(starts)
    rows = rows.repartitionByRange(max(1, len(tasks)), "task").sortWithinPartitions("task")
    run = _runner(trials, tasks, {n: (g.n, g.m) for n, g in graphs.items()})
    return materialise(rows.mapInArrow(run, _SCHEMA), "trials")


def _pieces(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The blocks of each trial in rows of PIECE edges."""
    for b in it:
        blocks = b.column("blocks")
        for i in range(b.num_rows):
            own = blocks.slice(i, 1).flatten()
            for lo in range(0, len(own), 1000 * PIECE):
                some = own.slice(lo, 1000 * PIECE).to_numpy()
                ends = np.append(np.arange(0, len(some), PIECE), len(some)).astype(np.int32)
                pieces = np.arange(len(ends) - 1) + lo // PIECE
                known = [pa.array([b.column(c)[i].as_py()] * len(pieces), b.column(c).type) for c in ("graph", "k", "trial")]
                yield pa.RecordBatch.from_arrays([*known, pa.array(pieces), pa.ListArray.from_arrays(pa.array(ends), pa.array(some))], names=["graph", "k", "trial", "piece", "blocks"])


def _joined(graphs: dict[str, Graph], numbered: DataFrame) -> DataFrame:
    """(trial, k, ends, block) of every placed edge. Blocks and edges meet by PIECE edges and by a shuffle: the files of blocks are small and what
    they unfold to is not, so a broadcast chosen by file size would fill the driver."""
    ends = None
    for name, g in graphs.items():
        one = g.edges.select(F.lit(name).alias("graph"), "eid", "u", "v")
        ends = one if ends is None else ends.unionByName(one)
    ends = ends.groupBy("graph", F.expr(f"eid div {PIECE}").alias("piece")).agg(F.array_sort(F.collect_list(F.struct("eid", "u", "v"))).alias("edges"))
    placed = numbered.where("blocks IS NOT NULL").select("graph", "k", "trial", "blocks").mapInArrow(_pieces, "graph string, k int, trial int, piece bigint, blocks array<int>")
    both = placed.hint("merge").join(ends.hint("merge"), ["graph", "piece"])
    return both.select("trial", "k", F.explode(F.arrays_zip("edges.u", "edges.v", "blocks")).alias("x")).select("trial", "k", "x.u", "x.v", F.col("x.blocks").alias("block"))


def measured(spark: SparkSession, graphs: dict[str, Graph], done: DataFrame) -> DataFrame:
    """The trials with what their stored blocks amount to, counted by SQL: placed, bad_blocks, max_load, over_cap, replicas, rf."""
    by = ["alg", "graph", "k"]
    cap = F.greatest(F.lit(1), F.expr("(edges * 103 + 100 * k - 1) div (100 * k)"))
    keys = [(i, *r) for i, r in enumerate(sorted(tuple(r) for r in done.select(*by).collect()))]  # a row per trial
    numbers = spark.createDataFrame(keys, "trial int, alg string, graph string, k int")
    numbered = done.join(F.broadcast(numbers), by)
    placed = _joined(graphs, numbered)
    sized = numbers.join(done.select(*by, "edges"), by).select("trial", "edges")
    per = placed.groupBy("trial", "k", "block").agg(F.count(F.lit(1)).alias("load")).join(F.broadcast(sized), "trial")
    loads = per.groupBy("trial").agg(F.sum("load").alias("placed"), F.max("load").alias("max_load"), F.count_if((F.col("block") < 0) | (F.col("block") >= F.col("k"))).alias("bad_blocks"), F.count_if(F.col("load") > cap).alias("over_cap"))
    copies = placed.select("trial", F.explode(F.array("u", "v")).alias("v"), "block").distinct().groupBy("trial").agg(F.count(F.lit(1)).alias("replicas"))
    sizes = spark.createDataFrame([(n, g.n) for n, g in graphs.items()], "graph string, n long")
    out = numbered.drop("blocks").join(loads, "trial", "left").join(copies, "trial", "left").drop("trial").join(F.broadcast(sizes), "graph")
    return materialise(out.withColumns({"rf": F.round(F.col("replicas") / F.col("n"), 6), "l_max": cap}), "measured")
