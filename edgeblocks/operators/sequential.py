"""Runs one-pass methods over the edge stream: in one task at every size, or, where asked for, in lanes of contiguous vertex ranges with own block quotas."""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import materialise
from .buffered import PIECE, Partition
from .canonical import Graph
from .metrics import block_cap

#: A kernel gets local vertex numbers, the number of vertices, k, the limit of each block and perhaps a dict for its figures, and returns a block per edge.
Kernel = Callable[..., np.ndarray]
#: Edges of a lane that default_lanes counts on; above it a task keeps its edges in a file without a name.
LANE_EDGES = 20_000_000
#: Edges that are Python numbers at a time; edges that a task sorts before the stream.
SLICE, SORTED_EDGES = 1 << 16, 1 << 20


def default_lanes(m: int, k: int) -> int:
    """Lanes for callers who give up the exact stream order for more tasks: as few as keep LANE_EDGES. Every lane may
    round its quota up by an edge a block, so there are no more than the balance has room for. No method takes them unasked."""
    return max(1, min(-(-m // LANE_EDGES), 3 * m // (100 * k)))


def lane_limits(sizes: list[int], k: int, l_max: int) -> list[int]:
    """Per lane the edges it may put in a block: enough for its own edges, and at most l_max in sum."""
    need = [-(-s // k) for s in sizes]
    spare = l_max - sum(need)
    if spare < 0:
        raise ValueError("too many lanes for this balance")
    total = max(1, sum(sizes))
    return [n + spare * s // total for n, s in zip(need, sizes)]


def _held(size: int, kind: type) -> np.ndarray:
    """An array for the edges of a lane, read in order by every pass; a large one in a file."""
    if size <= LANE_EDGES:
        return np.empty(size, kind)
    with tempfile.TemporaryFile() as f:
        return np.memmap(f, kind, "w+", shape=(size,))


def numbered(u: np.ndarray, v: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The ids that occur, sorted, and both ends as places among them; by marks and in place where they are dense among n."""
    if n > 16 * len(u) + (1 << 20):
        ids, local = np.unique(np.concatenate([u, v]), return_inverse=True)
        return ids.astype(np.int64), local[: len(u)], local[len(u) :]
    met = np.zeros(n, bool)
    for x in (u, v):
        for lo in range(0, len(x), SLICE):
            met[x[lo : lo + SLICE]] = True
    place = np.cumsum(met, dtype=u.dtype) - 1
    for x in (u, v):
        for lo in range(0, len(x), SLICE):
            x[lo : lo + SLICE] = place[x[lo : lo + SLICE]]
    return np.flatnonzero(met), u, v


def edges_of(u: np.ndarray, v: np.ndarray, at: np.ndarray | None = None) -> Iterator[tuple[int, int, int]]:
    """(edge, u, v) in order, or those at some places; as Python numbers of a slice at a time."""
    for lo in range(0, len(u) if at is None else len(at), SLICE):
        e = np.arange(lo, min(lo + SLICE, len(u))) if at is None else at[lo : lo + SLICE]
        yield from zip(e.tolist(), u[e].tolist(), v[e].tolist())


def slices_of(u: np.ndarray, v: np.ndarray, wanted: Callable[[slice], np.ndarray] | None = None) -> Iterator[tuple]:
    """(places, u, v) of a slice of the edges at a time, both ends as lists of Python numbers; wanted(slice) marks those to take."""
    for lo in range(0, len(u), SLICE):
        s = slice(lo, lo + SLICE)
        if wanted is not None:
            s = np.flatnonzero(wanted(s)) + lo
        yield s, u[s].tolist(), v[s].tolist()


def _pieces(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sorted edges in rows of up to PIECE, each with its lane and its first edge."""
    for b in it:
        lane, eid, u, v = (b.column(c).to_numpy() for c in ("lane", "eid", "u", "v"))
        if len(lane):
            first = np.union1d(np.arange(0, len(lane), PIECE), np.flatnonzero(np.diff(lane)) + 1)
            ends = pa.array(np.append(first, len(lane)).astype(np.int32))
            lists = [pa.ListArray.from_arrays(ends, pa.array(x)) for x in (eid, u, v)]
            yield pa.RecordBatch.from_arrays([*(pa.array(x[first]) for x in (lane, v, u)), *lists], names=["lane", "first_v", "first_u", "eid", "u", "v"])


def run(g: Graph, k: int, kernel: Kernel, eps: float | str = "0.03", lanes: int = 1, passes: int = 1) -> Partition:
    """assign from a kernel over edges in stream order: by later end, then the other. With lanes, each lane sees its own edges only.

    Edges are sorted by range in many tasks; the task of a lane puts their pieces in a row.
    """
    l_max = block_cap(g.m, k, eps)
    width = max(1, -(-g.n // lanes))
    lane_of = F.floor(F.col("v") / F.lit(width)).cast("int")
    sizes = {0: g.m} if lanes == 1 else {r["lane"]: r["count"] for r in g.edges.groupBy(lane_of.alias("lane")).count().collect()}
    limit = dict(zip(sorted(sizes), lane_limits([sizes[x] for x in sorted(sizes)], k, l_max)))

    n, small = g.n, np.int32 if max(g.n, g.m) < 1 << 31 else np.int64

    def stream(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lane, at, held = None, 0, ()
        for b in it:
            lanes_ = b.column("lane").to_numpy()
            cuts = np.flatnonzero(np.diff(lanes_, prepend=lanes_[0] - 1)) if len(lanes_) else []
            for lo, hi in zip(cuts, [*cuts[1:], len(lanes_)]):
                if lanes_[lo] != lane:
                    if lane is not None:
                        yield from placed(lane, *held)
                    lane, at = int(lanes_[lo]), 0
                    held = tuple(_held(sizes[lane], small) for _ in range(3))
                for c, name in zip(held, ("eid", "u", "v")):
                    some = b.column(name).slice(lo, hi - lo).flatten().to_numpy()
                    c[at : at + len(some)] = some
                at += len(some)
        if lane is not None:
            yield from placed(lane, *held)

    def placed(lane: int, eid: np.ndarray, u: np.ndarray, v: np.ndarray) -> Iterator[pa.RecordBatch]:
        ids, u, v = numbered(u, v, n)
        block = kernel(u, v, len(ids), k, np.full(k, limit[lane]))
        for lo in range(0, len(eid), SLICE):
            s = slice(lo, lo + SLICE)
            cols = [eid[s].astype(np.int64), ids[u[s]], ids[v[s]], np.asarray(block[s], np.int32), np.full(len(eid[s]), lane, np.int64)]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["eid", "u", "v", "block", "batch"])

    rows = g.edges.select("eid", "u", "v", lane_of.alias("lane")).repartitionByRange(max(lanes, -(-g.m // SORTED_EDGES)), "lane", "v", "u").sortWithinPartitions("lane", "v", "u")
    rows = rows.mapInArrow(_pieces, "lane int, first_v bigint, first_u bigint, eid array<bigint>, u array<bigint>, v array<bigint>")
    rows = (rows.repartition(1) if lanes == 1 else rows.repartitionByRange(lanes, "lane")).sortWithinPartitions("lane", "first_v", "first_u")
    assign = materialise(rows.mapInArrow(stream, "eid bigint, u bigint, v bigint, block int, batch bigint"), "stream")
    return Partition(assign, assign.limit(0).select("batch"), g, k, eps, passes)


def relational(g: Graph, assign: DataFrame, k: int, eps: float | str = "0.03", passes: int = 1) -> Partition:
    return Partition(assign.withColumn("batch", F.lit(0).cast("long")), assign.limit(0).select(F.lit(0).alias("batch")), g, k, eps, passes)
