"""One-pass edge placement on the dual hypergraph.

Edges are read with their later end and each is placed at once. An edge lies in two nets, its ends; a block scores a point for
each of them that used it last (or ever, with net_memory="all"), less the Fennel penalty of its load. Only blocks seen on the two nets
and the lightest block are looked at, so time and memory do not grow with k beyond the loads.
"""

from __future__ import annotations

import math

import numpy as np

from . import sequential
from .buffered import Partition
from .canonical import Graph
from .fennel import GAMMA, Lightest


def place_stream(u: np.ndarray, v: np.ndarray, n: int, k: int, limits: np.ndarray, m: int, n_all: int, gamma: float = GAMMA, net_memory: str = "last", loads: np.ndarray | None = None, last: list | None = None) -> np.ndarray:
    """Blocks of edges in stream order. loads and last (block or set per net) are carried on if given."""
    alpha = math.sqrt(k) * n_all / max(m, 1) ** 1.5
    ag, expo = alpha * gamma, gamma - 1
    loads = np.zeros(k, np.int64) if loads is None else loads
    keep_all = net_memory == "all"
    last = ([set() for _ in range(n)] if keep_all else [-1] * n) if last is None else last
    pick, load, cap = Lightest(loads, limits), loads.tolist(), limits.tolist()
    out = np.empty(len(u), np.int32)
    for e, a, b in sequential.edges_of(u, v):
        la, lb = last[a], last[b]
        low = pick.get(1)
        seen = (la | lb) if keep_all else {x for x in (la, lb) if x >= 0}
        best, key = -1, None
        for i in {*seen, low}:
            if load[i] < cap[i]:
                hits = (i in la) + (i in lb) if keep_all else (i == la) + (i == lb)
                new = (ag * load[i] ** expo - hits, load[i], i)
                if key is None or new < key:
                    best, key = i, new
        out[e] = best
        load[best] += 1
        loads[best] += 1
        if keep_all:
            la.add(best)
            lb.add(best)
        else:
            last[a] = last[b] = best
    return out


def kernel(m: int | None = None, n_all: int | None = None, net_memory: str = "last") -> sequential.Kernel:
    """m and n_all: edges and vertices of the whole graph, where the kernel sees a part of it."""
    if net_memory not in ("last", "all"):
        raise ValueError(net_memory)

    def run(u, v, n, k, limits, info=None):
        last = [set() for _ in range(n)] if net_memory == "all" else [-1] * n
        out = place_stream(u, v, n, k, limits, m or len(u), n_all or n, net_memory=net_memory, last=last)
        if info is not None:
            info["cells"] = k + (sum(map(len, last)) if net_memory == "all" else len(last))
        return out

    return run


def partition(g: Graph, k: int, eps: float | str = "0.03", lanes: int = 1, net_memory: str = "last") -> Partition:
    return sequential.run(g, k, kernel(g.m, g.n, net_memory), eps, lanes)
