"""Generalised Fennel: gain, its parameter, and placing items one by one."""

from __future__ import annotations

import heapq
import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

GAMMA = 1.5


def gain(w_in: Column, weight: Column, load: Column, alpha: float, gamma: float = GAMMA) -> Column:
    """Link weight into a block less the penalty for its load."""
    return w_in - weight * F.lit(alpha * gamma) * F.pow(load.cast("double"), F.lit(gamma - 1))


def penalty(load, alpha: float, gamma: float = GAMMA):
    return alpha * gamma * np.asarray(load, float) ** (gamma - 1)


def alpha_vertex(k: int, n: float, m: float) -> float:
    """sqrt(k) m / n^(3/2): the form for vertex partitions."""
    return math.sqrt(k) * m / n**1.5 if n else 0.0


def alpha_column(k: Column, items: Column, links: Column) -> Column:
    """The same for counted items and links."""
    return F.sqrt(k.cast("double")) * links / F.pow(items.cast("double"), F.lit(1.5))


def alpha_static(k: int, m: int, y: float = 2.0, n: int | None = None, base: str = "items") -> float:
    """One value for all batches: items are the m edges, links are guessed as y per item. base="n" divides by the vertices instead."""
    items = m if base == "items" or n is None else n
    return alpha_vertex(k, items, y * m)


def alpha_batch(k: int, items: int, links: int) -> float:
    return alpha_vertex(k, items, links)


def alpha_dynamic(k: int, m: int, seen_edges: int, seen_links: int, y: float = 2.0) -> float:
    """The static form with the links per item of the batches so far in place of the guess."""
    per = seen_links / seen_edges if seen_edges else y
    return alpha_static(k, m, per)


class Lightest:
    """The least loaded block with room, ties to the smaller number; loads only grow. A heap with stale entries."""

    def __init__(self, loads: np.ndarray, limits: np.ndarray):
        self.loads, self.limits = loads, limits
        self.heap = [(int(x), i) for i, x in enumerate(loads)]
        heapq.heapify(self.heap)

    def get(self, weight: int) -> int:
        heap, held, found = self.heap, [], -1
        while heap:
            load, i = heap[0]
            if load != self.loads[i]:
                heapq.heapreplace(heap, (int(self.loads[i]), i))
            elif load + weight <= self.limits[i]:
                found = i
                break
            elif load + 1 > self.limits[i]:
                heapq.heappop(heap)  # full for good
            else:
                held.append(heapq.heappop(heap))
        for x in held:
            heapq.heappush(heap, x)
        return found


class LightestBuckets:
    """The same with a bucket of blocks per load. A block that grew is moved when it comes to the top of its old bucket."""

    def __init__(self, loads: np.ndarray, limits: np.ndarray):
        self.loads, self.limits = loads, limits
        self.buckets: dict[int, list[int]] = {}
        for i, x in enumerate(loads):
            self.buckets.setdefault(int(x), []).append(i)  # in order, so already a heap
        self.low, self.top = min(self.buckets, default=0), max(self.buckets, default=0)

    def get(self, weight: int) -> int:
        load = self.low
        while load <= self.top:
            bucket = self.buckets.get(load)
            while bucket and self.loads[bucket[0]] != load:
                i = heapq.heappop(bucket)
                now = int(self.loads[i])
                heapq.heappush(self.buckets.setdefault(now, []), i)
                self.top = max(self.top, now)
            if bucket:
                if load + weight <= self.limits[bucket[0]]:
                    return bucket[0]
                room = [i for i in bucket if self.loads[i] == load and load + weight <= self.limits[i]]
                if room:
                    return min(room)
            elif load == self.low:
                self.buckets.pop(load, None)
                self.low += 1
            load += 1
        return -1


def place_items(order, weights, neighbours, fixed, blocks, loads, limits, alpha: float, gamma: float = GAMMA, strategy: str = "two_set") -> int:
    """Gives every item of order with block -1 its best block with room; returns how many block scores were taken.

    neighbours(i): (items, link weights); fixed(i): (blocks, link weights). all_k scores every block; two_set scores the
    blocks of placed neighbours and fixed links, and the lightest block. Ties go to the lighter, then the smaller block.
    An item for which no block has room keeps -1.
    """
    ag, expo = alpha * gamma, gamma - 1
    k, scores = len(loads), 0
    whole, given = loads, blocks  # the loop works on lists
    loads, limits, blocks, weights, room = whole.tolist(), limits.tolist(), given.tolist(), weights.tolist(), limits - whole
    pick = None if strategy == "all_k" else (LightestBuckets if strategy == "two_set_bucket" else Lightest)(loads, limits)
    price = ag * whole.astype(float) ** expo if pick is None else None
    for i in order:
        if blocks[i] >= 0:
            continue
        c = weights[i]
        inside: dict[int, float] = {}
        for j, w in zip(*neighbours(i)):
            b = blocks[j]
            if b >= 0:
                inside[b] = inside.get(b, 0.0) + w
        for b, w in zip(*fixed(i)):
            inside[b] = inside.get(b, 0.0) + w
        if pick is None:
            value = -c * price
            for b, w in inside.items():
                value[b] += w
            value[room < c] = -np.inf
            scores += k
            top = value.max()
            if top == -np.inf:
                continue
            best = min(np.flatnonzero(value == top).tolist(), key=loads.__getitem__)
        else:
            best, key = -1, None
            low = pick.get(c)
            for b in {*inside, low} if low >= 0 else inside:
                load = loads[b]
                if load + c <= limits[b]:
                    scores += 1
                    new = (-(inside.get(b, 0.0) - c * (ag * float(load) ** expo)), load, b)
                    if key is None or new < key:
                        best, key = b, new
            if best < 0:
                continue
        blocks[i] = best
        loads[best] += c
        if pick is None:
            room[best] -= c
            price[best : best + 1] = ag * np.array([loads[best]], float) ** expo
    whole[:], given[:] = loads, blocks
    return scores


def stream_vertices(n: int, starts: np.ndarray, nbrs: np.ndarray, k: int, eps: float = 0.03, gamma: float = GAMMA, strategy: str = "two_set", weights: np.ndarray | None = None) -> np.ndarray:
    """Vertex blocks by one Fennel pass in id order over a graph in compressed rows."""
    weights = np.ones(n, np.int64) if weights is None else weights
    loads = np.zeros(k, np.int64)
    limits = np.full(k, max(int(weights.max(initial=1)), math.ceil((1 + eps) * weights.sum() / k)))
    blocks = np.full(n, -1)
    rows = lambda i: (nbrs[starts[i] : starts[i + 1]].tolist(), [1.0] * int(starts[i + 1] - starts[i]))
    place_items(range(n), weights, rows, lambda i: ((), ()), blocks, loads, limits, alpha_vertex(k, n, len(nbrs) / 2), gamma, strategy)
    return blocks
