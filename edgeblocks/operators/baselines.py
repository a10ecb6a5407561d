"""Streaming and hashing edge partitioners to compare with. Their inner workings follow the published literature on each."""

from __future__ import annotations

import heapq
import math
from array import array

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import sequential
from .buffered import Partition
from .canonical import Graph, degrees
from .fennel import Lightest

LAMBDA = 1.1


# ---- hashing: one pass of column arithmetic

def hash_edges(g: Graph, k: int) -> DataFrame:
    return g.edges.select("eid", "u", "v", F.pmod(F.col("u") * 31 + F.col("v") * 17, F.lit(k)).cast("int").alias("block"))


def dbh(g: Graph, k: int) -> DataFrame:
    """The end of smaller degree decides, ties the smaller id."""
    d = degrees(g.edges)
    with_d = g.edges.join(d.select(F.col("v").alias("u"), F.col("deg").alias("du")), "u").join(d.select("v", F.col("deg").alias("dv")), "v")
    end = F.when(F.col("dv") < F.col("du"), F.col("v")).otherwise(F.col("u"))
    return with_d.select("eid", "u", "v", F.pmod(end, F.lit(k)).cast("int").alias("block"))


def grid(g: Graph, k: int) -> DataFrame:
    """A vertex's edges stay in one row and one column of a square of blocks."""
    side = math.isqrt(k)
    return g.edges.select("eid", "u", "v", (F.pmod("u", F.lit(side)) * side + F.pmod("v", F.lit(side))).cast("int").alias("block"))


def round_robin(g: Graph, k: int) -> DataFrame:
    return g.edges.select("eid", "u", "v", F.pmod("eid", F.lit(k)).cast("int").alias("block"))


def random_blocks(g: Graph, k: int, seed: int = 12345) -> DataFrame:
    """By an arithmetic hash of the edge, so a retried task draws the same, and any other engine too."""
    x = F.col("eid") % 1_000_003
    mixed = (x * 7919 + seed) % 1_000_003 * (x + 104_729) % 998_244_353
    return g.edges.select("eid", "u", "v", F.pmod(mixed, F.lit(k)).cast("int").alias("block"))


# ---- greedy by degree

class _Greedy:
    """What each vertex met, as a table of n x k cells, and scores over all k blocks."""

    def __init__(self, n: int, k: int, limits: np.ndarray, lam: float, degree: np.ndarray | None):
        self.n, self.k, self.loads, self.limits, self.lam = n, k, np.zeros(k, np.int64), limits, lam
        self.partial, self.degree = degree is None, np.zeros(n, np.int64) if degree is None else degree
        self.table = np.zeros((n, k), bool)

    def score(self, a: int, b: int) -> np.ndarray:
        share = self.degree[a] / (self.degree[a] + self.degree[b])
        top, low = self.loads.max(), self.loads.min()
        out = self.table[a] * (2 - share) + self.table[b] * (1 + share) + self.lam * (top - self.loads) / (1e-9 + top - low or 1e-9)
        out[self.loads >= self.limits] = -1
        return out

    def place(self, a: int, b: int) -> int:
        if self.partial:
            self.degree[a] += 1
            self.degree[b] += 1
        return self.put(a, b, int(self.score(a, b).argmax()))

    def put(self, a: int, b: int, i: int) -> int:
        self.table[a, i] = self.table[b, i] = True
        self.loads[i] += 1
        return i

    def met(self, x: int, i: int) -> bool:
        return bool(self.table[x, i])

    def lightest(self) -> int:
        return int(np.where(self.loads < self.limits, self.loads, 1 << 62).argmin())

    def cells(self) -> int:
        """Entries held."""
        return self.n * self.k + self.loads.size + self.degree.size


#: Sets of blocks whose members are kept as tuples.
KEPT_SETS = 1 << 12


class _Seen:
    """The same blocks from those that can win: of the blocks that both ends met, that one end met and that none met, the lightest of each.

    Blocks with equal hits differ in their balance term alone, so a heavier one never wins. Where the best so far is ahead of all that hits and balance
    can give, the rest is not looked at. A vertex holds a number whose bits are its blocks, and a degree.
    """

    def __init__(self, n: int, k: int, limits: np.ndarray, lam: float, degree: np.ndarray | None):
        self.n, self.k = n, k
        self.loads, self.limits = load, limit = [0] * k, limits.tolist()
        self.bits = bits = bytearray(n) if k <= 8 else array("Q", bytes(8 * n)) if k <= 64 else [0] * n
        self.degree = deg = array("q", bytes(8 * n) if degree is None else degree.astype(np.int64).tobytes())
        light, partial, members, load_of = Lightest(load, limit), degree is None, {}, load.__getitem__
        top = low = 0
        at_low, room = k, sum(1 << i for i in range(k) if limit[i] > 0)

        def least(some: int) -> int:
            """The lightest of some blocks, ties to the smaller number."""
            if not some & (some - 1):
                return some.bit_length() - 1
            own = members.get(some)
            if own is None:
                if len(members) >= KEPT_SETS:
                    members.clear()
                left, found = some, []
                while left:
                    one = left & -left
                    found.append(one.bit_length() - 1)
                    left ^= one
                own = members[some] = tuple(found)
            return min(own, key=load_of)

        def place(a: int, b: int) -> int:
            da, db = deg[a], deg[b]
            if partial:
                da += 1
                db += 1
                deg[a], deg[b] = da, db
            share = da / (da + db)
            for_a, for_b, span = 2 - share, 1 + share, 1e-9 + top - low or 1e-9
            of_a, of_b = bits[a] & room, bits[b] & room
            both = of_a & of_b
            best, score = -1, -1.0
            if both:
                best = least(both)
                score = for_a + for_b + lam * (top - load[best]) / span
            if score <= (for_a if for_a > for_b else for_b) + lam:
                if of_a != both:
                    i = least(of_a ^ both)
                    one = for_a + lam * (top - load[i]) / span
                    if one > score or one == score and i < best:
                        best, score = i, one
                if of_b != both:
                    i = least(of_b ^ both)
                    one = for_b + lam * (top - load[i]) / span
                    if one > score or one == score and i < best:
                        best, score = i, one
                if score <= lam:
                    i = light.get(1)
                    if i >= 0 and not (of_a | of_b) >> i & 1:
                        one = lam * (top - load[i]) / span
                        if one > score or one == score and i < best:
                            best = i
            return put(a, b, best)

        def put(a: int, b: int, i: int) -> int:
            nonlocal top, low, at_low, room
            bit = 1 << i
            bits[a] |= bit
            bits[b] |= bit
            x = load[i]
            load[i] = x + 1
            if x == top:
                top = x + 1
            if x == low:
                at_low -= 1
                if not at_low:
                    low += 1
                    at_low = load.count(low)
            if x + 1 >= limit[i]:
                room &= ~bit
            return i

        self.place, self.put, self.lightest = place, put, lambda: light.get(1)

    def met(self, x: int, i: int) -> bool:
        return bool(self.bits[x] >> i & 1)

    def cells(self) -> int:
        return self.n * self.k + len(self.loads) + len(self.degree)


def _greedy(n: int, k: int, limits: np.ndarray, lam: float, degree: np.ndarray | None, scan: str) -> _Greedy | _Seen:
    return (_Greedy if scan == "all" else _Seen)(n, k, limits, lam, degree)


def _degrees(u: np.ndarray, v: np.ndarray, n: int) -> np.ndarray:
    """Counted in parts of as many edges as there are vertices, a million at least."""
    out, part = np.zeros(n, np.int64), max(n, 1 << 20)
    for lo in range(0, len(u), part):
        for x in (u, v):
            out += np.bincount(x[lo : lo + part], minlength=n)
    return out


def hdrf_kernel(lam: float = LAMBDA, degrees: str = "partial", scan: str = "all") -> sequential.Kernel:
    """scan="all" scores every block, as published; "seen" only those that can win, with the same result in time free of k."""

    def kernel(u, v, n, k, limits, info=None):
        greedy = _greedy(n, k, limits, lam, _degrees(u, v, n) if degrees == "exact" else None, scan)
        out = np.empty(len(u), np.int32)
        for s, a, b in sequential.slices_of(u, v):
            out[s] = list(map(greedy.place, a, b))
        if info is not None:
            info["cells"] = greedy.cells()
        return out

    return kernel


def hdrf(g: Graph, k: int, eps: float | str = "0.03", lam: float = LAMBDA, degrees: str = "partial", lanes: int = 1, scan: str = "seen") -> Partition:
    """Prefers to copy the end of larger degree; lam weighs balance. degrees="exact" counts them in a pass before."""
    return sequential.run(g, k, hdrf_kernel(lam, degrees, scan), eps, lanes, 2 if degrees == "exact" else 1)


# ---- two phases

def stream_clusters(u: np.ndarray, v: np.ndarray, degree: np.ndarray, cap: float) -> tuple[np.ndarray, np.ndarray]:
    """Cluster of each vertex and volumes: along the stream the end in the lighter cluster joins the heavier, below the cap."""
    own, volume, d = (array("q", x.astype(np.int64).tobytes()) for x in (np.arange(len(degree)), degree, degree))
    for _, xs, ys in sequential.slices_of(u, v):
        for a, b in zip(xs, ys):
            ca, cb = own[a], own[b]
            if ca != cb:
                of_a, of_b = volume[ca], volume[cb]
                if of_a <= cap and of_b <= cap:
                    x, small, large, most = (a, ca, cb, of_b) if of_a <= of_b else (b, cb, ca, of_a)
                    if most + d[x] <= cap:
                        volume[large] = most + d[x]
                        volume[small] -= d[x]
                        own[x] = large
    return np.array(own, np.int64), np.array(volume, np.int64)


def pack_clusters(volume: np.ndarray, k: int) -> np.ndarray:
    """Block of each cluster: by falling volume to the lightest block. Empty ones come last and change nothing."""
    heap, out = [(0, i) for i in range(k)], np.zeros(len(volume), np.int64)
    held = np.flatnonzero(volume)
    for c in held[np.argsort(-volume[held], kind="stable")].tolist():
        load, i = heap[0]
        out[c] = i
        heapq.heapreplace(heap, (load + int(volume[c]), i))
    out[volume == 0] = heap[0][1]
    return out


def prepartition(edges: DataFrame, clusters: DataFrame, blocks: DataFrame) -> DataFrame:
    """Edges whose ends' clusters share a block: (eid, u, v, block). clusters (v, cluster), blocks (cluster, block)."""
    home = clusters.join(blocks, "cluster").select("v", "block")
    both = edges.join(home.select(F.col("v").alias("u"), F.col("block").alias("bu")), "u").join(home.select("v", F.col("block").alias("bv")), "v")
    return both.where("bu = bv").select("eid", "u", "v", F.col("bu").alias("block"))


def two_phase_kernel(second: str = "hdrf", lam: float = LAMBDA, scan: str = "all") -> sequential.Kernel:
    if second not in ("hdrf", "linear"):
        raise ValueError(second)

    def kernel(u, v, n, k, limits, info=None):
        degree = _degrees(u, v, n)
        own, volume = stream_clusters(u, v, degree, 2 * len(u) / k)
        home = pack_clusters(volume, k)[own].astype(np.int32)
        greedy = _greedy(n, k, limits, lam, degree, scan)
        out, loads, most, put = np.full(len(u), -1, np.int32), greedy.loads, limits.tolist(), greedy.put
        for s, a, b in sequential.slices_of(u, v, lambda s: home[u[s]] == home[v[s]]):
            out[s] = [put(x, y, i) if loads[i] < most[i] else -1 for x, y, i in zip(a, b, home[a].tolist())]
        linear = _linear(greedy, home, own, volume, k)
        for s, a, b in sequential.slices_of(u, v, lambda s: out[s] < 0):
            out[s] = list(map(greedy.place if second == "hdrf" else linear, a, b))
        if info is not None:
            info["cells"] = greedy.cells() + own.size + volume.size + home.size
        return out

    return kernel


def two_phase(g: Graph, k: int, second: str = "hdrf", eps: float | str = "0.03", lam: float = LAMBDA, lanes: int = 1, scan: str = "seen") -> Partition:
    """Clusters the stream, packs clusters on blocks, places what agrees, then the rest by HDRF over all blocks or, with
    second="linear", on one of the two blocks of the ends' clusters."""
    return sequential.run(g, k, two_phase_kernel(second, lam, scan), eps, lanes, 3)


def _linear(greedy: _Greedy | _Seen, home: np.ndarray, own: np.ndarray, volume: np.ndarray, k: int):
    """Places an edge on one of the two blocks of its ends' clusters, else by hash of the end of larger degree, else on the lightest."""
    loads, limits, degree = greedy.loads, greedy.limits, greedy.degree
    of = array("q", volume[own].astype(np.int64).tobytes())
    home = array("i", home.astype(np.int32).tobytes())

    def place(a: int, b: int) -> int:
        da, db = degree[a], degree[b]
        share, total = da / (da + db), max(1, of[a] + of[b])
        scored = []
        for i, c in ((home[a], of[a]), (home[b], of[b])):
            if loads[i] < limits[i]:
                scored.append((-(greedy.met(a, i) * (2 - share) + greedy.met(b, i) * (1 + share) + c / total), i))
        if scored:
            return greedy.put(a, b, min(scored)[1])
        x = (a if da >= db else b) % k
        return greedy.put(a, b, x if loads[x] < limits[x] else greedy.lightest())

    return place


# ---- further ones that the comparison leaves out

def neighbour_expansion(g: Graph, k: int, eps: float | str = "0.03", sample: float = 2.0, lanes: int = 1) -> Partition:
    """Grows one block after the other from a bounded window of the stream, taking next the vertex with fewest outside edges."""

    def kernel(u, v, n, k, limits, info=None):
        window = max(1, int(sample * len(u) / k))
        out, done, at, alive = np.full(len(u), -1, np.int32), 0, 0, 0
        count = np.zeros(n, np.int64)  # edges of each vertex in the window
        near = np.argsort(np.concatenate([u, v]), kind="stable")
        near %= max(len(u), 1)  # edges of each vertex; those of the window lie before at and have no block
        near = near.astype(np.int32 if len(u) < 1 << 31 else np.int64)
        starts = np.concatenate([[0], np.cumsum(_degrees(u, v, n))])

        def refill():
            nonlocal at, alive
            more = min(window - alive, len(u) - at)
            if more > 64:
                np.add.at(count, u[at : at + more], 1)
                np.add.at(count, v[at : at + more], 1)
            else:
                for e in range(at, at + more):
                    count[u[e]] += 1
                    count[v[e]] += 1
            at += max(more, 0)
            alive += max(more, 0)

        for block in range(k):
            room = int(limits[block]) if block < k - 1 else len(u)
            target = min(room, -(-(len(u) - done) // (k - block)))
            core: list[tuple[int, int]] = []
            refill()
            while target > 0 and alive:
                while core and not count[core[0][1]]:
                    heapq.heappop(core)
                x = heapq.heappop(core)[1] if core else int(np.where(count > 0, count, 1 << 62).argmin())
                own = near[starts[x] : starts[x + 1]]
                own = np.sort(own[(own < at) & (out[own] < 0)])[:target]
                for e, a, b in sequential.edges_of(u, v, own):
                    out[e] = block
                    target -= 1
                    done += 1
                    alive -= 1
                    for y in (a, b):
                        count[y] -= 1
                        if count[y] and y != x:
                            heapq.heappush(core, (int(count[y]), y))
                refill()
        rest = np.flatnonzero(out < 0)
        loads = np.bincount(out[out >= 0], minlength=k)
        for e in rest.tolist():
            i = int(np.where(loads < limits, loads, 1 << 62).argmin())
            out[e] = i
            loads[i] += 1
        return out

    return sequential.run(g, k, kernel, eps, lanes)


def window_greedy(g: Graph, k: int, window: int = 64, eps: float | str = "0.03", lam: float = LAMBDA, lanes: int = 1, adaptive: bool = True) -> Partition:
    """Keeps a window of edges and places the one with the best score next; scores are those of HDRF with exact degrees, ties go to the edge read first.

    The window starts with one edge. After as many placements as it holds, it doubles up to its bound if their mean score rose, and
    halves if it fell: edges wait only as long as waiting pays.
    """

    def kernel(u, v, n, k, limits, info=None):
        greedy = _Greedy(n, k, limits, lam, _degrees(u, v, n))
        pair = lambda e: (int(u[e]), int(v[e]))
        out, held, nxt = np.full(len(u), -1, np.int32), [], 0
        size, gained, before = 1 if adaptive else window, [], 0.0
        while nxt < len(u) or held:
            while len(held) < size and nxt < len(u):
                held.append(nxt)
                nxt += 1
            scores = np.array([greedy.score(*pair(e)) for e in held])
            at = int(scores.max(axis=1).argmax())
            e = held.pop(at)
            out[e] = greedy.put(*pair(e), int(scores[at].argmax()))
            gained.append(float(scores[at].max()))
            if adaptive and len(gained) >= size:
                mean = sum(gained) / len(gained)
                size = min(window, 2 * size) if mean >= before else max(1, size // 2)
                before, gained = mean, []
        return out

    return sequential.run(g, k, kernel, eps, lanes)


def restricted_buffer(g: Graph, k: int, buffer: int = 1024, eps: float | str = "0.03", lam: float = LAMBDA, lanes: int = 1) -> Partition:
    """Postpones edges that no block holds an end of, in a buffer of fixed size; the buffer is emptied by degree when full."""

    def kernel(u, v, n, k, limits, info=None):
        degree = _degrees(u, v, n)
        greedy = _Seen(n, k, limits, lam, degree)
        out, held = np.full(len(u), -1, np.int32), []
        bits, degree, place, begun = greedy.bits, greedy.degree, greedy.place, False

        def flush():
            for _, e, a, b in sorted((degree[a] + degree[b], e, a, b) for e, a, b in held):
                out[e] = place(a, b)
            held.clear()

        for s, xs, ys in sequential.slices_of(u, v):
            for e, a, b in zip(range(s.start, s.stop), xs, ys):
                if bits[a] or bits[b] or not begun:
                    out[e], begun = place(a, b), True
                else:
                    held.append((e, a, b))
                    if len(held) >= buffer:
                        flush()
        flush()
        return out

    return sequential.run(g, k, kernel, eps, lanes)
