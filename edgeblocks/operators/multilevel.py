"""Multilevel cut of one batch on arrays: cluster, contract, place, project, refine.

A level has items with whole-number weights, links (a, b, w) between items and links (item, block, w) to fixed blocks.
Rounds are synchronous: half of the items, drawn by hash, may move at a time, and moves into a target are admitted by gain while its
room lasts; that keeps them vectorised and the bounds strict.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np

from .fennel import GAMMA, place_items

#: Rounds of clustering and of refinement, bounds of the coarsest level, least shrinking, which part of a block a cluster
#: may fill, and below which part of the items the moves of two rounds end the refinement.
CLUSTER_ROUNDS, REFINE_ROUNDS, COARSEST_FACTOR, SHRINK, CAP_SHARE, STALLED = 5, 20, 4, 0.95, 2, 400
#: Cells (items x blocks) and blocks up to which a refinement keeps the link weight of every item into every block; items up to which a draw is kept.
DENSE_CELLS, DENSE_BLOCKS, KEPT_DRAW = 1 << 20, 64, 1 << 14


@dataclass
class Level:
    weights: np.ndarray
    a: np.ndarray
    b: np.ndarray
    w: np.ndarray
    items: np.ndarray  # of the fixed links
    fixed: np.ndarray  # their blocks
    fw: np.ndarray

    @property
    def size(self) -> int:
        return len(self.weights)


def _hash(x: np.ndarray, seed: int) -> np.ndarray:
    h = (x.astype(np.uint64) + np.uint64(seed + 1)) * np.uint64(0x9E3779B97F4A7C15)
    return (h ^ h >> np.uint64(32)) * np.uint64(0xD6E8FEB86659FD93) >> np.uint64(33)


@lru_cache(maxsize=256)
def _drawn(n: int, seed: int) -> np.ndarray:
    """Which of the items 0 to n - 1 may move, half of them by hash."""
    return _hash(np.arange(n), seed) & np.uint64(1) == 0


def _half(n: int, seed: int) -> np.ndarray:
    """The same; draws of small levels are kept, since all batches use them again."""
    top = 1 << max(n - 1, 0).bit_length()
    return _drawn(top, seed)[:n] if top <= KEPT_DRAW else _drawn.__wrapped__(n, seed)


@lru_cache(maxsize=512)
def _drawn_at(n: int, seed: int) -> np.ndarray:
    return np.flatnonzero(_half(n, seed))


def _half_at(n: int, seed: int) -> np.ndarray:
    """The same as positions; kept by powers of two, like the draws."""
    top = 1 << max(n - 1, 0).bit_length()
    if top > KEPT_DRAW:
        return _drawn_at.__wrapped__(n, seed)
    at = _drawn_at(top, seed)
    return at[: at.searchsorted(n)]


def _heads(x: np.ndarray) -> np.ndarray:
    """Positions at which a run of equal values begins."""
    new = np.ones(len(x), bool)
    np.not_equal(x[1:], x[:-1], out=new[1:])
    return np.flatnonzero(new)


def sort_with(key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Keys (0 or more) in order and where each stood, ties in the order they stood in; both go into one number where they fit."""
    bits = len(key).bit_length()
    if not len(key) or int(key.max()) >> (62 - bits):
        at = np.argsort(key, kind="stable")
        return key[at], at
    both = np.sort(key << bits | np.arange(len(key)))
    return both >> bits, both & ((1 << bits) - 1)


def _sum_by(key: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    key, at = sort_with(key)
    heads = _heads(key)
    run = np.zeros(len(key), np.int64)
    run[heads[1:]] = 1
    return key[heads], np.bincount(np.cumsum(run), weights=w[at], minlength=len(heads))


def coarsest_size(items: int, k: int, factor: int = COARSEST_FACTOR) -> int:
    """The larger of a share of the items per block and some items per block."""
    return max(items // (2 * k), factor * k)


def cluster(level: Level, cap: int, rounds: int = CLUSTER_ROUNDS, seed: int = 0) -> np.ndarray:
    """A cluster number per item by size-constrained label propagation; fixed links play no part."""
    n = level.size
    label, size = np.arange(n), level.weights.copy()
    x, y, w = np.concatenate([level.a, level.b]), np.concatenate([level.b, level.a]), np.concatenate([level.w, level.w])
    for r in range(rounds):
        key, total = _sum_by(x * n + label[y], w)
        item, target = key // n, key % n
        own = np.zeros(n)
        mine = target == label[item]
        own[item[mine]] = total[mine]
        movable = _half(n, seed + r)[item] & ~mine & (total > own[item]) & (size[target] + level.weights[item] <= cap)
        item, target, total = item[movable], target[movable], total[movable]
        if not len(item):
            if r % 2:
                break
            continue
        heads = _heads(item)  # pairs stand by item and target, so the first of the strongest has the smallest target
        most = np.maximum.reduceat(total, heads)
        first = np.flatnonzero(total == np.repeat(most, np.diff(np.append(heads, len(item)))))
        first = first[_heads(item[first])]
        item, target, total = item[first], target[first], total[first] - own[item[first]]
        # items of this half leave their clusters, so a target must not be one whose own last item is leaving for elsewhere
        order = np.lexsort((item, -total, target))
        item, target = item[order], target[order]
        c = level.weights[item]
        run = np.cumsum(c)
        start = _heads(target)
        base = np.repeat(run[start] - c[start], np.diff(np.append(start, len(target))))
        fits = size[target] + run - base <= cap
        item, target = item[fits], target[fits]
        np.subtract.at(size, label[item], level.weights[item])
        np.add.at(size, target, level.weights[item])
        label[item] = target
    used = np.zeros(n, np.int64)
    used[label] = 1
    return (np.cumsum(used) - 1)[label]


def contract(level: Level, clusters: np.ndarray) -> Level:
    """Weights add, parallel links merge with their sum, loops go; fixed links of merged items add per block."""
    n = int(clusters.max(initial=-1)) + 1
    weights = np.bincount(clusters, weights=level.weights, minlength=n).astype(np.int64)
    a, b = clusters[level.a], clusters[level.b]
    keep = a != b
    key, w = _sum_by(np.minimum(a, b)[keep] * n + np.maximum(a, b)[keep], level.w[keep])
    top = int(level.fixed.max(initial=0)) + 1
    fkey, fw = _sum_by(clusters[level.items] * top + level.fixed, level.fw)
    return Level(weights, key // max(n, 1), key % max(n, 1), w, fkey // top, fkey % top, fw)


def project(coarse: np.ndarray, clusters: np.ndarray) -> np.ndarray:
    return coarse[clusters]


def coarsen(level: Level, k: int, cap: int, rounds: int = CLUSTER_ROUNDS, seed: int = 0) -> tuple[list[Level], list[np.ndarray]]:
    """Levels from fine to coarse and the clusters between them; stops at the bound or when a level hardly shrinks."""
    levels, maps = [level], []
    bound = coarsest_size(level.size, k)
    while levels[-1].size > bound:
        clusters = cluster(levels[-1], cap, rounds, seed + 17 * len(maps))
        smaller = contract(levels[-1], clusters)
        if smaller.size > SHRINK * levels[-1].size:
            break
        levels.append(smaller)
        maps.append(clusters)
    return levels, maps


def _rows(n: int, x: np.ndarray, y: np.ndarray, w: np.ndarray):
    """Row access: values and weights of each x."""
    order = np.argsort(x, kind="stable")
    ends = np.concatenate([[0], np.cumsum(np.bincount(x, minlength=n))]).tolist()
    ys, ws = y[order].tolist(), w[order].tolist()
    return lambda i: (ys[ends[i] : ends[i + 1]], ws[ends[i] : ends[i + 1]])


def place(level: Level, blocks: np.ndarray, loads: np.ndarray, limits: np.ndarray, alpha: float, gamma: float, strategy: str) -> int:
    """Initial blocks by falling weight, then number."""
    n = level.size
    near = _rows(n, np.concatenate([level.a, level.b]), np.concatenate([level.b, level.a]), np.concatenate([level.w, level.w]))
    order = np.lexsort((np.arange(n), -level.weights))
    return place_items(order.tolist(), level.weights, near, _rows(n, level.items, level.fixed, level.fw), blocks, loads, limits, alpha, gamma, strategy)


def refine(level: Level, blocks: np.ndarray, loads: np.ndarray, limits: np.ndarray, alpha: float, gamma: float = GAMMA, rounds: int = REFINE_ROUNDS, seed: int = 0) -> int:
    """Moves items to adjacent blocks of larger gain, in place; fixed blocks count and stay; limits hold strictly. Either form makes the same moves."""
    dense = len(loads) <= DENSE_BLOCKS and level.size * len(loads) <= DENSE_CELLS
    return (_refine_dense if dense else _refine_sparse)(level, blocks, loads, limits, alpha * gamma, gamma - 1, rounds, seed)


def _admit(item: np.ndarray, block: np.ndarray, better: np.ndarray, weights: np.ndarray, blocks: np.ndarray, loads: np.ndarray, limits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Items that move and their old blocks: by gain while the target's room lasts, in place."""
    c = weights[item]
    more = np.bincount(block, weights=c, minlength=len(loads)).astype(np.int64)
    if (loads + more <= limits).all():  # room for all of them, in any order
        old = blocks[item]
        loads += more
        loads -= np.bincount(old, weights=c, minlength=len(loads)).astype(np.int64)
        blocks[item] = block
        return item, old
    order = np.lexsort((item, -better, block))
    item, block = item[order], block[order]
    c = weights[item]
    run = np.cumsum(c)
    start = _heads(block)
    base = np.repeat(run[start] - c[start], np.diff(np.append(start, len(block))))
    fits = loads[block] + run - base <= limits[block]
    item, block, c = item[fits], block[fits], c[fits]
    old = blocks[item]
    np.subtract.at(loads, old, c)
    np.add.at(loads, block, c)
    blocks[item] = block
    return item, old


def _refine_dense(level: Level, blocks: np.ndarray, loads: np.ndarray, limits: np.ndarray, edge: float, expo: float, rounds: int, seed: int) -> int:
    """With a table of link weight by block and item, to which each round adds what its moves change."""
    n, k, moves, idle = level.size, len(loads), 0, 0
    x, y, w = np.concatenate([level.a, level.b]), np.concatenate([level.b, level.a]), np.concatenate([level.w, level.w])
    flat = np.bincount(np.concatenate([blocks[y] * n + x, level.fixed * n + level.items]), weights=np.concatenate([w, level.fw]), minlength=n * k)
    table = flat.reshape(k, n)
    whole, moved = table.sum(axis=0), np.zeros(n, bool)
    for r in range(rounds):
        item = _half_at(n, seed + r)
        mine = flat[blocks[item] * n + item]
        linked = np.flatnonzero(whole[item] > mine)  # only items with a link into another block can move
        item, mine = item[linked], mine[linked]
        c = level.weights[item]
        now = mine - c * (edge * np.maximum(loads[blocks[item]] - c, 0).astype(float) ** expo)
        links = table.take(item, axis=1)
        value = links - c * (edge * loads.astype(float) ** expo)[:, None]
        can = np.flatnonzero(value.max(axis=0) > now + 1e-12)  # never by the own block, whose value is at most now
        light = np.lexsort((loads,))[:, None]  # of equal values the lightest block, then the smaller one
        value, now, c = value[light, can], now[can], c[can]
        value[(links[light, can] <= 0) | (c > (limits - loads)[light])] = -np.inf
        best = value.argmax(axis=0)
        value = value[best, np.arange(len(can))]
        ok = value > now + 1e-12
        if not ok.any():
            idle += 1
            if idle == 2:
                break
            continue
        item, old = _admit(item[can[ok]], light[best[ok], 0], (value - now)[ok], level.weights, blocks, loads, limits)
        moved[item] = True
        was = blocks.copy()
        was[item] = old
        touched = np.flatnonzero(moved[y])
        at, far = x[touched], y[touched]
        np.subtract.at(flat, was[far] * n + at, w[touched])
        np.add.at(flat, blocks[far] * n + at, w[touched])
        moved[item] = False
        moves += len(item)
        idle = idle + 1 if len(item) * STALLED < n else 0
        if idle == 2:
            break
    return moves


def _refine_sparse(level: Level, blocks: np.ndarray, loads: np.ndarray, limits: np.ndarray, edge: float, expo: float, rounds: int, seed: int) -> int:
    """With the pairs of item and block that are linked, summed anew in each round."""
    n, k, moves, idle = level.size, len(loads), 0, 0
    x, y, w = np.concatenate([level.a, level.b]), np.concatenate([level.b, level.a]), np.concatenate([level.w, level.w])
    for r in range(rounds):
        border = np.zeros(n, bool)  # only items with a link into another block can move
        border[x[blocks[x] != blocks[y]]] = True
        border[level.items[blocks[level.items] != level.fixed]] = True
        border &= _half(n, seed + r)
        near, far = border[x], border[level.items]
        key, total = _sum_by(np.concatenate([x[near] * k + blocks[y[near]], level.items[far] * k + level.fixed[far]]), np.concatenate([w[near], level.fw[far]]))
        item, block = key // k, key % k
        c = level.weights[item]
        home = block == blocks[item]
        now = -level.weights * (edge * np.maximum(loads[blocks] - level.weights, 0).astype(float) ** expo)
        now[item[home]] += total[home]
        value = total - c * (edge * loads[block].astype(float) ** expo)
        ok = ~home & (value > now[item] + 1e-12) & (loads[block] + c <= limits[block])
        item, block, value = item[ok], block[ok], value[ok]
        if not len(item):
            idle += 1
            if idle == 2:
                break
            continue
        order = np.lexsort((block, loads[block], -value, item))
        first = order[np.flatnonzero(np.diff(item[order], prepend=-1))]
        item, block, better = item[first], block[first], value[first] - now[item[first]]
        item, _ = _admit(item, block, better, level.weights, blocks, loads, limits)
        moves += len(item)
        idle = idle + 1 if len(item) * STALLED < n else 0
        if idle == 2:
            break
    return moves


def clusters(items: int, a: np.ndarray, b: np.ndarray, k: int, l_max: int, rounds: int = CLUSTER_ROUNDS, seed: int = 0) -> list[np.ndarray]:
    """The clusters between the levels of a cut. Neither fixed links nor loads play a part in them, so they don't wait for earlier batches."""
    none = np.zeros(0, np.int64)
    level = Level(np.ones(items, np.int64), a, b, np.ones(len(a)), none, none, np.zeros(0))
    return coarsen(level, k, max(1, l_max // CAP_SHARE), rounds, seed)[1]


@dataclass
class Cut:
    blocks: np.ndarray
    levels: int
    coarsest: int
    scores: int
    moves: int


def cut(level: Level, loads: np.ndarray, limits: np.ndarray, alpha: float, l_max: int, gamma: float = GAMMA, strategy: str = "two_set", cluster_rounds: int = CLUSTER_ROUNDS, refine_rounds: int = REFINE_ROUNDS, seed: int = 0, maps: list[np.ndarray] | None = None) -> Cut:
    """Blocks of a batch's items; loads (with earlier batches) are raised in place. maps: the clusters of clusters(), if known already.

    Clusters weigh at most a CAP_SHARE-th of the largest block; one for which no block has room is placed in parts on the next finer
    level, down to single edges, which always fit.
    """
    if maps is None:
        levels, maps = coarsen(level, len(loads), max(1, l_max // CAP_SHARE), cluster_rounds, seed)
    else:
        levels = [level]
        for m in maps:
            levels.append(contract(levels[-1], m))
    blocks = np.full(levels[-1].size, -1, np.int64)
    scores = place(levels[-1], blocks, loads, limits, alpha, gamma, strategy)
    moves = 0
    for at in range(len(levels) - 1, -1, -1):
        if at < len(maps):
            blocks = project(blocks, maps[at])
            if (blocks < 0).any():
                scores += place(levels[at], blocks, loads, limits, alpha, gamma, strategy)
        if (blocks >= 0).all():
            moves += refine(levels[at], blocks, loads, limits, alpha, gamma, refine_rounds, seed + 31 * at)
    if (blocks < 0).any():
        raise RuntimeError("no room for an edge: limits are too tight")
    return Cut(blocks, len(levels), levels[-1].size, scores, moves)
