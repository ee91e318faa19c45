"""Array kernels that run inside one part or on one replicated graph."""

from __future__ import annotations

import heapq
from array import array
from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np

#: Most arcs whose columns become lists; an entry of a list takes up to five times that of an array.
LIST_ARCS = 1_000_000


@dataclass
class Block:
    """Compressed rows of one part: local nodes, offsets, neighbours, weights, and edges where they are given."""

    ids: np.ndarray
    offsets: np.ndarray
    targets: np.ndarray
    weights: np.ndarray
    eids: np.ndarray

    @staticmethod
    def of(u: np.ndarray, v: np.ndarray, w: np.ndarray, eid: np.ndarray | None = None) -> Block:
        ids = np.union1d(u, v)
        lu, lv = np.searchsorted(ids, u).astype(np.int32), np.searchsorted(ids, v).astype(np.int32)
        order = np.lexsort((lv, lu))
        offsets = np.zeros(len(ids) + 1, np.int64)
        np.cumsum(np.bincount(lu, minlength=len(ids)), out=offsets[1:])
        return Block(ids, offsets, lv[order], w[order], np.empty(0, np.int64) if eid is None else eid[order])

    def place(self, nid: np.ndarray) -> np.ndarray:
        """Local places of node ids; -1 for those that are not here."""
        if not len(self.ids):
            return np.full(len(nid), -1)
        at = np.minimum(np.searchsorted(self.ids, nid), len(self.ids) - 1)
        return np.where(self.ids[at] == nid, at, -1)

    def lists(self) -> tuple[Sequence, Sequence, Sequence]:
        """Offsets, neighbours and weights to be read one by one: as lists, or as compact arrays where lists would fill a worker."""
        if not hasattr(self, "_lists"):
            columns = self.offsets, self.targets, self.weights
            self._lists = tuple(c.tolist() if len(self.targets) <= LIST_ARCS else array(c.dtype.char, c.tobytes()) for c in columns)
        return self._lists


def pack_block(block: Block, border: np.ndarray, mine: np.ndarray) -> bytes:
    """A part as bytes: sizes, ids, offsets, targets, weights, and two flags for each node."""
    n, e = len(block.ids), len(block.targets)
    pieces = [np.array([n, e], np.int64), block.ids.astype(np.int64), block.offsets.astype(np.int64), block.targets.astype(np.int32), border.astype(np.uint8), mine.astype(np.uint8)]
    return block.weights.tobytes() + b"".join(p.tobytes() for p in pieces[1:]) + pieces[0].tobytes()


def unpack_block(packed, number) -> tuple[Block, np.ndarray, np.ndarray]:
    """(block without edge ids, border flags, flags of nodes that this part reports)."""
    raw = np.frombuffer(packed, np.uint8)
    n, e = np.frombuffer(raw[-16:].tobytes(), np.int64).tolist()
    at = 0

    def take(count: int, kind) -> np.ndarray:
        nonlocal at
        size = count * np.dtype(kind).itemsize
        out = np.frombuffer(raw[at : at + size].tobytes(), kind)
        at += size
        return out

    weights, ids, offsets, targets, border, mine = take(e, number), take(n, np.int64), take(n + 1, np.int64), take(e, np.int32), take(n, np.uint8), take(n, np.uint8)
    return Block(ids, offsets, targets, weights, np.empty(0, np.int64)), border.astype(bool), mine.astype(bool)


def settle(lists: tuple[list, list, list], dist: list, seeds: list[tuple[float, int]], stop: set[int] | None = None, limit: float = float("inf")) -> list[int]:
    """Priority-queue shortest paths from several seeds; lowers ``dist`` and returns the changed places.

    Seeds count only where they lower what is known. With ``stop`` the search
    ends when all of its places are settled, and beyond ``limit`` it does not go.
    """
    offsets, targets, weights = lists
    heap, changed = [], set()
    for d, i in seeds:
        if d < dist[i] and d <= limit:
            dist[i] = d
            changed.add(i)
            heap.append((d, i))
    heapq.heapify(heap)
    left = set(stop) if stop is not None else None
    while heap:
        d, i = heapq.heappop(heap)
        if d > dist[i]:
            continue
        if left is not None:
            left.discard(i)
            if not left:
                break
        for k in range(offsets[i], offsets[i + 1]):
            e = d + weights[k]
            j = targets[k]
            if e < dist[j] and e <= limit:
                dist[j] = e
                changed.add(j)
                heapq.heappush(heap, (e, j))
    return list(changed)


def _once(a: np.ndarray) -> np.ndarray:
    """Sorted, each value once; sorts ``a``, which for few values is faster than a table of them."""
    a.sort()
    return a[np.concatenate(([True], a[1:] != a[:-1]))] if len(a) else a


def settle_each(block: Block, starts: np.ndarray, limit: float = float("inf")) -> np.ndarray:
    """Least costs from each of several places to all places, a row for each start; the largest number of the kind where there is no way.

    All runs advance together, over a window of cost that is four mean weights
    wide: what falls into it is passed on until nothing in it improves, the rest
    waits. Costs are those of a priority queue.
    """
    n, offsets, targets, weights = len(block.ids), block.offsets, block.targets, block.weights
    none = np.iinfo(weights.dtype).max if weights.dtype.kind == "i" else np.inf
    dist = np.full(len(starts) * n, none, weights.dtype)
    wide = max(4 * weights.mean(), np.finfo(float).tiny) if len(weights) else 1.0
    near = np.arange(len(starts)) * n + starts
    dist[near] = 0
    far, upto = [], wide
    while len(near):
        while len(near):
            node = near % n
            first = offsets[node]
            count = offsets[node + 1] - first
            ends = np.cumsum(count)
            arc = np.repeat(first - ends + count, count) + np.arange(ends[-1])
            cost, to = np.repeat(dist[near], count) + weights[arc], np.repeat(near - node, count) + targets[arc]
            better = (cost < dist[to]) & (cost <= limit)
            to, cost = to[better], cost[better]
            np.minimum.at(dist, to, cost)
            soon = cost < upto
            far.append(to[~soon])
            near = _once(to[soon])
        rest = np.concatenate(far)
        known = dist[rest]
        ahead = known >= upto  # the others have been passed on meanwhile
        rest, known = rest[ahead], known[ahead]
        if not len(rest):
            break
        upto = max(known.min() + wide, np.nextafter(float(known.min()), np.inf))
        now = known < upto
        near, far = _once(rest[now]), [rest[~now]]
    return dist.reshape(len(starts), n)


def brandes(block: Block, source: int, weighted: bool = True) -> np.ndarray:
    """Pair dependencies of one source on every node of the block (shortest path counting)."""
    offsets, targets, weights = block.lists()
    n = len(block.ids)
    dist, sigma, before, order = [float("inf")] * n, [0.0] * n, [[] for _ in range(n)], []
    dist[source], sigma[source] = 0, 1.0
    heap, done = [(0, source)], [False] * n
    while heap:
        d, i = heapq.heappop(heap)
        if done[i]:
            continue
        done[i] = True
        order.append(i)
        for k in range(offsets[i], offsets[i + 1]):
            j = targets[k]
            e = d + (weights[k] if weighted else 1)
            if e < dist[j]:
                dist[j], sigma[j], before[j] = e, sigma[i], [i]
                heapq.heappush(heap, (e, j))
            elif e == dist[j] and not done[j]:
                sigma[j] += sigma[i]
                before[j].append(i)
    delta = np.zeros(n)
    for j in reversed(order):
        for i in before[j]:
            delta[i] += sigma[i] / sigma[j] * (1 + delta[j])
    delta[source] = 0
    return delta
