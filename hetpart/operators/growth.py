"""Growing partitions in one task: best-first, breadth-first or depth-first.

A graph block is compressed rows in numpy; edges leave the pool once. Frontier keys only
fall while the covered set grows, so a heap with stale entries gives the least one.
"""

from __future__ import annotations

import heapq
from array import array
from collections import deque
from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class GrowthConfig:
    alpha: float = 0.3
    beta: float = 0.3
    order: str = "best"  # best, bfs, dfs
    seeds: str = "low_degree"  # low_degree, max_degree, random
    seed: int = 1
    memory_guard: bool = True


#: A vertex of so many edges or fewer is handled edge by edge.
FEW = 48


#: Edges that are handled at once while a block is built.
SLICE = 1 << 20


def _slices(n: int):
    return ((lo, min(n, lo + SLICE)) for lo in range(0, n, SLICE))


class Block:
    """Edges of one group with adjacency; edge i joins a[i] and b[i] (compressed ids).

    direction: 'both', or 'out' / 'in' for arcs, where growth only follows arcs from (to)
    the core; edges between covered vertices are taken whatever way they point. Numbers of
    vertices and edges have 32 bits while they fit."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, direction: str = "both"):
        self._build([src, dst], direction)

    @classmethod
    def taking(cls, ends: list[np.ndarray]) -> Block:
        """The block of [src, dst]; the list is emptied, so that they go before adjacency is made."""
        block = cls.__new__(cls)
        block._build(ends, "both")
        return block

    def _build(self, ends: list[np.ndarray], direction: str) -> None:
        self.ids = np.union1d(np.unique(ends[0]), np.unique(ends[1]))
        n, m = len(self.ids), len(ends[0])
        key = np.empty(m, np.int64)
        for lo, hi in _slices(m):
            key[lo:hi] = np.searchsorted(self.ids, ends[0][lo:hi]) * np.int64(n) + np.searchsorted(self.ids, ends[1][lo:hi])
        ends.clear()
        key.sort()
        kind = np.int32 if 2 * m < 1 << 31 else np.int64
        self.a, self.b = np.empty(m, kind), np.empty(m, kind)
        for lo, hi in _slices(m):
            self.a[lo:hi], self.b[lo:hi] = np.divmod(key[lo:hi], n)
        del key
        self._adjacent(n, m, kind)
        self.free = np.ones(m, np.bool_)
        self.degree = np.diff(self.ptr).astype(np.int64)
        if direction == "both":
            self.reach = (memoryview(self.ptr), memoryview(self.nbr), memoryview(self.eid), self.nbr, self.eid)
        else:
            ends, other = (self.a, self.b) if direction == "out" else (self.b, self.a)
            o = np.lexsort((other, ends))
            near, edge = np.ascontiguousarray(other[o], np.int64), o.astype(np.int64)
            self.reach = (memoryview(np.searchsorted(ends[o], np.arange(n + 1))), memoryview(near), memoryview(edge), near, edge)

    def _adjacent(self, n: int, m: int, kind) -> None:
        """Neighbours of each vertex in ascending order, with the edges that lead there."""
        if not (self.a < self.b).all():
            ends, other, eid = np.concatenate([self.a, self.b]), np.concatenate([self.b, self.a]), np.tile(np.arange(m), 2)
            o = np.lexsort((other, ends))
            self.nbr, self.eid = np.ascontiguousarray(other[o], kind), np.ascontiguousarray(eid[o], kind)
            self.ptr = np.searchsorted(ends[o], np.arange(n + 1))
            return
        # edges are in the order of a and b: a vertex has its lower neighbours first, then its higher ones
        by_b = np.argsort(self.b, kind="stable").astype(kind)
        higher = np.searchsorted(self.a, np.arange(n + 1, dtype=kind))
        lower = np.concatenate([[0], np.cumsum(np.bincount(self.b, minlength=n))])
        self.ptr = higher + lower
        self.nbr, self.eid = np.empty(2 * m, kind), np.empty(2 * m, kind)
        for lo, hi in _slices(m):
            e, all_ = by_b[lo:hi], np.arange(lo, hi)
            at = all_ + higher[self.b[e]]
            self.nbr[at], self.eid[at] = self.a[e], e
            at = all_ + lower[self.a[lo:hi] + 1]
            self.nbr[at], self.eid[at] = self.b[lo:hi], all_

    @property
    def src(self) -> np.ndarray:
        return self.ids[self.a]

    @property
    def dst(self) -> np.ndarray:
        return self.ids[self.b]


class Seeds:
    """Next start vertex among those with free edges: the least key, then the least number.
    Vertices come in the order that they have at first, and out of a heap once they were seen."""

    def __init__(self, block: Block, policy: str, seed: int):
        self.block, self.policy = block, policy
        n = len(block.ids)
        key = np.random.default_rng(seed).permutation(n) if policy == "random" else (-1 if policy == "max_degree" else 1) * block.degree
        self.key = key.astype(block.a.dtype)
        self.order = np.argsort(self.key, kind="stable").astype(block.a.dtype)
        self.at, self.heap = 0, []

    def _least(self) -> tuple[int, int] | None:
        if self.at < len(self.order):
            v = int(self.order[self.at])
            x = (int(self.key[v]), v)
            if not self.heap or x < self.heap[0]:
                self.at += 1
                return x
        return heapq.heappop(self.heap) if self.heap else None

    def next(self, done) -> int | None:
        sign = -1 if self.policy == "max_degree" else 1
        aside, found = [], None
        while (x := self._least()) is not None:
            key, v = x
            d = int(self.block.degree[v])
            if d == 0:
                continue
            if self.policy != "random" and key != sign * d:
                heapq.heappush(self.heap, (sign * d, v))
                continue
            aside.append(x)
            if not done[v]:
                found = v
                break
        for x in aside:
            heapq.heappush(self.heap, x)
        return found


def grow_one(block: Block, cap: int, border: np.ndarray, seeds: Seeds, cfg: GrowthConfig, room: float = np.inf, m_node: float = 1.0, m_edge: float = 2.0) -> np.ndarray:
    """Edges of one partition in the order they were taken; stops exactly at cap, or where
    the next edge wouldn't fit in memory. Adds the partition's frontier to the border.

    Vertices of few edges are handled one edge at a time, hubs by whole arrays: flags and
    counts live in buffers that plain Python and numpy both see."""
    n = len(block.ids)
    covered, core, touched = bytearray(n), bytearray(n), bytearray(n)
    see = lambda x: np.frombuffer(x, np.bool_)
    covered_, core_, touched_ = see(covered), see(core), see(touched)
    outside_ = block.degree.copy()
    outside, degree, free, edge_of, other = memoryview(outside_), memoryview(block.degree), memoryview(block.free.view(np.uint8)), memoryview(block.eid), memoryview(block.nbr)
    # priority = a1 * outside - pull, with pull fixed while this partition grows
    a1 = 1 + cfg.alpha
    pull = memoryview((cfg.alpha + cfg.beta * border) * block.degree)
    ptr, best = memoryview(block.ptr), cfg.order == "best"
    line: deque[int] = deque()
    heap: list[tuple[float, int]] = []
    taken = array("q")
    arrays: list[np.ndarray] = []
    bounded, used, count, full = np.isfinite(room), 0.0, 0, False
    push = heapq.heappush

    def cover_few(y: int, lo: int, hi: int) -> None:
        nonlocal used, count, full
        mine = 0
        for k in range(lo, hi):
            e = edge_of[k]
            if not free[e]:
                continue
            v = other[k]
            outside[v] -= 1
            if not covered[v] or v == y:
                continue
            if not full:
                grown = used
                if bounded:
                    grown += m_edge + m_node * ((not touched[v]) + (not touched[y]))
                if grown > room + 1e-9:
                    full = True
                else:
                    used, free[e] = grown, 0
                    touched[v] = touched[y] = 1
                    degree[v] -= 1
                    mine += 1
                    taken.append(e)
                    count += 1
                    full = count >= cap
            if best and not core[v]:
                push(heap, (a1 * outside[v] - pull[v], v))
        degree[y] -= mine

    def cover_many(y: int, lo: int, hi: int) -> None:
        nonlocal used, count, full, taken
        e, v = block.eid[lo:hi], block.nbr[lo:hi]
        k = block.free[e]
        e, v = e[k], v[k]
        outside_[v] -= 1
        k = covered_[v]
        e, v = e[k], v[k]
        if len(e):
            take = min(len(e), cap - count)
            if bounded:
                grown = used + m_edge * np.arange(1, take + 1) + m_node * (np.cumsum(~touched_[v[:take]]) + (not touched[y]))
                take = int(np.searchsorted(grown, room + 1e-9, "right"))
                used = float(grown[take - 1]) if take else used
            if take:
                own = v[:take]
                touched_[own] = True
                touched[y] = 1
                block.free[e[:take]] = False
                block.degree[own] -= 1
                degree[y] -= take
                arrays.append(np.array(taken, np.int64))
                arrays.append(e[:take])
                taken = array("q")
                count += take
            full = count >= cap or take < len(e)
        if best:
            for u in v[~core_[v]].tolist():
                push(heap, (a1 * outside[u] - pull[u], u))

    def cover(y: int) -> None:
        covered[y] = 1
        lo, hi = ptr[y], ptr[y + 1]
        (cover_few if hi - lo <= FEW else cover_many)(y, lo, hi)
        if best:
            push(heap, (a1 * outside[y] - pull[y], y))
        else:
            line.append(y)

    def pick() -> int | None:
        if best:
            while heap:
                key, v = heapq.heappop(heap)
                if not core[v] and key <= a1 * outside[v] - pull[v] + 1e-12:
                    return v
            return None
        while line:
            v = line.popleft() if cfg.order == "bfs" else line.pop()
            if not core[v]:
                return v
        return None

    while count < cap and not full:
        x = pick()
        if x is None:
            x = seeds.next(core)
            if x is None:
                break
            core[x] = 1
            if not covered[x]:
                cover(x)
        core[x] = 1
        if full:
            break
        lo, hi = block.reach[0][x], block.reach[0][x + 1]
        near, edge = block.reach[1], block.reach[2]
        if hi - lo <= FEW:
            todo = [near[k] for k in range(lo, hi) if free[edge[k]] and not covered[near[k]]]
        else:
            e, v = block.reach[4][lo:hi], block.reach[3][lo:hi]
            todo = v[block.free[e] & ~covered_[v]].tolist()
        for y in todo:
            if not covered[y]:
                cover(y)
                if full:
                    break
    border |= covered_ & ~core_
    arrays.append(np.array(taken, np.int64))
    return np.concatenate(arrays)


def grow_all(block: Block, caps: list[int], memory: list[float] | None, cfg: GrowthConfig, served: list[int] | None = None, m_node: float = 1.0, m_edge: float = 2.0) -> tuple[np.ndarray, np.ndarray]:
    """Machine (-1: not placed) and sequence number of each edge; machines grow in turn."""
    machine, seq = np.full(len(block.a), -1, np.int32), np.zeros(len(block.a), block.a.dtype)
    border, seeds = np.zeros(len(block.ids), np.bool_), Seeds(block, cfg.seeds, cfg.seed)
    for i in served if served is not None else range(len(caps)):
        room = memory[i] if memory is not None and cfg.memory_guard else np.inf
        e = grow_one(block, caps[i], border, seeds, cfg, room, m_node, m_edge)
        machine[e], seq[e] = i, np.arange(len(e))
    return machine, seq
