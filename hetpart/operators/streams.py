"""Placement of edges one after another, and of vertices, in one task: the comparators.

Each takes a block, a fleet and options and returns the machine of every edge. Methods
made for equal machines get a memory guard; those made for unequal ones run without it
unless asked, and violations are counted by the cost measures."""

from __future__ import annotations

import heapq

import numpy as np

from .capacity import Infeasible, plan, uniform
from .growth import Block, GrowthConfig, grow_all
from .machines import Fleet
from .refine import State


class Loads:
    """Holders of each vertex and loads of each machine while a stream passes."""

    def __init__(self, block: Block, fleet: Fleet, guard: bool):
        p = len(fleet)
        self.block, self.fleet, self.guard = block, fleet, guard
        self.held = np.zeros((len(block.ids), p), np.bool_)
        self.edges, self.vertices = np.zeros(p), np.zeros(p)
        self.mem = np.array(fleet.column("mem"), float)
        self.machine = np.full(len(block.a), -1, np.int32)

    def allowed(self, a: int, b: int) -> np.ndarray:
        if not self.guard:
            return np.ones(len(self.mem), np.bool_)
        f = self.fleet
        need = f.m_edge * (self.edges + 1) + f.m_node * (self.vertices + ~self.held[a] + ~self.held[b])
        return need <= self.mem + 1e-9

    def place(self, e: int, score: np.ndarray) -> None:
        """Puts an edge where the score is highest among the allowed machines."""
        a, b = self.block.a[e], self.block.b[e]
        ok = self.allowed(a, b)
        i = int(np.where(ok, score, -np.inf).argmax()) if ok.any() else int(((self.edges * self.fleet.m_edge + self.vertices * self.fleet.m_node) / self.mem).argmin())
        for v in (a, b):
            if not self.held[v, i]:
                self.held[v, i] = True
                self.vertices[i] += 1
        self.edges[i] += 1
        self.machine[e] = i


def shuffled(block: Block, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).permutation(len(block.a))


def degree_aware(block: Block, fleet: Fleet, seed: int = 1, lam: float = 1.1, guard: bool = True) -> np.ndarray:
    """One pass; replicas of the end with the larger degree so far weigh less, plus balance."""
    s, seen = Loads(block, fleet, guard), np.zeros(len(block.ids))
    for e in shuffled(block, seed).tolist():
        a, b = block.a[e], block.b[e]
        seen[a] += 1
        seen[b] += 1
        share = seen[a] / (seen[a] + seen[b])
        top, low = s.edges.max(), s.edges.min()
        s.place(e, s.held[a] * (2 - share) + s.held[b] * (1 + share) + lam * (top - s.edges) / (1 + top - low))
    return s.machine


def sorted_balance(block: Block, fleet: Fleet, a_weight: float = 1.0, b_weight: float = 1.0, guard: bool = True) -> np.ndarray:
    """Edges by ascending sum of degrees; fewest new replicas plus edge and vertex loads."""
    s, p = Loads(block, fleet, guard), len(fleet)
    full = np.diff(block.ptr)
    per_e, per_v = max(1.0, len(block.a) / p), max(1.0, len(block.ids) / p)
    for e in np.lexsort((block.b, block.a, full[block.a] + full[block.b])).tolist():
        a, b = block.a[e], block.b[e]
        s.place(e, -(~s.held[a] * 1.0 + ~s.held[b] + a_weight * s.edges / per_e + b_weight * s.vertices / per_v))
    return s.machine


def hetero_stream(block: Block, fleet: Fleet, seed: int = 1, weight: float = 1.0, guard: bool = False) -> np.ndarray:
    """One pass; holders count by how cheap their network is, loads by how slow they are."""
    s = Loads(block, fleet, guard)
    com, edge = np.array(fleet.column("c_com"), float), np.array(fleet.column("c_edge"), float)
    near = com.min() / np.maximum(com, 1e-12)
    for e in shuffled(block, seed).tolist():
        a, b = block.a[e], block.b[e]
        time = (s.edges + 1) * edge
        s.place(e, near * (s.held[a] * 1.0 + s.held[b]) - weight * time / max(time.mean(), 1e-12))
    return s.machine


def load_only(block: Block, fleet: Fleet, seed: int = 1) -> np.ndarray:
    """Quotas in proportion to speed, edges dealt at random within them: no communication term."""
    try:
        quota = plan(fleet, len(block.a), len(block.ids))
    except Infeasible:
        quota = uniform(len(fleet), len(block.a), 1.0)
    slots = np.repeat(np.arange(len(fleet)), quota)[: len(block.a)]
    out = np.empty(len(block.a), np.int32)
    out[shuffled(block, seed)] = slots
    return out


def traffic_migration(block: Block, fleet: Fleet, seed: int = 1, rounds: int = 10, guard: bool = False) -> np.ndarray:
    """Placement by expected traffic of new replicas, then rounds in which every machine
    offers the edges that have an end alone there, for machines that hold both ends; offers
    that save most communication win, as long as no machine gets slower than the slowest."""
    s, com = Loads(block, fleet, guard), np.array(fleet.column("c_com"), float)
    traffic = np.diff(block.ptr) / max(1.0, np.diff(block.ptr).mean())
    edge = np.array(fleet.column("c_edge"), float)
    for e in shuffled(block, seed).tolist():
        a, b = block.a[e], block.b[e]
        new = ~s.held[a] * traffic[a] + ~s.held[b] * traffic[b]
        time = (s.edges + 1) * edge
        s.place(e, -(new * com / max(com.mean(), 1e-12) + time / max(time.mean(), 1e-12)))
    state = State(block, fleet, s.machine, np.arange(len(block.a)))
    ends = (block.a, block.b)
    for _ in range(rounds):
        held = state.count > 0
        n, all_ = held.sum(0), sum(c * h for c, h in zip(com, held, strict=True))
        m = state.machine
        saved = np.zeros(len(m))
        for v in ends:  # both sides of each link of a replica that would go
            saved += np.where(state.count[m, v] == 1, (n[v] - 2) * com[m] + all_[v], 0)
        best, to = np.full(len(m), np.inf), np.full(len(m), -1)
        for j, t in enumerate(state.t):
            here = held[j, block.a] & held[j, block.b] & (m != j) & (t < best)
            best[here], to[here] = t, j
        offers = np.flatnonzero((to >= 0) & (saved > 0))
        moved = 0
        for e in offers[np.argsort(-saved[offers], kind="stable")].tolist():
            i, j, a, b = int(state.machine[e]), int(to[e]), block.a[e], block.b[e]
            alone = state.count[i, a] == 1 or state.count[i, b] == 1
            if not alone or not state.count[j, a] or not state.count[j, b] or state.t[j] + edge[j] > state.t.max():
                continue
            if guard and not state.fits(e)[j]:
                continue
            state.remove(e)
            state.add(e, j)
            moved += 1
        if not moved:
            break
    return state.machine


def expansion(block: Block, fleet: Fleet, caps: list[int], seed: int = 1, guard: bool = True) -> np.ndarray:
    """Neighbour expansion: fewest new neighbours first, random starts, given capacities."""
    cfg = GrowthConfig(alpha=0.0, beta=0.0, seeds="random", seed=seed, memory_guard=guard)
    return grow_all(block, caps, fleet.column("mem"), cfg, m_node=fleet.m_node, m_edge=fleet.m_edge)[0]


#: Links of vertices to machines that are counted at once.
CELLS = 4_000_000


def multilevel_homes(block: Block, p: int, imbalance: float = 1.03, seed: int = 1) -> np.ndarray:
    """Vertex homes by heavy-edge matching, a greedy split of the coarsest graph by degree
    weights, and refinement by gain on the way back.

    A level is kept as what it merges its vertices to and where the block's vertices are in
    it; on the way back its edges are the block's own again, seen from there."""
    n = len(block.ids)
    degree = np.diff(block.ptr).astype(np.int64)
    levels, a, b, w = [], block.a, block.b, np.ones(len(block.a), np.int64)
    weight, at = degree, np.arange(n, dtype=np.int32)
    rng = np.random.default_rng(seed)
    limit = max(1.0, imbalance * weight.sum() / p)
    while n > 50 * p:
        # each vertex proposes to its heaviest neighbour; mutual proposals merge
        ends, other, ww = np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([w, w])
        ok = weight[ends] + weight[other] <= max(limit / 2, 2)
        ends, other, ww = ends[ok], other[ok], ww[ok]
        o = np.lexsort((rng.random(n)[other], -ww, ends))
        ends, other = ends[o], other[o]
        first = np.flatnonzero(np.diff(ends, prepend=-1))
        best = np.full(n, -1)
        best[ends[first]] = other[first]
        del ends, other, ww, ok, o
        mutual = (best >= 0) & (best[np.maximum(best, 0)] == np.arange(n))
        if mutual.sum() < 0.02 * n:
            break
        to = np.where(mutual, np.minimum(np.arange(n), best), np.arange(n))
        _, label = np.unique(to, return_inverse=True)
        label = label.astype(np.int32)
        levels.append((at, label))
        at, weight = label[at], np.bincount(label, weight).astype(np.int64)
        x, y = np.minimum(label[a], label[b]), np.maximum(label[a], label[b])
        keep = x != y
        n = len(weight)
        key, inv = np.unique(x[keep] * np.int64(n) + y[keep], return_inverse=True)
        a, b, w = key // n, key % n, np.bincount(inv, w[keep]).astype(np.int64)
        del x, y, keep, key, inv
    # coarse split: heaviest vertices first, to the part with most weight in common that has room
    home, load = np.full(n, -1), np.zeros(p)
    ends, other, ww = np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([w, w])
    o = np.argsort(ends, kind="stable")
    other, ww, ptr = other[o], ww[o], np.searchsorted(ends[o], np.arange(n + 1))
    heap = [(-int(x), v) for v, x in enumerate(weight)]
    heapq.heapify(heap)
    while heap:
        _, v = heapq.heappop(heap)
        near = other[ptr[v] : ptr[v + 1]]
        k = home[near] >= 0
        gain = np.bincount(home[near][k], ww[ptr[v] : ptr[v + 1]][k], p)
        room = load + weight[v] <= limit
        i = int(np.where(room, gain - load / limit, -np.inf).argmax()) if room.any() else int(load.argmin())
        home[v], load[i] = i, load[i] + weight[v]
    del a, b, w, ends, other, ww, o
    while levels:
        at, label = levels.pop()
        home, weight = home[label], np.bincount(at, degree).astype(np.int64)
        load = np.bincount(home, weight, p).astype(float)
        x, y = at[block.a], at[block.b]
        x, y = x[x != y], y[x != y]
        ends, other = np.concatenate([x, y]), np.concatenate([y, x])
        del x, y
        for _ in range(2):
            goal, gain = _goals(ends, other, home, p)
            for v in np.flatnonzero(gain > 0)[np.argsort(-gain[gain > 0], kind="stable")].tolist():
                if load[goal[v]] + weight[v] <= limit:
                    load[home[v]] -= weight[v]
                    home[v] = goal[v]
                    load[home[v]] += weight[v]
    return home


def _goals(ends: np.ndarray, other: np.ndarray, home: np.ndarray, p: int) -> tuple[np.ndarray, np.ndarray]:
    """For each vertex the machine where most of its neighbours are, and how many more they
    are there than at its home; a range of vertices at a time."""
    n, step = len(home), max(1, CELLS // p)
    goal, gain = np.zeros(n, np.int64), np.zeros(n, np.int64)
    for lo in range(0, n, step):
        hi = min(n, lo + step)
        mine = slice(None) if hi - lo == n else (ends >= lo) & (ends < hi)
        links = np.bincount((ends[mine] - np.int64(lo)) * p + home[other[mine]], minlength=(hi - lo) * p).reshape(hi - lo, p)
        row = np.arange(hi - lo)
        goal[lo:hi] = links.argmax(1)
        gain[lo:hi] = links[row, goal[lo:hi]] - links[row, home[lo:hi]]
    return goal, gain


def from_homes(block: Block, fleet: Fleet, homes: np.ndarray, seed: int = 1, guard: bool = True) -> np.ndarray:
    """Each edge to the home of one of its ends, at random while memory lasts."""
    s = Loads(block, fleet, guard)
    coin = np.random.default_rng(seed).random(len(block.a)) < 0.5
    for e in range(len(block.a)):
        a, b = (block.a[e], block.b[e]) if coin[e] else (block.b[e], block.a[e])
        score = np.zeros(len(fleet))
        score[homes[b]] = 1
        score[homes[a]] = 2
        s.place(e, score)
    return s.machine
