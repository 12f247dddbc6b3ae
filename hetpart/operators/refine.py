"""Costs kept up to date edge by edge, greedy repair and local search, in one task.

``State`` holds, for each machine and vertex, how many of the machine's edges touch it;
adding or removing an edge changes the costs of its ends' holders only.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np

from .capacity import Infeasible, plan
from .growth import Block, GrowthConfig, Seeds, _slices, grow_one
from .machines import Fleet


@dataclass(frozen=True)
class SearchConfig:
    gamma: float = 0.9
    theta: float = 0.01
    fails: int = 5  # failures in a row before a re-partition
    rounds: int = 9
    partners: int = 3  # machines that a re-partition pools
    objective: str = "superstep"  # or barrier_split
    time_limit_s: float | None = None


class State:
    def __init__(self, block: Block, fleet: Fleet, machine: np.ndarray, seq: np.ndarray):
        self.block, self.fleet, p = block, fleet, len(fleet)
        self.machine, self.seq = machine.copy(), seq.astype(np.int32 if len(machine) < 1 << 26 else np.int64)  # edges move a few times each at most
        self.com, self.node, self.edge, self.mem = (np.array(fleet.column(c), float) for c in ("c_com", "c_node", "c_edge", "mem"))
        most = int(np.diff(block.ptr).max(initial=0))
        self.count = np.zeros((p, len(block.ids)), np.min_scalar_type(most))  # of a byte where no vertex has more edges
        for lo, hi in _slices(len(machine)):
            self._tally(np.add, machine[lo:hi], slice(lo, hi))
        self.clock, self.repartitions = int(seq.max(initial=0)) + 1, 0
        self.recompute()

    def _tally(self, how: np.ufunc, machine: np.ndarray, edges) -> None:
        """Adds or subtracts edges on machines (-1: none) to or from the counts of their ends."""
        on = machine >= 0
        row, flat, one = machine[on].astype(np.int64) * self.count.shape[1], self.count.reshape(-1), self.count.dtype.type(1)
        for ends in (self.block.a, self.block.b):
            how.at(flat, row + ends[edges][on], one)

    def recompute(self) -> None:
        self.n_edges = np.bincount(self.machine[self.machine >= 0], minlength=len(self.fleet)).astype(float)
        n, all_ = np.zeros(self.count.shape[1]), np.zeros(self.count.shape[1])
        for i, c in enumerate(self.com):  # one machine's row at a time: no second matrix
            held = self.count[i] > 0
            n += held
            all_ += c * held
        self.n_vertices, self.t_com = np.zeros(len(self.com)), np.zeros(len(self.com))
        for i, c in enumerate(self.com):
            held = self.count[i] > 0
            self.n_vertices[i] = held.sum()
            self.t_com[i] = np.where(held & (n > 1), (n - 2) * c + all_, 0).sum()

    @property
    def t_cal(self) -> np.ndarray:
        return self.edge * self.n_edges + self.node * self.n_vertices

    @property
    def t(self) -> np.ndarray:
        return self.t_cal + self.t_com

    @property
    def used(self) -> np.ndarray:
        return self.fleet.m_edge * self.n_edges + self.fleet.m_node * self.n_vertices

    def goal(self, objective: str = "superstep") -> float:
        return float(self.t.max() if objective == "superstep" else self.t_cal.max() + self.t_com.max())

    def _hold(self, i: int, v: int, sign: int) -> None:
        others = np.flatnonzero(self.count[:, v] > 0)
        others = others[others != i]
        self.n_vertices[i] += sign
        if len(others):
            self.t_com[i] += sign * (len(others) * self.com[i] + self.com[others].sum())
            self.t_com[others] += sign * (self.com[i] + self.com[others])

    def add(self, e: int, i: int) -> None:
        for v in (self.block.a[e], self.block.b[e]):
            if self.count[i, v] == 0:
                self._hold(i, v, 1)
            self.count[i, v] += 1
        self.n_edges[i] += 1
        self.machine[e], self.seq[e] = i, self.clock
        self.clock += 1

    def remove(self, e: int) -> None:
        i = self.machine[e]
        for v in (self.block.a[e], self.block.b[e]):
            self.count[i, v] -= 1
            if self.count[i, v] == 0:
                self._hold(i, v, -1)
        self.n_edges[i] -= 1
        self.machine[e] = -1

    def fits(self, e: int) -> np.ndarray:
        new = (self.count[:, self.block.a[e]] == 0).astype(float) + (self.count[:, self.block.b[e]] == 0)
        return self.used + self.fleet.m_edge + self.fleet.m_node * new <= self.mem + 1e-9

    def choose(self, e: int, guard: bool = True) -> int:
        """Of the machines holding both ends, else one, else of all, the one with least time
        that has memory; -1 if none has."""
        a, b = self.count[:, self.block.a[e]] > 0, self.count[:, self.block.b[e]] > 0
        ok, t = self.fits(e) if guard else np.ones(len(self.mem), np.bool_), self.t
        for some in (a & b, a | b, np.ones(len(t), np.bool_)):
            which = np.flatnonzero(some & ok)
            if len(which):
                return int(which[t[which].argmin()])
        return -1

    def repair(self, edges, guard: bool = True, else_to: np.ndarray | None = None) -> None:
        """Places edges; those that no machine has memory for go to ``else_to`` or nowhere."""
        for k, e in enumerate(edges):
            i = self.choose(int(e), guard)
            if i < 0 and else_to is not None:
                i = int(else_to[k])
            if i >= 0:
                self.add(int(e), i)


def victims(t: np.ndarray, gamma: float) -> np.ndarray:
    return np.flatnonzero(t >= t.min() + gamma * (t.max() - t.min()) - 1e-9)


def destroy_and_repair(s: State, cfg: SearchConfig) -> bool:
    """Takes the newest edges of the slowest machines off and places them again."""
    before, lost = s.goal(cfg.objective), []
    for i in victims(s.t, cfg.gamma).tolist():
        own = np.flatnonzero(s.machine == i)
        n = min(len(own), int(np.ceil(cfg.theta * len(own))))
        lost += own[np.lexsort((own, s.seq[own]))[::-1][:n]].tolist()
    old = s.machine[lost].copy()
    for e in lost:
        s.remove(e)
    s.repair(lost, else_to=old)
    return s.goal(cfg.objective) < before - 1e-9


def repartition(s: State, cfg: SearchConfig, grow: GrowthConfig) -> None:
    """Pools the slowest machine with those that share most vertices with it; regrows them."""
    worst = int(s.t.argmax())
    own = s.count[worst] > 0
    shared = np.array([((c > 0) & own).sum() for c in s.count])
    shared[worst] = -1
    which = [worst, *np.lexsort((np.arange(len(shared)), -shared))[: max(0, cfg.partners - 1)].tolist()]
    pool = np.flatnonzero(np.isin(s.machine, which))
    if not len(pool):
        return
    part = Block(s.block.ids[s.block.a[pool]], s.block.ids[s.block.b[pool]])  # the pool is in (src, dst) order already
    fleet = s.fleet.subset(which)
    try:
        caps = plan(fleet, len(pool), len(part.ids))
    except Infeasible:
        return
    others = np.delete(np.arange(len(s.fleet)), which)
    at, border = np.searchsorted(s.block.ids, part.ids), np.zeros(len(part.ids), np.bool_)
    for i in others.tolist():
        border |= s.count[i][at] > 0
    seeds = Seeds(part, grow.seeds, grow.seed)
    new = np.full(len(pool), -1, np.int32)
    seq = np.zeros(len(pool), np.int64)
    for k, i in enumerate(which):
        e = grow_one(part, caps[k], border, seeds, grow, s.mem[i], s.fleet.m_node, s.fleet.m_edge)
        new[e], seq[e] = i, s.clock + np.arange(len(e))
    old = s.machine[pool].copy()
    on = new >= 0
    for lo, hi in _slices(len(pool)):
        s._tally(np.subtract, old[lo:hi], pool[lo:hi])
    for lo, hi in _slices(len(pool)):
        s._tally(np.add, new[lo:hi], pool[lo:hi])
    s.machine[pool], s.seq[pool] = new, seq
    s.clock = int(s.seq.max(initial=0)) + 1
    s.recompute()
    s.repair(pool[~on].tolist(), else_to=old[~on])


def local_search(s: State, cfg: SearchConfig, grow: GrowthConfig) -> tuple[np.ndarray, np.ndarray, float, list[float]]:
    """The best assignment ever seen, its cost, and the cost after each round."""
    best, machine, seq, fails, trace = s.goal(cfg.objective), s.machine.copy(), s.seq.copy(), 0, []
    began = time.monotonic()
    for _ in range(cfg.rounds):
        if cfg.time_limit_s is not None and time.monotonic() - began > cfg.time_limit_s:
            break
        fails = 0 if destroy_and_repair(s, cfg) else fails + 1
        if fails >= cfg.fails:
            repartition(s, cfg, grow)
            s.repartitions += 1
            fails = 0
        now = s.goal(cfg.objective)
        trace.append(now)
        if now < best - 1e-9 and (s.used <= s.mem + 1e-6).all():
            best, machine, seq = now, s.machine.copy(), s.seq.copy()
    return machine, seq, best, trace
