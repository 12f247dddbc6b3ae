"""Edge capacities: how many edges each machine should hold so that the slowest computes
as briefly as possible. All state is p rows, so plans are made on the driver; the SQL
form of the closed solution is ``waterfill``."""

from __future__ import annotations

import itertools
import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .machines import Fleet


class Infeasible(ValueError):
    """The machines' memory can't hold all edges."""


def terms(fleet: Fleet, edges: int, vertices: int, ratios: list[float] | None = None) -> tuple[list[float], list[float]]:
    """Cost of an edge with its share of vertices, and the edges that memory allows.
    ratios: vertices an edge by machine, where they are known."""
    r = ratios or [vertices / edges] * len(fleet)
    cost = [m.c_edge + x * m.c_node for m, x in zip(fleet.machines, r, strict=True)]
    cap = [m.mem / (fleet.m_edge + fleet.m_node * x) for m, x in zip(fleet.machines, r, strict=True)]
    return cost, cap


def terms_df(fleet: Fleet, spark, edges: int, vertices: int) -> DataFrame:
    cost, cap = terms(fleet, edges, vertices)
    return spark.createDataFrame([(i, c, k) for i, (c, k) in enumerate(zip(cost, cap, strict=True))], "machine int, cost double, cap double")


def waterfill(t: DataFrame, edges: int) -> DataFrame:
    """Real-valued optimum over (machine, cost, cap), as one relational plan.

    Machines in ascending order of the time their full memory takes: the first ones are
    full, the others share the rest in inverse proportion to cost. The common level is
    that of the first machine which the shared level doesn't overflow."""
    w = Window.orderBy(F.col("cost") * F.col("cap"), "machine")
    s = t.withColumn("full", F.coalesce(F.sum("cap").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))).withColumn("speed", F.sum(1 / F.col("cost")).over(w.rowsBetween(0, Window.unboundedFollowing)))
    level = s.withColumn("level", (edges - F.col("full")) / F.col("speed")).where(F.col("level") <= F.col("cost") * F.col("cap") * (1 + 1e-12)).agg(F.min_by("level", F.struct(F.col("cost") * F.col("cap"), "machine")).alias("level"))
    return t.crossJoin(F.broadcast(level)).select("machine", F.least("cap", F.col("level") / F.col("cost")).alias("amount"), "level")


def rounds(cost: list[float], cap: list[float], edges: float) -> list[float]:
    """The same by rounds: share what is left in inverse proportion to cost, freeze the
    machines that overflow at their memory, and share again."""
    if sum(cap) < edges:
        raise Infeasible(f"{edges} edges, memory for {sum(cap):.0f}")
    out, open_, left = [0.0] * len(cost), set(range(len(cost))), float(edges)
    while open_:
        speed = sum(1 / cost[i] for i in open_)
        over = [i for i in open_ if left / speed / cost[i] > cap[i]]
        if not over:
            for i in open_:
                out[i] = left / speed / cost[i]
            return out
        for i in over:
            out[i] = cap[i]
            left -= cap[i]
            open_.discard(i)
    return out


def whole(cost: list[float], cap: list[float], amounts: list[float], edges: int, remainder: str = "greedy") -> list[int]:
    """Integers from the real optimum. What rounding down leaves goes, edge by edge, to the
    machine that then takes least time ('greedy'), or to the last that has room ('last')."""
    limit = [math.floor(c + 1e-9) for c in cap]
    out = [min(math.floor(a + 1e-9), k) for a, k in zip(amounts, limit, strict=True)]
    left = edges - sum(out)
    if remainder == "none":
        return out
    while left > 0:
        room = [i for i in range(len(out)) if out[i] < limit[i]]
        if not room:
            raise Infeasible(f"{left} edges left without memory")
        if remainder == "last":
            take = min(left, limit[room[-1]] - out[room[-1]])
            out[room[-1]] += take
        else:
            take = 1
            out[min(room, key=lambda i: (cost[i] * (out[i] + 1), i))] += 1
        left -= take
    return out


def plan(fleet: Fleet, edges: int, vertices: int, remainder: str = "greedy", ratios: list[float] | None = None) -> list[int]:
    """Integer capacities of a fleet for a graph."""
    if edges == 0:
        return [0] * len(fleet)
    cost, cap = terms(fleet, edges, vertices, ratios)
    return whole(cost, cap, rounds(cost, cap, edges), edges, remainder)


def exact_level(cost: list[float], cap: list[float], edges: int) -> float:
    """Least time in which integer capacities can hold all edges, by bisection over the
    levels at which some machine takes one edge more."""
    limit = [math.floor(c + 1e-9) for c in cap]
    if sum(limit) < edges:
        raise Infeasible(f"{edges} edges, memory for {sum(limit)}")
    fits = lambda t: sum(min(k, math.floor(t / c * (1 + 1e-12))) for c, k in zip(cost, limit, strict=True)) >= edges
    lo, hi = 0.0, max(c * k for c, k in zip(cost, limit, strict=True))
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (lo, mid) if fits(mid) else (mid, hi)
    return max(c * min(k, math.floor(hi / c * (1 + 1e-12))) for c, k in zip(cost, limit, strict=True))


def branch_and_bound(cost: list[float], cap: list[float], edges: int) -> list[int]:
    """Independent exact answer for a handful of machines and edges."""
    best: tuple[float, list[int]] = (math.inf, [])

    def go(i: int, left: int, worst: float, chosen: list[int]) -> None:
        nonlocal best
        if worst >= best[0]:
            return
        if i == len(cost) - 1:
            if left <= cap[i] + 1e-9:
                best = min(best, (max(worst, cost[i] * left), [*chosen, left]))
            return
        for x in range(min(left, math.floor(cap[i] + 1e-9)) + 1):
            go(i + 1, left - x, max(worst, cost[i] * x), [*chosen, x])

    go(0, edges, 0.0, [])
    if not best[1]:
        raise Infeasible(f"{edges} edges")
    return best[1]


def uniform(p: int, edges: int, alpha: float = 1.1) -> list[int]:
    return [math.ceil(alpha * edges / p)] * p


def memory_only(fleet: Fleet, edges: int, vertices: int) -> list[int]:
    return [math.floor(c) for c in terms(fleet, edges, vertices)[1]]


def gap(cost: list[float], cap: list[float], edges: int) -> tuple[float, float]:
    """Relative excess of the planned integers over the exact level, and the bound p * p / E."""
    got = max(c * x for c, x in zip(cost, whole(cost, cap, rounds(cost, cap, edges), edges), strict=True))
    return got / exact_level(cost, cap, edges) - 1, len(cost) ** 2 / edges


def all_plans(p: int, edges: int):
    """Every way to give edges to p machines; for tests."""
    return (x for x in itertools.product(range(edges + 1), repeat=p) if sum(x) == edges)
