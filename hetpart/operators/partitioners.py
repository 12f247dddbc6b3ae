"""Complete methods on edge DataFrames: (src, dst) in, (src, dst, machine, seq) out.

``kernel`` runs a method exactly, in one task for each block, and raises where memory is
short. ``two_level`` is another algorithm, for graphs beyond one task: vertices are dealt
to blocks by cluster, each block is partitioned in its own task, blocks share each
machine's memory by their size, and edges that a block can't place are placed in rounds
under the memory that all blocks left. ``partition`` never changes from one to the other
by itself.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut
from ..sources.graphs import stats
from . import streams
from .capacity import Infeasible, memory_only, plan, uniform
from .growth import Block, GrowthConfig, grow_all
from .machines import Fleet
from .refine import SearchConfig, State, local_search

SCHEMA = "src long, dst long, machine int, seq long"
#: Edges that one task partitions exactly, and bytes of its table of machines and vertices.
KERNEL_EDGES, KERNEL_BYTES = 20_000_000, 1_000_000_000


@dataclass(frozen=True)
class Config:
    steps: tuple[str, ...] = ("capacity", "best_first", "refine")
    growth: GrowthConfig = field(default_factory=GrowthConfig)
    search: SearchConfig = field(default_factory=SearchConfig)
    balance: float = 1.1
    remainder: str = "greedy"
    machine_order: str = "given"  # or capacity, network


def served_order(fleet: Fleet, caps: list[int], how: str = "given") -> list[int]:
    if how == "capacity":
        return sorted(range(len(fleet)), key=lambda i: (-caps[i], i))
    if how == "network":
        return sorted(range(len(fleet)), key=lambda i: (fleet.machines[i].c_com, i))
    return list(range(len(fleet)))


def three_phase(block: Block, fleet: Fleet, cfg: Config, trace: list | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Capacities, growth and local search, as far as cfg.steps says."""
    edges, vertices = len(block.a), len(block.ids)
    if "capacity" in cfg.steps:
        caps = plan(fleet, edges, vertices, cfg.remainder)
    else:
        caps = [min(a, b) for a, b in zip(uniform(len(fleet), edges, cfg.balance), memory_only(fleet, edges, vertices), strict=True)]
    growth = cfg.growth if "best_first" in cfg.steps else GrowthConfig(0.0, 0.0, cfg.growth.order, cfg.growth.seeds, cfg.growth.seed, cfg.growth.memory_guard)
    machine, seq = grow_all(block, caps, fleet.column("mem"), growth, served_order(fleet, caps, cfg.machine_order), fleet.m_node, fleet.m_edge)
    left = np.flatnonzero(machine < 0).tolist()
    state = State(block, fleet, machine, seq)
    del machine, seq  # the state has its own
    state.repair(left)
    if "refine" not in cfg.steps:
        return state.machine, state.seq
    machine, seq, _, costs = local_search(state, cfg.search, cfg.growth)
    if trace is not None:
        trace += costs
    return machine, seq


def _seq(machine: np.ndarray) -> np.ndarray:
    return np.arange(len(machine), dtype=np.int64)


def method(name: str, fleet: Fleet, cfg: Config | None = None, seed: int = 1) -> Callable[[Block], tuple[np.ndarray, np.ndarray]]:
    """A method by name, as a function of a block."""
    cfg = cfg or Config()
    steps = {"full": cfg.steps, "plus": ("capacity", "best_first"), "star": ("capacity",), "naive": ()}
    if name in steps:
        own = replace(cfg, steps=steps[name])
        return lambda b: three_phase(b, fleet, own)

    def speed_caps(b: Block) -> list[int]:
        cost = np.array([m.c_edge + m.c_node * len(b.ids) / len(b.a) for m in fleet.machines])
        share = len(b.a) / cost / (1 / cost).sum()
        return np.ceil(share).astype(int).tolist()

    def settled(b: Block, machine: np.ndarray, guard: bool) -> np.ndarray:
        state = State(b, fleet, machine, np.zeros(len(machine), np.int64))
        state.repair(np.flatnonzero(machine < 0).tolist(), guard)
        return state.machine

    plain = {
        "degree_aware_stream": lambda b: streams.degree_aware(b, fleet, seed),
        "sorted_balance": lambda b: streams.sorted_balance(b, fleet),
        "neighbor_expansion": lambda b: settled(b, streams.expansion(b, fleet, uniform(len(fleet), len(b.a), cfg.balance), seed), True),
        "multilevel": lambda b: streams.from_homes(b, fleet, streams.multilevel_homes(b, len(fleet), seed=seed), seed),
        "load_only": lambda b: streams.load_only(b, fleet, seed),
        "traffic_migration": lambda b: streams.traffic_migration(b, fleet, seed),
        "hetero_stream": lambda b: streams.hetero_stream(b, fleet, seed),
        "hetero_expansion": lambda b: settled(b, streams.expansion(b, fleet, speed_caps(b), seed, guard=False), False),
    }
    return lambda b: (m := plain[name](b), _seq(m))


PAPER_METHODS = ("full", "plus", "star", "naive")
BASELINES = ("multilevel", "degree_aware_stream", "neighbor_expansion", "sorted_balance", "load_only", "traffic_migration", "hetero_stream", "hetero_expansion")


def kernel(edges: DataFrame, run: Callable[[Block], tuple[np.ndarray, np.ndarray]], limit: int = KERNEL_EDGES, direction: str = "both", machines: int = 30) -> DataFrame:
    """Runs a method over all edges in one task; refuses more edges, or more machines times
    vertices, than one task takes. With a direction, src -> dst are arcs and growth follows
    them ('out') or goes against them ('in')."""
    n, v = graph_size(edges)
    if n > limit or 4 * v * machines > KERNEL_BYTES:
        raise ValueError(f"{n} edges and {v} vertices; one task takes {limit} edges and {KERNEL_BYTES // (4 * machines)} vertices. Use mode='two_level' or rounds.best_first_parallel()")
    return edges.withColumn("_b", F.lit(0)).groupBy("_b").applyInArrow(lambda t: _apply(t, run, direction), SCHEMA)


def _apply(t: pa.Table, run, direction: str) -> pa.Table:
    b = Block(t.column("src").to_numpy(), t.column("dst").to_numpy(), direction)
    machine, seq = run(b)
    if (machine < 0).any():
        raise Infeasible(f"{int((machine < 0).sum())} edges find no machine with memory")
    return pa.Table.from_arrays([pa.array(b.src), pa.array(b.dst), pa.array(machine.astype(np.int32)), pa.array(seq.astype(np.int64))], names=["src", "dst", "machine", "seq"])


def clusters(edges: DataFrame, blocks: int, rounds: int = 3) -> DataFrame:
    """(v, block): a few rounds in which each vertex takes the most frequent label of its
    neighbours, then labels dealt to blocks by hash. Hubs only send counts."""
    from ..sources.graphs import both_ways

    arcs = cut(both_ways(edges))
    label = cut(arcs.groupBy("v").agg(F.min("u").alias("label")))
    for _ in range(rounds):
        votes = arcs.join(label.withColumnRenamed("v", "u"), "u").groupBy("v", "label").agg(F.count(F.lit(1)).alias("n"))
        label = cut(votes.groupBy("v").agg(F.max_by("label", F.struct("n", "label")).alias("label")))
    # a label that holds more than half a block's share of the vertices is dealt by vertex
    sizes = label.groupBy("label").agg(F.count(F.lit(1)).alias("n"))
    total = label.count()
    large = F.broadcast(sizes.where(F.col("n") > max(1, total // (2 * blocks))).select("label", F.lit(True).alias("large")))  # 2 * blocks rows at most
    split = label.join(large, "label", "left")
    return split.select("v", F.pmod(F.when(F.col("large"), F.xxhash64("v")).otherwise(F.xxhash64("label")), F.lit(blocks)).cast("int").alias("block"))


def two_level(edges: DataFrame, fleet: Fleet, name: str = "full", cfg: Config | None = None, blocks: int = 8, seed: int = 1) -> DataFrame:
    """Blocks of clustered vertices, each partitioned in its own task for all machines with
    memory and capacity in proportion to the block's edges. What a block can't place goes,
    in rounds, where the blocks together left memory; raises Infeasible if that is short."""
    home = clusters(edges, blocks)
    part = cut(edges.join(home.withColumnRenamed("v", "src"), "src").select("src", "dst", "block"))
    n = part.count()
    largest = part.groupBy("block").count().agg(F.max("count")).first()[0]
    if largest and largest > KERNEL_EDGES:
        raise ValueError(f"a block has {largest} edges; one task takes {KERNEL_EDGES}. Use more blocks")

    def run(t: pa.Table) -> pa.Table:
        share = t.num_rows / n
        own = replace(fleet, machines=tuple(replace(m, mem=m.mem * share) for m in fleet.machines))
        b = Block(t.column("src").to_numpy(), t.column("dst").to_numpy())
        try:
            machine, seq = method(name, own, cfg, seed)(b)
        except Infeasible:
            machine, seq = np.full(len(b.src), -1, np.int32), np.zeros(len(b.src), np.int64)
        return pa.Table.from_arrays([pa.array(b.src), pa.array(b.dst), pa.array(machine.astype(np.int32)), pa.array(seq.astype(np.int64))], names=["src", "dst", "machine", "seq"])

    from .rounds import Filling, place_left

    out = cut(part.groupBy("block").applyInArrow(run, SCHEMA))
    left = out.where("machine < 0").select("src", "dst")
    if left.isEmpty():
        return out
    state = Filling(fleet, edges.sparkSession)
    state.take(out.where("machine >= 0"))
    place_left(cut(left), state, 1 << 10)
    return state.placed()


def partition(edges: DataFrame, fleet: Fleet, name: str = "full", cfg: Config | None = None, mode: str = "auto", blocks: int | None = None, seed: int = 1) -> DataFrame:
    """Any method on any graph: mode 'sequential' is exact, in one task, and refuses graphs
    beyond it; 'two_level' is the form for those, 'parallel' the growth by rounds (of the
    method itself, not the comparators) with batched local search. 'auto' is 'sequential'."""
    if mode in ("auto", "sequential"):
        return kernel(edges, method(name, fleet, cfg, seed), machines=len(fleet))
    if mode == "two_level":
        n = edges.count()
        return two_level(edges, fleet, name, cfg, blocks or max(2, -(-2 * n // KERNEL_EDGES)), seed)
    if mode == "parallel" and name in ("full", "plus"):
        from .rounds import best_first_parallel, refine_rounds

        cfg = cfg or Config()
        grown = best_first_parallel(edges, fleet, cfg.growth.alpha, cfg.growth.beta)
        s = cfg.search
        return grown if name == "plus" else refine_rounds(grown, fleet, s.gamma, s.theta, s.rounds, s.fails, s.partners)
    raise ValueError(f"no mode {mode} for {name}")


def hash_placement(edges: DataFrame, p: int) -> DataFrame:
    from ..functions.columns import hash_machine

    return edges.select("src", "dst", hash_machine(F.col("src"), F.col("dst"), p).alias("machine"))


def graph_size(edges: DataFrame) -> tuple[int, int]:
    r = stats(edges).first()
    return int(r["n_edges"]), int(r["n_vertices"])
