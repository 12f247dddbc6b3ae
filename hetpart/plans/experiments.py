"""Experiment workloads: parameter sweeps, ablation, comparisons, sizes, fleets.

A sweep is a small table of settings; each row is one run of a method on one graph. A run is
the method itself on the whole graph, in one task, whatever the graph's size. The size only
says how many runs go side by side and in how many ``blocks`` of edges a run is counted
again; neither changes a value. Edges never pass the driver. Each run's costs are counted
twice, as the search keeps them and by the definition, pair by pair (``agrees``)."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..operators import machines
from ..operators.growth import Block, GrowthConfig
from ..operators.machines import Fleet
from ..operators import partitioners
from ..operators.partitioners import BASELINES, PAPER_METHODS, Config, method
from ..operators.refine import SearchConfig, State
from ..operators.rounds import Filling, place_left
from ..session import cut, give_back
from ..sources import graphs
from . import oracle as O

QUERIES: dict = {}
SQL: dict[str, str] = {}
#: Edges that the runs of a sweep hold side by side (one run holds its graph, whatever its size),
#: and those of a block in which a run's costs are counted by the definition.
SWEEP_EDGES, BLOCK_EDGES = 24_000_000, 1_000_000
#: Vertices whose holders are compared at once.
HOLDERS = 1 << 16
#: Machines in one word of a vertex's holders.
WORD_BITS = 62
RESULT = "graph string, method string, parameter string, value double, tc double, rf double, balance double, t_cal double, t_com double, comm_share double, over_memory int, seconds double, edges_per_second double, n_edges long, agrees boolean, blocks int"
#: What the task of a run tells, for Spark and as its batches.
TOLD_AS = "tc double, rf double, balance double, t_cal double, t_com double, comm_share double, over_memory int, agrees boolean, seconds double, left long"
_ARROW = {"double": pa.float64(), "int": pa.int32(), "long": pa.int64(), "boolean": pa.bool_()}
TOLD = pa.schema([(c, _ARROW[t]) for c, t in (x.split() for x in TOLD_AS.split(", "))])


def query(name, sql=None):
    def put(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


def configured(parameter: str, value: float) -> Config:
    """The default configuration with one parameter changed."""
    g, s = {}, {}
    if parameter in ("alpha", "beta"):
        g[parameter] = value
    elif parameter in ("gamma", "theta"):
        s[parameter] = value
    elif parameter in ("fails", "rounds"):
        s[parameter] = int(value)
    elif parameter == "seed":
        g = {"seed": int(value), "seeds": "random"}
    return Config(growth=GrowthConfig(**g), search=SearchConfig(**s))


def measure(block: Block, fleet: Fleet, machine: np.ndarray) -> dict:
    s = State(block, fleet, machine, np.zeros(len(machine), np.int32))
    t = s.t
    return {"tc": s.goal(), "rf": float(s.n_vertices.sum() / len(block.ids)), "balance": float(s.n_edges.max() * len(fleet) / s.n_edges.sum()), "t_cal": float(s.t_cal.max()), "t_com": float(s.t_com.max()), "comm_share": float(s.t_com.sum() / t.sum()), "over_memory": int((s.used > s.mem + 1e-6).sum())}


def agrees(block: Block, fleet: Fleet, machine: np.ndarray, told: float, step: int = BLOCK_EDGES) -> bool:
    """Whether the slowest machine's time is what the definition gives: for each pair of
    machines both ends' cost for every vertex that both hold. Holders are bits of words, told
    by blocks of edges and compared by ranges of vertices."""
    p, n = len(fleet), len(block.ids)
    words, more, placed = np.zeros(-(-p // WORD_BITS) * n, np.int64), np.zeros(p), True
    for lo in range(0, len(machine), step):
        some = machine[lo : lo + step].astype(np.int64)
        on = some >= 0
        placed &= bool(on.all())
        some, more = some[on], more + np.bincount(some[on], minlength=p)
        for ends in (block.a, block.b):
            np.bitwise_or.at(words, some // WORD_BITS * n + ends[lo : lo + step][on], np.int64(1) << some % WORD_BITS)
    words, shared = words.reshape(-1, n), np.zeros((p, p))
    for lo in range(0, n, HOLDERS):
        held = np.stack([(words[i // WORD_BITS, lo : lo + HOLDERS] >> (i % WORD_BITS)) & 1 for i in range(p)]).astype(float)
        shared += held @ held.T
    held_by = np.diag(shared).copy()
    np.fill_diagonal(shared, 0)
    com = np.array(fleet.column("c_com"), float)
    t = more * np.array(fleet.column("c_edge")) + held_by * np.array(fleet.column("c_node")) + (shared * (com[:, None] + com[None])).sum(1)
    return bool(placed and abs(t.max() - told) <= 1e-6 * max(1.0, told))


def blocked(edges: DataFrame, n: int) -> tuple[DataFrame, int]:
    """(src, dst, block) in blocks of about BLOCK_EDGES edges, and their number: clusters of
    vertices; of a cluster that is larger, pieces by hash. No sweep takes this form."""
    part = edges.join(partitioners.clusters(edges, -(-n // BLOCK_EDGES)).withColumnRenamed("v", "src"), "src").select("src", "dst", "block")
    part = cut(part)
    pieces = part.groupBy("block").agg(F.count(F.lit(1)).alias("_n")).select("block", F.ceil(F.col("_n") / BLOCK_EDGES).alias("_pieces"))
    part = part.join(F.broadcast(pieces), "block")  # a row for each block
    part = cut(part.select("src", "dst", (F.col("block") * (1 << 20) + F.pmod(F.xxhash64("src", "dst"), "_pieces")).cast("long").alias("block")))
    return part, part.select("block").distinct().count()


def _words(machine: np.ndarray, v: np.ndarray, p: int) -> tuple[np.ndarray, list[np.ndarray]]:
    """Vertices and their machines as bits of words."""
    at, flat = np.unique(v, return_inverse=True)
    words = [np.zeros(len(at), np.int64) for _ in range(-(-p // WORD_BITS))]
    for i in np.unique(machine).tolist():
        held = np.zeros(len(at), np.bool_)
        held[flat[machine == i]] = True
        words[i // WORD_BITS] |= held.astype(np.int64) << (i % WORD_BITS)
    return at, words


def _held(edges: DataFrame, p: int) -> DataFrame:
    """(kind, v, n, w0...): kind 0 a vertex with its machines as bits, 1 the edges of machine
    v, of assigned edges in any grouping; kind 2 counts the edges without a machine."""
    n_words = -(-p // WORD_BITS)

    def run(batches):
        for b in batches:
            yield _told(b.column(0).to_numpy(), b.column(1).to_numpy(), b.column(2).to_numpy(), p)

    return edges.select("src", "dst", "machine").mapInArrow(run, "kind int, v long, n long" + "".join(f", w{k} long" for k in range(n_words)))


def _told(src: np.ndarray, dst: np.ndarray, machine: np.ndarray, p: int) -> pa.RecordBatch:
    on = machine >= 0
    at, words = _words(np.tile(machine[on], 2), np.concatenate([src[on], dst[on]]), p)
    more, none = np.bincount(machine[on], minlength=p), np.zeros(p + 1, np.int64)
    kind = np.concatenate([np.zeros(len(at), np.int32), np.ones(p, np.int32), np.full(1, 2, np.int32)])
    v = np.concatenate([at, np.arange(p), [0]])
    count = np.concatenate([np.zeros(len(at), np.int64), more, [(~on).sum()]])
    return pa.RecordBatch.from_arrays([pa.array(x) for x in (kind, v, count, *(np.concatenate([w, none]) for w in words))], names=["kind", "v", "n", *(f"w{k}" for k in range(len(words)))])


def _totals(rows: DataFrame, fleet: Fleet) -> dict:
    """Of rows as _held gives them: edges, vertices and communication of each machine by one
    pass over holders, the number of vertices that each pair of machines shares, all
    vertices, and the edges without a machine. p rows of p numbers a task reach the driver."""
    p, com = len(fleet), np.array(fleet.column("c_com"), float)
    words = [c for c in rows.columns if c.startswith("w")]
    one = rows.groupBy("kind", "v").agg(F.sum("n").alias("n"), *[F.bit_or(w).alias(w) for w in words])

    def run(batches):
        edges, held_by, talk, shared, vertices, left = np.zeros(p), np.zeros(p), np.zeros(p), np.zeros((p, p)), 0, 0
        for b in batches:
            kind, v, n = (b.column(k).to_numpy() for k in range(3))
            np.add.at(edges, v[kind == 1], n[kind == 1])
            left += int(n[kind == 2].sum())
            here = [b.column(3 + k).to_numpy()[kind == 0] for k in range(len(words))]
            held = np.stack([(here[i // WORD_BITS] >> (i % WORD_BITS)) & 1 for i in range(p)], 1).astype(float)
            vertices += len(held)
            shared += held.T @ held
            held_by += held.sum(0)
            holders, all_ = held.sum(1), held @ com
            talk += (held * np.where(holders > 1, 1, 0)[:, None] * ((holders - 2)[:, None] * com + all_[:, None])).sum(0)
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([edges, held_by, talk, shared.ravel(), [vertices, left]])[None].tolist())], names=["x"])

    x = np.sum([r["x"] for r in one.mapInArrow(run, "x array<double>").collect()], axis=0)
    return {"n_edges": x[:p], "n_vertices": x[p : 2 * p], "t_com": x[2 * p : 3 * p], "shared": x[3 * p : -2].reshape(p, p), "vertices": int(x[-2]), "left": int(x[-1])}


def _measured(x: dict, fleet: Fleet) -> dict:
    """The measures of a whole assignment out of its totals."""
    node, edge, com, mem = (np.array(fleet.column(c), float) for c in ("c_node", "c_edge", "c_com", "mem"))
    t_cal, t_com = edge * x["n_edges"] + node * x["n_vertices"], x["t_com"]
    t, pairs = t_cal + t_com, x["shared"] - np.diag(np.diag(x["shared"]))
    defined = t_cal + (pairs * (com[:, None] + com[None])).sum(1)
    told = float(t.max())
    used = fleet.m_edge * x["n_edges"] + fleet.m_node * x["n_vertices"]
    return {"tc": told, "rf": float(x["n_vertices"].sum() / x["vertices"]), "balance": float(x["n_edges"].max() * len(fleet) / x["n_edges"].sum()), "t_cal": float(t_cal.max()), "t_com": float(t_com.max()), "comm_share": float(t_com.sum() / t.sum()), "over_memory": int((used > mem + 1e-6).sum()), "agrees": bool(x["left"] == 0 and abs(defined.max() - told) <= 1e-6 * max(1.0, told))}


def _run(n: int, name: str, fleet: Fleet, cfg: Config, seed: int):
    """A method on a whole graph of n edges, which come in batches to one task: its measures
    with the number of edges that it found no memory for, or its assignment."""
    step = BLOCK_EDGES

    def placed(batches) -> tuple[Block, np.ndarray, float]:
        ends, at = [np.empty(n, np.int64), np.empty(n, np.int64)], 0
        for b in batches:
            for k in (0, 1):
                ends[k][at : at + b.num_rows] = b.column(k).to_numpy()
            at += b.num_rows
        assert at == n
        block = Block.taking(ends)
        began = time.perf_counter()
        machine, _ = method(name, fleet, cfg, seed)(block)
        return block, machine, time.perf_counter() - began

    def told(batches):
        block, machine, took = placed(batches)
        left = int((machine < 0).sum())
        row = measure(block, fleet, machine)
        row |= {"agrees": agrees(block, fleet, machine, row["tc"], step), "seconds": took, "left": left}
        del block, machine
        give_back()
        yield pa.RecordBatch.from_pylist([row], schema=TOLD)

    def assigned(batches):
        block, machine, _ = placed(batches)
        for lo in range(0, n, step):
            a, b, some = block.a[lo : lo + step], block.b[lo : lo + step], machine[lo : lo + step].astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (block.ids[a], block.ids[b], some, np.arange(lo, lo + len(some)))], names=["src", "dst", "machine", "seq"])

    return told, assigned


def _placed_after(whole: DataFrame, assigned, fleet: Fleet) -> dict:
    """The measures of a run after the edges without a machine went where memory is left;
    raises Infeasible where it is short."""
    all_ = cut(whole.mapInArrow(assigned, partitioners.SCHEMA))
    state = Filling(fleet, whole.sparkSession)
    state.take(all_.where("machine >= 0"))
    place_left(cut(all_.where("machine < 0").select("src", "dst")), state, 1 << 10)
    return _measured(_totals(_held(state.placed(), len(fleet)), fleet), fleet)


def sweep(edges: DataFrame, graph: str, runs: list[tuple[str, str, float]], fleet_of=None) -> DataFrame:
    """Runs (method, parameter, value) on one graph; fleet_of(edges, parameter, value)."""
    edges = cut(edges)
    n = edges.count()
    whole = edges.select("src", "dst").coalesce(1)

    def row(run: tuple[str, str, float]) -> tuple:
        name, p, v = run
        fleet = (fleet_of or (lambda k, p, v: machines.small(k).with_memory(1.5)))(n, p, v)
        told, assigned = _run(n, name, fleet, configured(p, v), int(v) if p == "seed" else 1)
        (r,) = (x.asDict() for x in whole.mapInArrow(told, TOLD_AS).collect())
        if r["left"]:
            began = time.perf_counter()
            r |= _placed_after(whole, assigned, fleet)
            r["seconds"] = time.perf_counter() - began
        r |= {"graph": graph, "method": name, "parameter": p, "value": float(v), "edges_per_second": n / r["seconds"], "n_edges": n, "blocks": -(-n // BLOCK_EDGES)}
        return tuple(r[f.name] for f in StructType.fromDDL(RESULT).fields)

    # a job for each run: a union of single partitions would be one task for all of them
    with ThreadPoolExecutor(max(1, min(len(runs), SWEEP_EDGES // max(1, n)))) as pool:
        rows = list(pool.map(row, runs if n else []))
    return edges.sparkSession.createDataFrame(rows, RESULT)


def _graph(s, d, g):
    return graphs.rmat(s, 10) if g == "rmat" else graphs.grid(s, 60, 50) if g == "grid" else graphs.GRAPHS[g](s, d)


def _count_sql(g: str) -> str:
    return f"select count(*) from ({O.rmat(10) if g == 'rmat' else O.grid(60, 50) if g == 'grid' else O.EDGES[g]})"


def _inv_sql(settings: list[tuple[str, list]]) -> str:
    """What must hold for runs (graph, runs) of methods within memory."""
    rows = [f"('{g}', '{m}', '{p}', {float(v)}::DOUBLE)" for g, runs in settings for m, p, v in runs]
    sizes = " union all ".join(f"select '{g}' as graph, ({_count_sql(g)})::BIGINT as n_edges" for g, _ in settings)
    return f"select t.graph, method, parameter, value, n_edges, true as agrees, 0::INTEGER as over_memory, true as bounded from (values {', '.join(rows)}) t(graph, method, parameter, value) join ({sizes}) c on c.graph = t.graph"


def _inv(r: DataFrame) -> DataFrame:
    """Runs as invariants: all edges placed, costs as defined, memory kept, and no replica or
    time below what the definitions allow."""
    bounded = (F.col("rf") >= 1) & (F.col("balance") >= 1) & (F.col("tc") >= F.greatest("t_cal", "t_com") - 1e-6) & (F.col("tc") <= F.col("t_cal") + F.col("t_com") + 1e-6)
    return r.select("graph", "method", "parameter", "value", "n_edges", "agrees", "over_memory", bounded.alias("bounded"))


def _sweep(g: str, runs, fleet_of=None):
    return lambda s, d: sweep(_graph(s, d, g), g, runs, fleet_of)


TENTHS = [k / 10 for k in range(10)]
SWEEPS = {
    "alpha": ("alpha", TENTHS),
    "beta": ("beta", TENTHS),
    "gamma": ("gamma", [k / 10 for k in range(11)]),
    "theta": ("theta", [k / 500 for k in range(1, 11)]),
    "n0": ("fails", list(range(1, 10))),
    "t0": ("rounds", list(range(1, 10))),
}
GUARDED = ("multilevel", "degree_aware_stream", "neighbor_expansion", "sorted_balance")
FIVE = ("full", *GUARDED)
_nine = lambda n, p, v: machines.nine(n)
_more = lambda n, p, v: machines.share_super(n, int(v)).with_memory(1.5)
_types = lambda n, p, v: machines.typed(n, int(v))


#: Where an experiment's name means a drawn graph, the measured values are those of a graph of
#: the given tables with the same nature: pages and their terms have hubs as R-MAT has, turns of
#: conversations are a mesh. What must hold (inv_exp) is checked on the drawn graphs.
GIVEN = {"rmat": "g10", "grid": "g13"}


def _put(name: str, g: str, runs: list, fleet_of=None, *, guarded: bool = True) -> None:
    """The experiment, and beside it what must hold for its runs, checked by SQL."""
    query(f"exp_{name}")(_sweep(GIVEN.get(g, g), runs, fleet_of))
    if guarded:
        query(f"inv_exp_{name}", _inv_sql([(g, runs)]))(lambda s, d: _inv(sweep(_graph(s, d, g), g, runs, fleet_of)))


for _name, (_p, _values) in SWEEPS.items():
    for _g in ("g1", "g4", "g5", "g6", "g9", "rmat"):
        _put(f"{_name}_{_g}", _g, [("full", _p, v) for v in _values], guarded=_g in ("g4", "g9", "rmat"))
for _g in ("g1", "g2", "g3", "g4", "g5", "g6", "g9", "grid", "rmat"):
    _put(f"ablation_{_g}", _g, [(m, "none", 0.0) for m in PAPER_METHODS])
    _put(f"compare_{_g}", _g, [(m, "none", 0.0) for m in FIVE])
for _g in ("g1", "g2", "g3", "g4", "g5", "g6", "g9", "rmat"):
    _put(f"hetero_{_g}", _g, [(m, "none", 0.0) for m in ("full", *BASELINES[4:])], _nine, guarded=False)
    _put(f"nine_{_g}", _g, [(m, "none", 0.0) for m in FIVE], _nine)
_put("homogeneous", "g4", [(m, "none", 0.0) for m in FIVE], lambda n, p, v: machines.homogeneous(n))
_put("machines", "g4", [(m, "machines", v) for m in ("full", "neighbor_expansion", "sorted_balance") for v in (30, 45, 60, 75, 90)], _more)
_put("types", "g4", [(m, "types", v) for m in ("full", "neighbor_expansion", "sorted_balance") for v in range(1, 7)], _types)
_put("seeds", "g4", [("full", "seed", v) for v in range(1, 11)])


@query("exp_repeat")
def exp_repeat(s, d):
    """Ten seeded runs of each method that has a seed: mean and spread."""
    runs = [(m, "seed", v) for m in ("full", "degree_aware_stream", "neighbor_expansion") for v in range(1, 11)]
    r = sweep(_graph(s, d, "g4"), "g4", runs)
    return r.groupBy("graph", "method").agg(F.count(F.lit(1)).alias("runs"), F.avg("tc").alias("tc_mean"), F.stddev("tc").alias("tc_stddev"), F.avg("seconds").alias("seconds_mean"))


@query("exp_seconds")
def exp_seconds(s, d):
    """Partitioning time and throughput of every method."""
    out = None
    for g in ("g1", "g3", "g4", "g5"):
        r = sweep(_graph(s, d, g), g, [(m, "none", 0.0) for m in (*PAPER_METHODS, *BASELINES)])
        out = r if out is None else out.unionByName(r)
    return out.select("graph", "method", "n_edges", "seconds", "edges_per_second")


@query("exp_gains")
def exp_gains(s, d):
    """Gain of each step of the method over the one before, by graph."""
    out = None
    for g in ("g1", "g4", "g6", "g9", "rmat"):
        r = sweep(_graph(s, d, g), g, [(m, "none", 0.0) for m in PAPER_METHODS])
        out = r if out is None else out.unionByName(r)
    t = out.groupBy("graph").pivot("method", list(PAPER_METHODS)).agg(F.first("tc"))
    return t.select("graph", (F.col("naive") / F.col("star")).alias("capacity_gain"), (F.col("star") / F.col("plus")).alias("best_first_gain"), (F.col("plus") / F.col("full")).alias("search_gain"))


def _weighted(s, d, g):
    """A graph's edges with the arithmetic weights of the distance workload."""
    return _graph(s, d, g).withColumn("weight", (F.col("src") * 31 + F.col("dst") * 17) % 97 + 1)


def _wedges(e: DataFrame) -> DataFrame:
    """Triangle counting in two steps, as vertices are active in it: all send their lists,
    then those that have two neighbours or more look for the third edge."""
    deg = graphs.degrees(e)
    return deg.select(F.lit(1).alias("step"), "v").unionByName(deg.where("degree > 1").select(F.lit(2).alias("step"), "v"))


def workload_times(s, d, g: str, fleet, methods: tuple[str, ...]) -> DataFrame:
    """Simulated time of PageRank (ten dense steps), triangles, breadth-first levels and
    distances, from which vertices are active in which step, beside TC."""
    from ..operators import algos, bsp, costs
    from ..session import cut

    e = cut(_graph(s, d, g))
    n = e.count()
    f, start, steps = fleet(n), e.agg(F.min("src")).first()[0], []
    levels = cut(algos.bfs(e, start))
    algos.sssp(_weighted(s, d, g), start, steps)
    active = steps[0]
    for x in steps[1:]:
        active = active.unionByName(x)
    work = {"triangles": _wedges(e), "bfs": bsp.level_activity(levels), "sssp": cut(active)}
    rows = []
    for m in methods:
        a = cut(partitioners.kernel(e, method(m, f)))
        tc = float(costs.total(a, f).first()[0])
        dense = bsp.simulate(a, f, bsp.dense_activity(a, 1)).agg(F.sum("t")).first()[0]
        split = bsp.simulate(a, f, bsp.dense_activity(a, 1), "barrier_split").agg(F.sum("t")).first()[0]
        rest = [float(bsp.simulate(a, f, x).agg(F.sum("t")).first()[0]) for x in work.values()]
        rows.append((g, m, n, tc, 10 * float(dense), 10 * float(split), *rest))
    return s.createDataFrame(rows, "graph string, method string, n_edges long, tc double, pagerank double, pagerank_mapreduce double, triangles double, bfs double, sssp double")


HETERO = ("full", *BASELINES[4:])
for _g in ("g1", "g3", "g4", "g5", "g6", "g9"):
    query(f"exp_times_hetero_{_g}")(lambda s, d, g=_g: workload_times(s, d, g, machines.nine, HETERO if g == "g4" else HETERO[:3]))
for _g in ("g1", "g4", "g9"):
    query(f"exp_times_{_g}")(lambda s, d, g=_g: workload_times(s, d, g, machines.nine, ("full", "degree_aware_stream", "neighbor_expansion", "sorted_balance")))
query("exp_times_homogeneous")(lambda s, d: workload_times(s, d, "g4", machines.homogeneous, FIVE))


@query("exp_rmat")
def exp_rmat(s, d, scales=tuple(range(8, 15))):
    """Sizes doubling; the slope of ln TC over the scale follows from the rows."""
    out = None
    for scale in scales:
        part = sweep(graphs.rmat(s, scale), f"rmat{scale}", [(m, "scale", float(scale)) for m in FIVE])
        out = part if out is None else out.unionByName(part)
    return out


@query("exp_slope")
def exp_slope(s, d):
    r = exp_rmat(s, d, (7, 8, 9, 10, 11))
    return r.groupBy("method").agg(F.regr_slope(F.ln("tc"), "value").alias("slope"), F.exp(F.regr_slope(F.ln("tc"), "value")).alias("growth_per_doubling"))


@query("exp_histogram")
def exp_histogram(s, d):
    """Time of each machine, computing and talking, for the four variants on three graphs."""
    from ..operators import costs
    from .core import run_method

    out = None
    for g in ("g4", "g5", "g9"):
        for m in PAPER_METHODS:
            a, _, f = run_method(s, d, g, m)
            c = costs.costs(a, f).select(F.lit(g).alias("graph"), F.lit(m).alias("method"), "machine", "t_cal", "t_com", "t")
            out = c if out is None else out.unionByName(c)
    return out


@query("exp_tc_vs_time")
def exp_tc_vs_time(s, d):
    """TC beside simulated times of four workloads for three methods on two graphs: how far
    each ratio of times is from the ratio of TC (against the first method)."""
    out = None
    for g in ("g1", "g4"):
        r = workload_times(s, d, g, lambda n: machines.small(n).with_memory(1.5), ("degree_aware_stream", "neighbor_expansion", "full"))
        out = r if out is None else out.unionByName(r)
    first = out.where("method = 'degree_aware_stream'")
    base = first.select("graph", *[F.col(c).alias(f"{c}_0") for c in ("tc", "pagerank", "triangles", "bfs", "sssp")])
    off = lambda c: ((F.col(c) / F.col(f"{c}_0")) / (F.col("tc") / F.col("tc_0")) - 1).alias(f"{c}_error")
    return out.join(F.broadcast(base), "graph").select("graph", "method", "tc", "pagerank", "triangles", "bfs", "sssp", *[off(c) for c in ("pagerank", "triangles", "bfs", "sssp")])


GAPS = "exact boolean, near boolean"


def _gaps(batches):
    """Whether plans are exact, and within five percent, for fleets of a few machines."""
    from ..operators import capacity

    for b in batches:
        exact, near = [], []
        for fleet, orders in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            cost, cap = [m["cost"] for m in fleet], [m["cap"] for m in fleet]
            edges = min(sum(cap), 8 + orders % 20)
            best = max(c * x for c, x in zip(cost, capacity.branch_and_bound(cost, cap, edges), strict=True))
            got = max(c * x for c, x in zip(cost, capacity.whole(cost, cap, capacity.rounds(cost, cap, edges), edges), strict=True))
            exact.append(abs(best - capacity.exact_level(cost, cap, edges)) < 1e-9)
            near.append(got <= 1.05 * best + 1e-9)
        yield pa.RecordBatch.from_arrays([pa.array(exact, pa.bool_()), pa.array(near, pa.bool_())], names=["exact", "near"])


@query("exp_gap", "select true as plan_is_exact, true as within_five_percent")
def exp_gap(s, d):
    """Capacity plans against branch and bound on fleets of three for graphs of a few edges:
    three customers in a row are machines, with cost by nation and memory by balance, and
    their number of orders gives the edges."""
    c, o = graphs.read(s, d, "customer"), graphs.read(s, d, "orders")
    three = lambda k: F.floor(F.col(k) / 3).alias("fleet")
    cost = (1 + F.pmod(F.coalesce("c_nationkey", F.lit(0)), F.lit(5))).cast("long").alias("cost")
    cap = (5 + F.pmod(F.floor(F.coalesce("c_acctbal", F.lit(0.0))), F.lit(25))).cast("long").alias("cap")
    fleets = c.groupBy(three("c_custkey")).agg(F.sort_array(F.collect_list(F.struct("c_custkey", cost, cap))).alias("machines"))
    orders = o.groupBy(three("o_custkey")).agg(F.count(F.lit(1)).alias("orders"))
    tried = fleets.join(orders, "fleet", "left").select("machines", F.coalesce("orders", F.lit(0)).alias("orders")).mapInArrow(_gaps, GAPS)
    return tried.agg(F.coalesce(F.bool_and("exact"), F.lit(True)).alias("plan_is_exact"), F.coalesce(F.bool_and("near"), F.lit(True)).alias("within_five_percent"))
