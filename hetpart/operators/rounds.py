"""Local search and growth as DataFrame rounds, for graphs beyond one task.

What a machine holds is known on the driver as p rows; edges, frontiers and holders stay
distributed. Memory is kept in every round: a machine takes at most as many new edges as
fit if both ends of each were new to it, and what it really holds is counted after the
round, so the room that is left is used in the next one."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import priority
from ..session import cut
from ..sources.graphs import both_ways, degrees, stats
from .capacity import Infeasible, plan
from .costs import costs, overlap, replicas
from .machines import Fleet


def frontier_scores(edges: DataFrame, covered: DataFrame, border: DataFrame, alpha: float = 0.3, beta: float = 0.3) -> DataFrame:
    """v, outside, degree, w: priority of every covered vertex; covered: v; border: v."""
    arcs = both_ways(edges)
    near = arcs.join(covered.select("v"), "v").join(covered.select(F.col("v").alias("u"), F.lit(1).alias("inner")), "u", "left")
    n = near.groupBy("v").agg(F.sum(F.col("inner").isNull().cast("long")).alias("outside"), F.count(F.lit(1)).alias("degree"))
    n = n.join(border.select("v", F.lit(True).alias("b")), "v", "left")
    return n.select("v", "outside", "degree", priority(F.col("outside"), F.col("degree"), F.coalesce("b", F.lit(False)), alpha, beta).alias("w"))


def by_machine(values: list, kind: str = "double") -> Column:
    """A machine's value out of a list."""
    return F.get(F.array(*[F.lit(x).cast(kind) for x in values]), F.col("machine"))


def quota_rank(rows: DataFrame, key: str, order: Column, band: Column | None = None) -> DataFrame:
    """Adds rank within key by (band, order) in two steps: ranks within bands, plus the sizes
    of the bands before; no key is one task. Without a band, order is a 64-bit hash and its
    leading bits are the band."""
    r = rows.withColumn("_o", order)
    r = r.withColumn("_band", (F.shiftright(F.col("_o"), 58) if band is None else band).cast("long"))
    sizes = r.groupBy(key, "_band").agg(F.count(F.lit(1)).alias("_n"))
    before = sizes.withColumn("_before", F.coalesce(F.sum("_n").over(Window.partitionBy(key).orderBy("_band").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("_n")
    inner = F.row_number().over(Window.partitionBy(key, "_band").orderBy("_o"))
    return r.withColumn("_r", inner).join(before, [key, "_band"]).withColumn("rank", F.col("_r") + F.col("_before")).drop("_o", "_band", "_r", "_before")


def compact(df: DataFrame) -> DataFrame:
    """A union's partitions brought down to the session's number: unions of many rounds
    would give a task for each round's partitions."""
    return df.coalesce(max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))))


class Filling:
    """What the machines hold while edges are placed: counts on the driver, holders (v,
    machine) and placed edges as DataFrames."""

    def __init__(self, fleet: Fleet, spark, caps: list[int] | None = None):
        p = len(fleet)
        self.fleet, self.caps = fleet, caps
        self.edges, self.vertices = [0] * p, [0] * p
        self.held = spark.createDataFrame([], "v long, machine int")
        self.parts: list[DataFrame] = []

    def take(self, got: DataFrame) -> None:
        """got: checkpointed src, dst, machine, seq."""
        ends = got.select(F.explode(F.array("src", "dst")).alias("v"), "machine").distinct()
        new = cut(ends.join(self.held, ["v", "machine"], "left_anti"))
        for r in got.groupBy("machine").count().collect():  # p rows
            self.edges[r["machine"]] += r["count"]
        for r in new.groupBy("machine").count().collect():  # p rows
            self.vertices[r["machine"]] += r["count"]
        self.held = cut(compact(self.held.unionByName(new)))
        self.parts.append(got)

    def memory_room(self) -> list[int]:
        """Edges that fit for sure: both ends may be new to the machine."""
        f = self.fleet
        each = f.m_edge + 2 * f.m_node
        return [max(0, int((m.mem - f.m_edge * e - f.m_node * v + 1e-9) // each)) for m, e, v in zip(f.machines, self.edges, self.vertices, strict=True)]

    def room(self) -> list[int]:
        """Edges that fit for sure and stay within the capacities."""
        rooms = self.memory_room()
        return rooms if self.caps is None else [max(0, min(r, c - e)) for r, c, e in zip(rooms, self.caps, self.edges, strict=True)]

    def holders(self) -> DataFrame:
        return self.held.groupBy("v").agg(F.sort_array(F.collect_set("machine")).alias("machines"))

    def placed(self) -> DataFrame:
        out = self.parts[0]
        for x in self.parts[1:]:
            out = out.unionByName(x)
        return compact(out)


def _within(won: DataFrame, rooms: list[int], seq: int) -> DataFrame:
    """The choices (src, dst, machine) that are within the machines' rooms."""
    ranked = quota_rank(won, "machine", F.xxhash64("src", "dst")).where(F.col("rank") <= by_machine(rooms, "long"))
    return cut(ranked.select("src", "dst", "machine", (F.lit(seq).cast("long") * (1 << 40) + F.col("rank")).alias("seq")))


def _dealt(options: Column, rooms: list[int], salt: int) -> Column:
    """One of the machines in ``options``, by a hash of the edge in proportion to their rooms."""
    room = F.array(*[F.lit(float(x)) for x in rooms])
    u = lambda m: (F.pmod(F.xxhash64("src", "dst", m, F.lit(salt)), F.lit(1 << 30)) + 1) / float((1 << 30) + 2)
    return F.array_min(F.transform(options, lambda m: F.struct((-F.ln(u(m)) / F.get(room, m)).alias("x"), m.alias("m"))))["m"]


def place_left(free: DataFrame, state: Filling, seq: int) -> None:
    """Places the edges that growth left: at machines that hold both ends, else one, else at
    any, in proportion to their rooms and within them, in rounds. Capacities bind while they
    have room, memory always; raises Infeasible if memory is short."""
    none = F.array().cast("array<int>")
    while not free.isEmpty():
        rooms = state.room()
        if not any(rooms):
            rooms = state.memory_room()
        if not any(rooms):
            raise Infeasible(f"{free.count()} edges are left when no machine has memory for one more edge with two new ends")
        open_ = F.array(*[F.lit(i) for i, x in enumerate(rooms) if x])
        h = state.holders()
        x = free.join(h.select(F.col("v").alias("src"), F.col("machines").alias("a")), "src", "left").join(h.select(F.col("v").alias("dst"), F.col("machines").alias("b")), "dst", "left")
        a, b = F.array_intersect(F.coalesce("a", none), open_), F.array_intersect(F.coalesce("b", none), open_)
        x = x.withColumn("_both", F.array_intersect(a, b)).withColumn("_any", F.array_union(a, b))
        options = F.when(F.size("_both") > 0, F.col("_both")).when(F.size("_any") > 0, F.col("_any")).otherwise(open_)
        got = _within(x.select("src", "dst", _dealt(options, rooms, seq).alias("machine")), rooms, seq)
        state.take(got)
        free, seq = cut(free.join(got, ["src", "dst"], "left_anti")), seq + 1


def _seeds(free: DataFrame, idle: dict[int, int], k: int) -> DataFrame:
    """(v, machine): starts for idle machines, as many as a share of their rooms needs, among
    the vertices of at most the median free degree, by hash; one at least."""
    deg = cut(degrees(free))
    n, mean, median = deg.agg(F.count(F.lit(1)), F.avg("degree"), F.percentile_approx("degree", 0.5)).first()
    wanted = {i: max(1.0, room / (4 * mean)) for i, room in idle.items()}
    low = deg.where(F.col("degree") <= median)
    share = min(1.0, sum(wanted.values()) / max(1, n / 2))
    h = F.pmod(F.xxhash64("v", F.lit(k)), F.lit(1 << 30)) / float(1 << 30)
    total, at, which = sum(wanted.values()), 0.0, F.lit(None).cast("int")
    for i, w in wanted.items():  # p branches
        at += w / total
        which = F.coalesce(which, F.when(F.pmod(F.xxhash64("v", F.lit(k), F.lit(1)), F.lit(1 << 30)) / float(1 << 30) < at, F.lit(i)))
    some = low.where(h < share).select("v", F.coalesce(which, F.lit(list(wanted)[-1])).cast("int").alias("machine"))
    first = low.orderBy("degree", F.xxhash64("v")).limit(len(idle)).collect()  # p rows
    sure = free.sparkSession.createDataFrame([(r["v"], i) for r, i in zip(first, wanted, strict=False)], "v long, machine int")
    return some.unionByName(sure)


def best_first_parallel(edges: DataFrame, fleet: Fleet, alpha: float = 0.3, beta: float = 0.3, width: float = 0.5, max_rounds: int = 12, trace: dict | None = None) -> DataFrame:
    """All machines grow at once. In a round each machine with room takes the better part of
    its frontier (``width``, by an approximate quantile of the priority), covers the free
    neighbours, and claims free edges between covered vertices; an edge goes to the claim of
    the least filled machine; claims over a machine's room stay free. Machines without a
    frontier get new starts. It ends when nothing is free or no machine has room, or after
    ``max_rounds``; what is left is placed by ``place_left``. trace gets the rounds and the
    number of edges that growth placed."""
    spark, p = edges.sparkSession, len(fleet)
    free = cut(edges.select("src", "dst"))
    s = stats(free).first()
    caps = plan(fleet, int(s["n_edges"]), int(s["n_vertices"]))
    state = Filling(fleet, spark, caps)
    cover = spark.createDataFrame([], "v long, machine int")
    k, idle_rounds = 0, 0
    while k < max_rounds and idle_rounds < 2 and not free.isEmpty():
        rooms = state.room()
        if not any(rooms):
            break
        arcs = both_ways(free)
        open_ = [i for i in range(p) if rooms[i]]
        mine = cover.where(F.col("machine").isin(open_))
        front = mine.join(arcs, "v").join(cover.select(F.col("v").alias("u"), "machine", F.lit(1).alias("inner")), ["u", "machine"], "left")
        scored = front.groupBy("v", "machine").agg(F.sum(F.col("inner").isNull().cast("long")).alias("outside"), F.count(F.lit(1)).alias("degree"))
        border = cover.groupBy("v").agg((F.count(F.lit(1)) > 1).alias("b"))
        scored = cut(scored.join(border, "v").withColumn("w", priority(F.col("outside"), F.col("degree"), F.col("b"), alpha, beta)))
        limit = {r["machine"]: r["q"] for r in scored.groupBy("machine").agg(F.percentile_approx("w", width).alias("q")).collect()}  # p rows
        chosen = scored.where(F.col("w") <= by_machine([limit.get(i) for i in range(p)])).select("v", "machine")
        idle = {i: rooms[i] for i in open_ if i not in limit}
        if idle:
            chosen = cut(chosen.unionByName(_seeds(free, idle, k)).distinct())
        new = chosen.join(arcs, "v").select(F.col("u").alias("v"), "machine").unionByName(chosen)
        cover = cut(cover.unionByName(new).distinct())
        a, b = cover.select(F.col("v").alias("src"), "machine"), cover.select(F.col("v").alias("dst"), "machine")
        claims = free.join(a, "src").join(b, ["dst", "machine"]).where(F.col("machine").isin(open_)).select("src", "dst", "machine")
        load = by_machine([state.edges[i] / max(1, caps[i]) for i in range(p)])
        won = claims.groupBy("src", "dst").agg(F.min_by("machine", F.struct(load, F.xxhash64("src", "machine"))).alias("machine"))
        got = _within(won, rooms, k)
        if got.isEmpty():
            idle_rounds += 1
        else:
            idle_rounds = 0
            state.take(got)
            free = cut(free.join(got, ["src", "dst"], "left_anti"))
        k += 1
    if trace is not None:
        trace |= {"rounds": k, "grown": sum(state.edges), "edges": int(s["n_edges"])}
    place_left(free, state, max_rounds + 1)
    return state.placed()


# ---------------------------------------------------------------- local search


def victims(cost: DataFrame, gamma: float = 0.9) -> DataFrame:
    """Machines at or above min + gamma (max - min)."""
    edge = cost.agg(F.min("t").alias("lo"), F.max("t").alias("hi"))
    return cost.crossJoin(F.broadcast(edge)).where(F.col("t") >= F.col("lo") + gamma * (F.col("hi") - F.col("lo"))).select("machine", "t")


def newest(assign: DataFrame, who: DataFrame, theta: float = 0.01, bands: int = 256) -> DataFrame:
    """The last share of each victim's edges by (seq, src, dst). They are ranked within bands
    of seq, and only bands that the share reaches into are ranked at all."""
    own = assign.join(F.broadcast(who.select("machine")), "machine")
    n = own.groupBy("machine").agg(F.ceil(theta * F.count(F.lit(1))).alias("n"), F.min("seq").alias("_lo"), F.max("seq").alias("_hi"))
    banded = own.join(F.broadcast(n), "machine").withColumn("_b", F.floor((F.col("_hi") - F.col("seq")).cast("double") * bands / (F.col("_hi") - F.col("_lo") + 1)))
    sizes = banded.groupBy("machine", "_b").agg(F.count(F.lit(1)).alias("_m"))  # p * bands rows
    before = sizes.withColumn("_before", F.coalesce(F.sum("_m").over(Window.partitionBy("machine").orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("_m")
    near = banded.join(F.broadcast(before), ["machine", "_b"]).where(F.col("_before") < F.col("n"))
    rank = F.row_number().over(Window.partitionBy("machine", "_b").orderBy(F.desc("seq"), F.desc("src"), F.desc("dst"))) + F.col("_before")
    return near.withColumn("_r", rank).where(F.col("_r") <= F.col("n")).select("src", "dst", "machine", "seq")


def greedy_choice(lost: DataFrame, kept: DataFrame, cost: DataFrame, p: int, rooms: list[int] | None = None) -> DataFrame:
    """For each edge the machine of least time among those holding both ends, else one
    end, else all; times as they stand (a batch), ties to the least machine. With rooms,
    only machines with room count; an edge that no machine can take has a null one."""
    times = {r["machine"]: float(r["t"]) for r in cost.select("machine", "t").collect()}  # p rows
    t = F.array(*[F.lit(times.get(i, 0.0)) for i in range(p)])
    open_ = F.array(*[F.lit(i) for i in range(p) if rooms is None or rooms[i] > 0]).cast("array<int>")
    h, none = replicas(kept), F.array().cast("array<int>")
    x = lost.select("src", "dst").join(h.select(F.col("v").alias("src"), F.col("machines").alias("a")), "src", "left").join(h.select(F.col("v").alias("dst"), F.col("machines").alias("b")), "dst", "left")
    a, b = F.array_intersect(F.coalesce("a", none), open_), F.array_intersect(F.coalesce("b", none), open_)
    options = F.when(F.size(F.array_intersect(a, b)) > 0, F.array_intersect(a, b)).when(F.size(F.array_union(a, b)) > 0, F.array_union(a, b)).otherwise(open_)
    return x.select("src", "dst", F.array_min(F.transform(options, lambda m: F.struct(F.get(t, m).alias("t"), m.alias("m"))))["m"].alias("machine"))


def repair(lost: DataFrame, kept: DataFrame, fleet: Fleet, seq: int, batches: int = 4) -> DataFrame:
    """kept with the lost edges (src, dst, machine, seq) placed again, batch after batch, the
    costs taken anew before each. A machine takes a new edge only into memory that was free
    before the edges were lost, so an edge that finds no place can stay where it was."""
    p, each = len(fleet), fleet.m_edge + 2 * fleet.m_node
    used = {r["machine"]: r["mem_used"] for r in costs(kept.unionByName(lost), fleet).collect()}  # p rows
    rooms = [max(0, int((m.mem - used.get(i, 0.0) + 1e-9) // each)) for i, m in enumerate(fleet.machines)]
    now = kept
    for k in range(batches):
        part = lost.where(F.pmod(F.xxhash64("src", "dst"), F.lit(batches)) == k)
        back = part.select("src", "dst", F.col("machine").alias("old"), F.col("seq").alias("was"))
        choice = greedy_choice(part, now, costs(now, fleet), p, rooms)
        ranked = quota_rank(choice.where("machine IS NOT NULL"), "machine", F.xxhash64("src", "dst")).where(F.col("rank") <= by_machine(rooms, "long"))
        got = cut(back.join(ranked.select("src", "dst", "machine"), ["src", "dst"], "left").select("src", "dst", F.coalesce("machine", "old").alias("machine"), F.when(F.col("machine").isNull(), F.col("was")).otherwise(F.lit(seq).cast("long") + F.pmod(F.xxhash64("dst", "src"), F.lit(1 << 16))).alias("seq"), F.col("machine").isNotNull().alias("moved")))
        for r in got.where("moved").groupBy("machine").count().collect():  # p rows
            rooms[r["machine"]] -= r["count"]
        now = cut(compact(now.unionByName(got.drop("moved"))))
    return now


def repartition(assign: DataFrame, fleet: Fleet, partners: int = 3, seq: int = 0, **growth) -> DataFrame:
    """Pools the edges of the slowest machine and of those that share most vertices with it,
    and grows them anew on these machines; unchanged if they can't hold them so."""
    worst = costs(assign, fleet).orderBy(F.desc("t"), "machine").first()["machine"]
    shared = overlap(assign, worst).orderBy(F.desc("n"), "other").limit(max(0, partners - 1)).collect()  # p rows at most
    which = [worst, *(r["other"] for r in shared)]
    inside = F.col("machine").isin(which)
    pool = cut(assign.where(inside).select("src", "dst"))
    try:
        grown = best_first_parallel(pool, fleet.subset(which), **growth)
    except Infeasible:
        return assign
    name = F.get(F.array(*[F.lit(i) for i in which]), F.col("machine"))
    again = grown.select("src", "dst", name.alias("machine"), (F.lit(seq).cast("long") + F.pmod(F.col("seq"), F.lit(1 << 16))).alias("seq"))
    return cut(compact(assign.where(~inside).select("src", "dst", "machine", "seq").unionByName(again)))


def refine_rounds(assign: DataFrame, fleet: Fleet, gamma: float = 0.9, theta: float = 0.01, rounds: int = 3, fails: int = 5, partners: int = 3, batches: int = 4, trace: list | None = None, growth: dict | None = None) -> DataFrame:
    """Destroy and repair in batches; after ``fails`` rounds in a row without a gain, the
    slowest machine and its partners are grown anew. The best assignment seen that is within
    memory (or no further over it than the given one) is returned; trace gets each round's
    step and cost."""
    best = now = cut(assign.select("src", "dst", "machine", "seq"))

    def state(x: DataFrame) -> tuple[float, float]:
        c = costs(x, fleet).select("t", F.greatest(F.col("mem_used") - by_machine([m.mem for m in fleet.machines]), F.lit(0.0)).alias("over"))
        return c.agg(F.max("t"), F.sum("over")).first()

    low, over = state(now)
    t, failed, seq = low, 0, int(now.agg(F.coalesce(F.max("seq"), F.lit(0))).first()[0]) + 1
    for k in range(rounds):
        if failed >= fails:
            now, step, failed = repartition(now, fleet, partners, seq, **(growth or {})), "repartition", 0
        else:
            c = cut(costs(now, fleet).select("machine", "t"))
            lost = cut(newest(now, victims(c, gamma), theta))
            kept = cut(now.join(lost, ["src", "dst"], "left_anti").select("src", "dst", "machine", "seq"))
            now, step = repair(lost, kept, fleet, seq, batches), "repair"
        seq += 1 << 17
        before, (t, beyond) = t, state(now)
        failed = 0 if t < before else failed + 1
        if trace is not None:
            trace.append((step, float(t)))
        if t < low and beyond <= over + 1e-6:
            best, low, over = now, t, beyond
    return best
