"""Queries of the reference's methods with their checks."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from ..functions.columns import priority
from ..operators import algos, bsp, capacity, costs, extensions, machines, partitioners, rounds
from ..operators.partitioners import graph_size, hash_placement
from ..sources import graphs
from . import oracle as O

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


def r6(c, name=None):
    c = F.col(c) if isinstance(c, str) else c
    return F.round(c, 6).alias(name) if name else F.round(c, 6)


def edges(spark, d, g):
    return graphs.GRAPHS[g](spark, d)


def setting(spark, d, g="g4"):
    e = edges(spark, d, g)
    return hash_placement(e, 30), machines.small(e.count())


# ------------------------------------------------------------------ graphs
for _g in O.EDGES:
    query(f"graph_{_g}", O.EDGES[_g])(lambda s, d, g=_g: edges(s, d, g))
query("graph_g11")(lambda s, d: edges(s, d, "g11"))
query("mesh_grid", O.grid(40, 25))(lambda s, d: graphs.grid(s, 40, 25))
query("graph_rmat", O.rmat(9))(lambda s, d: graphs.rmat(s, 9))


def _rmat_source(spark, d):
    from ..sources.rmat_source import register

    register(spark)
    return graphs.as_edges(spark.read.format("hetpart_rmat").option("scale", 9).load())


query("rmat_source", O.rmat(9))(_rmat_source)
_STATS = "with g as materialized ({}), d as (select v, count(*) as degree from (select src as v from g union all select dst from g) group by 1) select (sum(degree) / 2)::BIGINT as n_edges, count(*) as n_vertices, max(degree) as max_degree, round(sum(degree) / 2 / count(*)::DOUBLE, 6) as edges_per_vertex, round(sum(degree) / count(*)::DOUBLE, 6) as mean_degree from d"
for _g in ("g1", "g2", "g3", "g4", "g5", "g6"):
    query(f"graph_stats_{_g}", _STATS.format(O.EDGES[_g]))(lambda s, d, g=_g: graphs.stats(edges(s, d, g)).withColumns({"edges_per_vertex": r6("edges_per_vertex"), "mean_degree": r6("mean_degree")}))
query("degree_hist", f"with g as materialized ({O.EDGES['g4']}) select degree, count(*) as n from (select v, count(*) as degree from (select src as v from g union all select dst from g) group by 1) group by 1")(lambda s, d: graphs.degrees(edges(s, d, "g4")).groupBy("degree").agg(F.count(F.lit(1)).alias("n")))
query("page_arcs", f"select distinct (page_id * 16 + 8)::BIGINT as src, {O.TERM_ID} as dst from {O.TERMS}")(graphs.page_terms)

# ------------------------------------------------------------------ fleets
_FLEET = "machine, mem, c_node, c_edge, c_com, kind"
query("fleet_two_type", f"select {_FLEET} from ({O.small_fleet('g4')})")(lambda s, d: machines.small(edges(s, d, "g4").count()).df(s))
query("fleet_nine", f"select i::INTEGER as machine, ceil((select count(*) from ({O.EDGES['g4']})) / 9.0::DOUBLE * (case when i < 3 then 9 else 3.6::DOUBLE end)) as mem, (case when i < 3 then 10 else 5 end)::DOUBLE as c_node, (case when i < 3 then 15 else 10 end)::DOUBLE as c_edge, (case when i < 3 then 15 else 10 end)::DOUBLE as c_com, case when i < 3 then 'super' else 'normal' end as kind from range(9) t(i)")(lambda s, d: machines.nine(edges(s, d, "g4").count()).df(s))
for _q in (1, 2, 3, 6):
    _kind = f"greatest(0, {_q - 1} - (29 - i) // 5)"
    query(f"fleet_typed_{_q}" if _q != 3 else "fleet_typed", f"select i::INTEGER as machine, 5.0 * (1 + 0.25 * {_kind}) as c_node, 10.0 * (1 + 0.25 * {_kind}) as c_edge, 10.0 * (1 + 0.25 * {_kind}) as c_com, 'type' || {_kind} as kind from range(30) t(i)")(lambda s, d, q=_q: machines.typed(100_000, q).df(s).drop("mem"))


def _bench(spark, d):
    n = F.col("n_nationkey")
    return graphs.read(spark, d, "nation").select(n.cast("int").alias("machine"), (8 * (1 + n % 4)).cast("long").alias("mem_gb"), (2 * (1 + n % 5)).cast("long").alias("fp_ns"), (2 * (2 + n % 5) + 2).cast("long").alias("fp2_ns"), (4096 * (1 + n % 3)).cast("long").alias("co_ns"))


query("quantify_machines", "with b as (select n_nationkey::INTEGER as machine, 8 * (1 + n_nationkey % 4) as mem_gb, 2 * (1 + n_nationkey % 5) as fp_ns, 2 * (2 + n_nationkey % 5) + 2 as fp2_ns, 4096 * (1 + n_nationkey % 3) as co_ns from nation) select machine, mem_gb * 250000000.0::DOUBLE / 8 as mem, 1 / 8.0::DOUBLE as m_node, 2 / 8.0::DOUBLE as m_edge, fp_ns / 2.0::DOUBLE as c_node, fp2_ns / 2.0::DOUBLE as c_edge, co_ns / 2048.0::DOUBLE as c_com from b")(lambda s, d: machines.quantify(_bench(s, d)))
query("quantify_attributes", "with b as (select n_nationkey::INTEGER as machine, 8 * (1 + n_nationkey % 4) as mem_gb, 2 * (1 + n_nationkey % 5) as fp_ns, 2 * (2 + n_nationkey % 5) + 2 as fp2_ns, 4096 * (1 + n_nationkey % 3) as co_ns from nation) select machine, mem_gb * 250000000.0::DOUBLE / 8 as mem, 10 / 8.0::DOUBLE as m_node, 2 / 8.0::DOUBLE as m_edge, 10 * fp_ns / 2.0::DOUBLE as c_node, fp2_ns / 2.0::DOUBLE as c_edge, co_ns / 2048.0::DOUBLE as c_com from b")(lambda s, d: machines.quantify(_bench(s, d), attr_factor=10))
query("work_weights", f"select machine, c_node * 3 as c_node, c_edge * 0.5::DOUBLE as c_edge from ({O.small_fleet('g4')})")(lambda s, d: machines.small(edges(s, d, "g4").count()).with_work(3, 0.5).df(s).select("machine", "c_node", "c_edge"))

# ------------------------------------------------------------------ costs on hash placement
_S = O.setting("g4")
query("base_hash", O.placed("g4"))(lambda s, d: setting(s, d)[0])
query("cost_sizes", _S + "select machine, n_vertices, n_edges from s")(lambda s, d: costs.sizes(*setting(s, d)))
query("cost_memory", _S + "select k.machine, mem_used, mem, mem_used <= mem as fits from k join f on f.machine = k.machine")(lambda s, d: costs.memory(*setting(s, d)))
query("cost_tcal", _S + "select machine, t_cal from k")(lambda s, d: costs.t_cal(*setting(s, d)))
query("cost_tcom", _S + "select machine, t_com from k")(lambda s, d: costs.t_com(*setting(s, d)))
query("cost_all", _S + "select * from k")(lambda s, d: costs.costs(*setting(s, d)))
query("cost_tc", _S + "select max(t) as tc, round(ln(max(t)), 9) as ln_tc from k")(lambda s, d: costs.total(*setting(s, d)).select("tc", F.round(F.ln("tc"), 9).alias("ln_tc")))
query("cost_barrier_split", _S + "select max(t_cal) + max(t_com) as tc from k")(lambda s, d: costs.total(*setting(s, d), mode="barrier_split"))
query("cost_rf", _S + "select round(count(*) / count(distinct v)::DOUBLE, 9) as rf from h")(lambda s, d: costs.replication_factor(setting(s, d)[0]).select(F.round("rf", 9).alias("rf")))
query("cost_balance", _S + "select round(max(n_edges) * 30 / sum(n_edges)::DOUBLE, 9) as by_edges, round(max(n_vertices) * 30 / sum(n_vertices)::DOUBLE, 9) as by_vertices, round(max(t_cal) * 30 / sum(t_cal), 9) as by_time from k")(
    lambda s, d: costs.costs(*setting(s, d)).agg(*[F.round(F.max(c) * 30 / F.sum(c), 9).alias(n) for c, n in (("n_edges", "by_edges"), ("n_vertices", "by_vertices"), ("t_cal", "by_time"))])
)
query("cost_border", _S + "select count(*) filter (n > 1) as n_border, count(*) as n_vertices from (select v, count(*) as n from h group by 1)")(lambda s, d: costs.border_count(setting(s, d)[0]))
query("cost_share", _S + "select machine, round(t_com / t, 9) as share from k")(lambda s, d: costs.comm_share(*setting(s, d)).select("machine", F.round("share", 9).alias("share")))
query("cost_histogram", _S + "select least(floor(t * 10 / (select max(t) from k)), 9)::BIGINT as band, count(*) as machines, sum(t_cal) as t_cal, sum(t_com) as t_com from k group by 1")(lambda s, d: costs.histogram(*setting(s, d)))


def _identity(s, d):
    e = edges(s, d, "g4")
    return costs.homogeneous_identity(hash_placement(e, 30), machines.Fleet((machines.Machine(1e9, 1, 1, 1),) * 30))


query("cost_identity", "select 2.0::DOUBLE as ratio")(_identity)
query("replica_sets", _S + "select v, count(*)::INTEGER as n, min(machine) as first, max(machine) as last from h group by 1")(lambda s, d: costs.replicas(setting(s, d)[0]).select("v", F.size("machines").alias("n"), F.element_at("machines", 1).alias("first"), F.element_at("machines", -1).alias("last")))
query("overlap_matrix", _S + "select j.machine as other, count(*) as n from h i join h j on i.v = j.v where i.machine = 0 and j.machine <> 0 group by 1")(lambda s, d: costs.overlap(setting(s, d)[0], 0))


def _homes(s, d, g="g4"):
    ids = edges(s, d, g).select(F.explode(F.array("src", "dst")).alias("v")).distinct()
    return ids.select("v", (F.col("v") % 7).cast("int").alias("machine"))


query("cost_edge_cut", f"with g as ({O.EDGES['g4']}) select count(*) filter (src % 7 <> dst % 7) as n_cut, count(*) as n_edges from g")(lambda s, d: costs.edge_cut(edges(s, d, "g4"), _homes(s, d)))

# ------------------------------------------------------------------ capacities
for _g in ("g1", "g4", "g6"):
    query(f"cap_terms_{_g}", O.count_terms(_g) + "select machine, round(cost, 9) as cost, round(cap, 6) as cap from t")(lambda s, d, g=_g: (lambda e: capacity.terms_df(machines.small(e.count()), s, *graph_size(e)).select("machine", F.round("cost", 9).alias("cost"), r6("cap", "cap")))(edges(s, d, g)))
    query(f"cap_waterfill_{_g}", O.waterfill(_g) + "select machine, round(least(cap, level / cost), 6) as amount, round(level, 6) as level from t, l")(lambda s, d, g=_g: _water(s, d, g))
    query(f"cap_rounds_{_g}", O.waterfill(_g) + "select machine, round(least(cap, level / cost), 4) as amount from t, l")(lambda s, d, g=_g: _rounds(s, d, g))


def _water(s, d, g):
    e = edges(s, d, g)
    n, v = graph_size(e)
    return capacity.waterfill(capacity.terms_df(machines.small(n), s, n, v), n).select("machine", r6("amount", "amount"), r6("level", "level"))


def _rounds(s, d, g):
    n, v = graph_size(edges(s, d, g))
    out = capacity.rounds(*capacity.terms(machines.small(n), n, v), n)
    return s.createDataFrame([(i, float(x)) for i, x in enumerate(out)], "machine int, amount double").select("machine", F.round("amount", 4).alias("amount"))


@query("cap_integer", f"select count(*)::BIGINT as total, 0::BIGINT as n_over, 0::BIGINT as n_empty from ({O.EDGES['g4']})")
def _cap_integer(s, d):
    n, v = graph_size(edges(s, d, "g4"))
    f = machines.small(n)
    caps, limit = capacity.plan(f, n, v), capacity.terms(f, n, v)[1]
    return s.createDataFrame([(sum(caps), sum(c > k for c, k in zip(caps, limit, strict=True)), sum(c < 1 for c in caps))], "total long, n_over long, n_empty long")


query("cap_uniform", f"select i::INTEGER as machine, ceil(1.1::DOUBLE * (select count(*) from ({O.EDGES['g4']})) / 30)::BIGINT as cap from range(30) t(i)")(lambda s, d: s.createDataFrame(list(enumerate(capacity.uniform(30, edges(s, d, "g4").count()))), "machine int, cap long"))
query("cap_memory_only", O.count_terms("g4") + "select machine, floor(cap)::BIGINT as cap from t")(lambda s, d: (lambda n, v: s.createDataFrame(list(enumerate(capacity.memory_only(machines.small(n), n, v))), "machine int, cap long"))(*graph_size(edges(s, d, "g4"))))


@query("cap_gap", "select true as within_bound, true as at_least_level, true as equals_exact")
def _cap_gap(s, d):
    """On every graph the integer plan is within the bound of the exact level."""
    ok = []
    for g in ("g1", "g4", "g6"):
        n, v = graph_size(edges(s, d, g))
        f = machines.small(n)
        cost, cap = capacity.terms(f, n, v)
        gap, bound = capacity.gap(cost, cap, n)
        level = max(c * x for c, x in zip(cost, capacity.rounds(cost, cap, n), strict=True))
        ok.append((gap <= bound + 1e-9, capacity.exact_level(cost, cap, n) >= level - 1e-6, abs(gap) < 1e-9))
    return s.createDataFrame([tuple(all(x) for x in zip(*ok, strict=True))], "within_bound boolean, at_least_level boolean, equals_exact boolean")


# ------------------------------------------------------------------ growth and refinement as plans
_FRONT = f"""with g as materialized ({O.EDGES['g4']}), arcs as (select src as v, dst as u from g union all select dst, src from g),
c as (select distinct v from arcs where v % 3 = 0), b as (select distinct v from arcs where v % 5 = 0)
select arcs.v, count(*) filter (arcs.u % 3 <> 0) as outside, count(*) as degree, round(1.3::DOUBLE * count(*) filter (arcs.u % 3 <> 0) - (0.3::DOUBLE + case when arcs.v % 5 = 0 then 0.3::DOUBLE else 0 end) * count(*), 6) as w from arcs join c on c.v = arcs.v group by arcs.v"""


@query("priority_scores", _FRONT)
def _priority(s, d):
    e = edges(s, d, "g4")
    v = e.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
    return rounds.frontier_scores(e, v.where("v % 3 = 0"), v.where("v % 5 = 0")).withColumn("w", r6("w"))


query("priority_example", "select * from (values ('X', 0.2::DOUBLE), ('Y', 1.1::DOUBLE), ('Z', 1.4::DOUBLE)) t(name, w)")(lambda s, d: s.createDataFrame([("X", 2, 4, True), ("Y", 2, 5, False), ("Z", 2, 4, False)], "name string, o int, n int, b boolean").select("name", r6(priority(F.col("o"), F.col("n"), F.col("b"), 0.3, 0.3), "w")))
query("victims", _S + "select machine, t from k where t >= (select min(t) + 0.5::DOUBLE * (max(t) - min(t)) from k)")(lambda s, d: rounds.victims(costs.costs(*setting(s, d)), 0.5))
_SEQ = "(src * 31 + dst) % 100003"
query("lifo_tail", _S + f", w as (select machine from k where t >= (select min(t) + 0.9::DOUBLE * (max(t) - min(t)) from k)) select src, dst, machine, seq from (select *, {_SEQ} as seq, row_number() over (partition by machine order by {_SEQ} desc, src desc, dst desc) as r, count(*) over (partition by machine) as n from a where machine in (select machine from w)) where r <= ceil(0.01::DOUBLE * n)")(lambda s, d: _tail(s, d))


def _tail(s, d):
    a, f = setting(s, d)
    a = a.withColumn("seq", (F.col("src") * 31 + F.col("dst")) % 100003)
    return rounds.newest(a, rounds.victims(costs.costs(a, f)), 0.01)


query(
    "greedy_choice",
    _S + """, lost as (select src, dst from a where (src + dst) % 97 = 0), kept as (select * from a where (src + dst) % 97 <> 0), hk as (select distinct v, machine from (select src as v, machine from kept union all select dst, machine from kept)),
o as (select l.src, l.dst, k.machine, k.t, (x.machine is not null)::INT + (y.machine is not null)::INT as n from lost l cross join k left join hk x on x.v = l.src and x.machine = k.machine left join hk y on y.v = l.dst and y.machine = k.machine)
select src, dst, machine from (select *, row_number() over (partition by src, dst order by n desc, t, machine) as r from o) where r = 1""",
)(lambda s, d: _choice(s, d))


def _choice(s, d):
    a, f = setting(s, d)
    return rounds.greedy_choice(a.where("(src + dst) % 97 = 0"), a.where("(src + dst) % 97 <> 0"), costs.costs(a, f), 30)


# ------------------------------------------------------------------ methods: invariants and comparisons


def run_method(s, d, g, name, fleet=None, cfg=None, seed=1):
    e = edges(s, d, g)
    f = fleet or machines.small(e.count()).with_memory(1.5)
    return partitioners.kernel(e, partitioners.method(name, f, cfg, seed)), e, f


def _inv_sql(g):
    return f"select count(*)::BIGINT as n_edges, count(*)::BIGINT as n_assigned, 0::BIGINT as n_duplicate, 0::BIGINT as n_foreign, 0::BIGINT as n_unknown, 0::BIGINT as n_over_memory from ({O.EDGES[g]})"


FREE_OF_MEMORY = ("load_only", "traffic_migration", "hetero_stream", "hetero_expansion")
for _m in (*partitioners.PAPER_METHODS, *partitioners.BASELINES):
    for _g in ("g1", "g4", "g6") if _m in partitioners.PAPER_METHODS else ("g4",):
        _sql = _inv_sql(_g)
        if _m in FREE_OF_MEMORY:
            _sql = f"select * exclude (n_over_memory) from ({_sql})"

        def _inv(s, d, g=_g, m=_m):
            a, e, f = run_method(s, d, g, m)
            out = costs.invariants(a, e, f)
            return out.drop("n_over_memory") if m in FREE_OF_MEMORY else out

        query(f"inv_{_m}_{_g}", _sql)(_inv)
for _o in ("bfs", "dfs"):
    query(f"inv_grow_{_o}", _inv_sql("g4"))(lambda s, d, o=_o: (lambda a, e, f: costs.invariants(a, e, f))(*run_method(s, d, "g4", "plus", cfg=partitioners.Config(growth=partitioners.GrowthConfig(order=o)))))


@query("method_full")
def _full(s, d):
    a, _, f = run_method(s, d, "g1", "full")
    return costs.costs(a, f)


def _parallel(s, d, g):
    """Growth by rounds: the invariants, and whether growth placed most edges by itself."""
    e, told = edges(s, d, g), {}
    f = machines.small(e.count(), 2, 4).with_memory(8)
    a = rounds.best_first_parallel(e, f, max_rounds=6, trace=told)
    return costs.invariants(a, e, f).withColumn("mostly_grown", F.lit(told["grown"] > 0.5 * told["edges"]))


for _g in ("g6", "g9"):
    query("inv_grow_parallel" + ("" if _g == "g6" else f"_{_g}"), f"select *, true as mostly_grown from ({_inv_sql(_g)})")(lambda s, d, g=_g: _parallel(s, d, g))


def _tight(s, d):
    """Growth by rounds on machines with little memory to spare."""
    e = edges(s, d, "g6")
    f = machines.small(e.count(), 2, 4).with_memory(6)
    return costs.invariants(rounds.best_first_parallel(e, f, max_rounds=3), e, f)


query("inv_grow_parallel_tight", _inv_sql("g6"))(_tight)


def _rounds_of(s, d, fails):
    """Local search by rounds from a placement within memory: invariants, never worse, and
    which steps ran."""
    e = edges(s, d, "g6")
    f = machines.small(e.count(), 2, 4).with_memory(8)
    a, steps = hash_placement(e, 6).withColumn("seq", (F.col("src") * 31 + F.col("dst")) % 100003), []
    b = rounds.refine_rounds(a, f, theta=0.05, rounds=1, fails=fails, batches=2, trace=steps, growth={"max_rounds": 2})
    t = lambda x: costs.total(x, f).first()[0]
    return costs.invariants(b, e, f).withColumn("not_worse", F.lit(t(b) <= t(a) + 1e-6)).withColumn("steps", F.lit(",".join(x for x, _ in steps)))


query("inv_refine_rounds", f"select *, true as not_worse, 'repair' as steps from ({_inv_sql('g6')})")(lambda s, d: _rounds_of(s, d, 5))
query("inv_repartition_rounds", f"select *, true as not_worse, 'repartition' as steps from ({_inv_sql('g6')})")(lambda s, d: _rounds_of(s, d, 0))


def _searched(s, d, **search):
    """Invariants of the full method with some search settings on G4."""
    from ..operators.refine import SearchConfig

    return run_method(s, d, "g4", "full", cfg=partitioners.Config(search=SearchConfig(**search)))


query("inv_repartition", _inv_sql("g4"))(lambda s, d: costs.invariants(*_searched(s, d, fails=0, rounds=3)))


def _goal(s, d):
    """The search with the map-reduce goal: that goal is no worse than without a search."""
    a, e, f = _searched(s, d, objective="barrier_split")
    b = run_method(s, d, "g4", "plus")[0]
    goal = lambda x: costs.total(x, f, "barrier_split").first()[0]
    return costs.invariants(a, e, f).withColumn("not_worse", F.lit(goal(a) <= goal(b) + 1e-6))


query("inv_goal_barrier_split", f"select *, true as not_worse from ({_inv_sql('g4')})")(_goal)


def _no_time(s, d):
    """A search without time is none: the assignment without a search."""
    a, e, _ = _searched(s, d, time_limit_s=-1.0)
    b = run_method(s, d, "g4", "plus")[0]
    same = a.select("src", "dst", "machine").intersect(b.select("src", "dst", "machine"))
    return same.agg(F.count(F.lit(1)).alias("n_equal"))


query("search_time_limit", f"select count(*)::BIGINT as n_equal from ({O.EDGES['g4']})")(_no_time)


def _own_ratios(s, d):
    """Capacity terms with a ratio of vertices to edges of each machine's own."""
    a, f = setting(s, d)
    n = {r["machine"]: r["n_vertices"] / r["n_edges"] for r in costs.costs(a, f).collect()}  # p rows
    cost, cap = capacity.terms(f, 1, 1, [n[i] for i in range(len(f))])
    return s.createDataFrame([(i, c, k) for i, (c, k) in enumerate(zip(cost, cap, strict=True))], "machine int, cost double, cap double").select("machine", r6("cost", "cost"), r6("cap", "cap"))


query("cap_own_ratios", _S + "select k.machine, round(f.c_edge + f.c_node * (n_vertices::DOUBLE / n_edges), 6) as cost, round(f.mem / (2 + n_vertices::DOUBLE / n_edges), 6) as cap from k join f on f.machine = k.machine")(_own_ratios)
for _w in ("out", "in", "both"):
    _sql = f"select count(*)::BIGINT as n_edges, count(*)::BIGINT as n_assigned, 0::BIGINT as n_duplicate, 0::BIGINT as n_foreign, 0::BIGINT as n_unknown, 0::BIGINT as n_over_memory from (select distinct page_id, t from {O.TERMS})"

    def _directed(s, d, w=_w):
        arcs = graphs.page_terms(s, d)
        f = machines.small(arcs.count(), 2, 4).with_memory(9)
        return costs.invariants(partitioners.kernel(arcs, partitioners.method("full", f), direction=w), arcs, f)

    query(f"inv_directed_{_w}", _sql)(_directed)
for _w in ("capacity", "network"):
    query(f"inv_order_{_w}", _inv_sql("g4"))(lambda s, d, w=_w: costs.invariants(*run_method(s, d, "g4", "plus", cfg=partitioners.Config(machine_order=w))))
query("inv_two_level", _inv_sql("g4"))(lambda s, d: (lambda e: (lambda f: costs.invariants(partitioners.two_level(e, f, blocks=4), e, f))(machines.small(e.count()).with_memory(2)))(edges(s, d, "g4")))


@query("refine_never_worse", "select true as not_worse, 0::BIGINT as n_lost")
def _never_worse(s, d):
    a, f = setting(s, d)
    a = a.withColumn("seq", F.monotonically_increasing_id())
    b = rounds.refine_rounds(a, f, rounds=2)
    t = lambda x: costs.total(x, f).first()[0]
    lost = a.select("src", "dst").exceptAll(b.select("src", "dst")).count()
    return s.createDataFrame([(t(b) <= t(a) + 1e-6, lost)], "not_worse boolean, n_lost long")


# ------------------------------------------------------------------ extensions
query("ext_directed", f"with a as (select distinct (page_id * 16 + 8)::BIGINT as src, {O.TERM_ID} as dst from {O.TERMS}) select v, sum(i)::BIGINT as n_in, sum(o)::BIGINT as n_out from (select src as v, 0 as i, 1 as o from a union all select dst, 1, 0 from a) group by 1")(lambda s, d: extensions.directed_degrees(graphs.page_terms(s, d)))
_LABELS = "select (c_custkey * 16 + 1)::BIGINT as v, c_mktsegment as label, length(c_mktsegment)::BIGINT as bytes from customer"
query("ext_labels", O.setting("g2") + f"select machine, count(*) as n_labels, sum(bytes)::BIGINT as bytes from h join ({_LABELS}) l on l.v = h.v group by 1")(
    lambda s, d: extensions.label_volume(setting(s, d, "g2")[0], graphs.read(s, d, "customer").select((F.col("c_custkey") * 16 + 1).cast("long").alias("v"), F.col("c_mktsegment").alias("label"), F.char_length("c_mktsegment").cast("long").alias("bytes")))
)
query("ext_vertex_home", _S + ", p as (select v, machine, count(*) as n from (select src as v, machine from a union all select dst, machine from a) group by 1, 2) select v, machine from (select *, row_number() over (partition by v order by n desc, machine) as r from p) where r = 1")(lambda s, d: extensions.to_vertex_partition(setting(s, d)[0]))
query("ext_vertex_to_edge", f"select src, dst, (case when (src * 31 + dst * 17 + 1) % 2 = 0 then src % 7 else dst % 7 end)::INTEGER as machine from ({O.EDGES['g4']})")(lambda s, d: extensions.to_edge_partition(edges(s, d, "g4"), _homes(s, d)))


def _quota(s, d):
    """A vertex partition with room for five in a hundred more: vertices, rows, unknown
    machines, and machines over the quota."""
    a, _ = setting(s, d, "g6")
    n = a.select(F.explode(F.array("src", "dst")).alias("v")).distinct().count()
    capacity = -(-n * 21 // (20 * 30))
    h = extensions.to_vertex_partition(a, capacity, 30)
    sizes = h.groupBy("machine").agg(F.count(F.lit(1)).alias("n"))
    over = sizes.agg(F.sum((F.col("n") > capacity).cast("long")).alias("n_over"), F.sum((~F.col("machine").between(0, 29)).cast("long")).alias("n_unknown"))
    return h.agg(F.count_distinct("v").alias("n_vertices"), F.count(F.lit(1)).alias("n_rows")).crossJoin(over)


query("ext_vertex_quota", f"with g as ({O.EDGES['g6']}), v as (select src as v from g union select dst from g) select count(*)::BIGINT as n_vertices, count(*)::BIGINT as n_rows, 0::BIGINT as n_over, 0::BIGINT as n_unknown from v")(_quota)
_HOME = ", p as (select v, machine, count(*) as n from (select src as v, machine from a union all select dst, machine from a) group by 1, 2), home as (select v, machine from (select *, row_number() over (partition by v order by n desc, machine) as r from p) where r = 1)"
query("ext_edges_at_homes", _S + _HOME + " select distinct src, dst, machine from (select a.src, a.dst, x.machine from a join home x on x.v = a.src union all select a.src, a.dst, y.machine from a join home y on y.v = a.dst)")(lambda s, d: (lambda a: extensions.edges_at_homes(a.select("src", "dst"), extensions.to_vertex_partition(a)))(setting(s, d)[0]))
_LABELLED = f""", lab as (select v, sum(bytes) as bytes from ({_LABELS}) group by 1), hw as materialized (select h.v, h.machine, 1 + coalesce(bytes, 0) / 10.0::DOUBLE as w from h left join lab on lab.v = h.v),
com as (select x.machine, sum((fi.c_com + fj.c_com) * x.w) as t_com from hw x join hw y on y.v = x.v and y.machine <> x.machine join f fi on fi.machine = x.machine join f fj on fj.machine = y.machine group by 1),
vw as (select machine, sum(w) as w from hw group by 1)
select k.machine, round(vw.w + 2 * k.n_edges, 6) as mem_used, round(f.c_edge * k.n_edges + f.c_node * vw.w, 6) as t_cal, round(coalesce(com.t_com, 0), 6) as t_com from k join f on f.machine = k.machine join vw on vw.machine = k.machine left join com on com.machine = k.machine"""


def _customer_labels(s, d):
    return graphs.read(s, d, "customer").select((F.col("c_custkey") * 16 + 1).cast("long").alias("v"), F.col("c_mktsegment").alias("label"), F.char_length("c_mktsegment").cast("long").alias("bytes"))


query("ext_labelled_costs", O.setting("g2") + _LABELLED)(lambda s, d: extensions.labelled_costs(setting(s, d, "g2")[0], _customer_labels(s, d).select("v", "bytes"), setting(s, d, "g2")[1], 10.0).select("machine", r6("mem_used", "mem_used"), r6("t_cal", "t_cal"), r6("t_com", "t_com")))
query("base_mapping", _S + "select machine as part, n_edges, (row_number() over (order by n_edges desc, machine) - 1)::INTEGER as place from k")(lambda s, d: _mapping(s, d))


def _mapping(s, d):
    a, f = setting(s, d)
    c = costs.costs(a, f).select("machine", "n_edges")
    to = extensions.map_partitions(c, f, "sorted")
    order = sorted(range(len(f)), key=lambda i: (f.machines[i].c_edge, i))
    place = F.array_position(F.array(*[F.lit(i) for i in order]), F.col("to")) - 1
    return c.join(to.select(F.col("part").alias("machine"), F.col("machine").alias("to")), "machine").select(F.col("machine").alias("part"), "n_edges", place.cast("int").alias("place"))


# ------------------------------------------------------------------ workloads
_PR = f"with g as materialized ({O.EDGES['g4']}), arcs as materialized (select src as v, dst as u from g union all select dst, src from g), deg as materialized (select v, count(*) as n from arcs group by 1), c as (select count(*) as n from deg), r0 as materialized (select v, 1.0::DOUBLE / (select n from c) as r from deg)"
for _k in range(1, 6):
    _PR += f", r{_k} as materialized (select arcs.v, 0.15::DOUBLE / (select n from c) + 0.85::DOUBLE * sum(r / deg.n) as r from arcs join r{_k - 1} x on x.v = arcs.u join deg on deg.v = arcs.u group by arcs.v)"
query("pagerank", _PR + " select v, round(r, 9) as rank from r5")(lambda s, d: algos.pagerank(setting(s, d)[0], 5).select("v", F.round("rank", 9).alias("rank")))
query("triangles", f"with g as materialized ({O.EDGES['g5']}) select count(*) as n_triangles from g a join g b on a.dst = b.src join g c on c.src = a.src and c.dst = b.dst")(lambda s, d: algos.triangles(edges(s, d, "g5")))
_BFS = "with recursive g as materialized ({}), arcs as materialized (select src as v, dst as u from g union all select dst, src from g), b(v, level) as (select {}::BIGINT, 0 union select u, level + 1 from b join arcs on arcs.v = b.v where level < {}) select v, min(level)::INTEGER as level from b group by 1"
query("bfs_levels", _BFS.format(O.EDGES["g6"], 17, 3))(lambda s, d: algos.bfs(edges(s, d, "g6"), 17))
query("bfs_chain", "with recursive g as materialized ({}), arcs as materialized (select src as v, dst as u from g union all select dst, src from g), s as (select min(src) as v from g), b(v, level) as (select v, 0 from s union select u, level + 1 from b join arcs on arcs.v = b.v where level < 40) select v, min(level)::INTEGER as level from b group by 1".format(O.EDGES["g12"]))(lambda s, d: (lambda e: algos.bfs(e, e.agg(F.min("src")).first()[0]))(edges(s, d, "g12")))


def weighted(s, d):
    """Order-part edges with the largest price in cents as weight."""
    w = graphs.read(s, d, "lineitem").select((F.col("l_orderkey") * 16 + 2).cast("long").alias("a"), (F.col("l_partkey") * 16 + 3).cast("long").alias("b"), F.round(F.col("l_extendedprice") * 100).cast("long").alias("w"))
    return w.groupBy(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).agg(F.max("w").alias("weight"))


_W = "select least(a, b) as src, greatest(a, b) as dst, max(w) as weight from (select l_orderkey * 16 + 2 as a, l_partkey * 16 + 3 as b, round(l_extendedprice * 100)::BIGINT as w from lineitem) group by 1, 2"
query("weighted_edges", _W)(weighted)


def _chain_weights(s, d):
    return graphs.turn_chain(s, d).withColumn("weight", (F.col("src") + F.col("dst")) % 11 + 1)


query("sssp_dist", f"with recursive g as materialized (select src, dst, (src + dst) % 11 + 1 as w from ({O.EDGES['g12']})), arcs as materialized (select src as v, dst as u, w from g union all select dst, src, w from g), s as (select min(src) as v from g), b(v, dist, hops) as (select v, 0::BIGINT, 0 from s union select u, dist + w, hops + 1 from b join arcs on arcs.v = b.v where hops < 40) select v, min(dist)::BIGINT as dist from b group by 1")(
    lambda s, d: (lambda e: algos.sssp(e, e.agg(F.min("src")).first()[0]))(_chain_weights(s, d))
)
query("sssp_full")(lambda s, d: algos.sssp(weighted(s, d), 16 + 2))
query("components", f"with recursive g as materialized ({O.EDGES['g12']}), arcs as materialized (select src as v, dst as u from g union all select dst, src from g), b(v, r) as (select v, v from (select distinct v from arcs) union select u, r from b join arcs on arcs.v = b.v) select v, min(r) as component from b group by 1")(lambda s, d: algos.components(edges(s, d, "g12")))
_DENSE = "select step, max(t_cal) as t_cal, max(t_com) as t_com, {} as t from k cross join (values (1), (2), (3)) x(step) group by 1"
query("bsp_dense", _S + _DENSE.format("max(t)"))(lambda s, d: (lambda a, f: bsp.simulate(a, f, bsp.dense_activity(a, 3)))(*setting(s, d)))
query("bsp_mapreduce", _S + _DENSE.format("max(t_cal) + max(t_com)"))(lambda s, d: (lambda a, f: bsp.simulate(a, f, bsp.dense_activity(a, 3), "barrier_split"))(*setting(s, d)))
_SPARSE = """, act as materialized (select v, (v % 4 + 1)::INTEGER as step from (select distinct v from h)),
n as (select act.step, h.machine, count(*) as nv from act join h on h.v = act.v group by 1, 2), e as (select step, machine, count(*) as ne from (select distinct act.step, a.src, a.dst, a.machine from a join act on act.v = a.src or act.v = a.dst) group by 1, 2),
m as (select act.step, i.machine, sum(fi.c_com + fj.c_com) as t_com from act join h i on i.v = act.v join h j on j.v = i.v and j.machine <> i.machine join f fi on fi.machine = i.machine join f fj on fj.machine = j.machine group by 1, 2),
z as (select n.step, n.machine, f.c_node * nv + f.c_edge * coalesce(ne, 0) as t_cal, coalesce(t_com, 0) as t_com from n join f on f.machine = n.machine left join e on e.step = n.step and e.machine = n.machine left join m on m.step = n.step and m.machine = n.machine)
select step, max(t_cal) as t_cal, max(t_com) as t_com, max(t_cal + t_com) as t from z group by 1"""
query("bsp_sparse", O.setting("g6") + _SPARSE)(lambda s, d: (lambda a, f: bsp.simulate(a, f, a.select(F.explode(F.array("src", "dst")).alias("v")).distinct().withColumn("step", (F.col("v") % 4 + 1).cast("int"))))(*setting(s, d, "g6")))


@query("recursive_bfs", f"with recursive a as materialized ({O.EDGES['g12']}), b(v, level) as (select min(src), 0 from a union all select a.dst, level + 1 from b join a on a.src = b.v where level < 40) select v, level from b")
def _recursive(s, d):
    return s.sql("WITH RECURSIVE b(v, level) AS (SELECT min(src), 0 FROM {a} UNION ALL SELECT a.dst, level + 1 FROM b JOIN {a} a ON a.src = b.v WHERE level < 40) SELECT v, level FROM b", a=edges(s, d, "g12"))


_EXAMPLE = f"""with g as materialized ({O.EDGES['g6']}), n as (select count(*)::DOUBLE as n from g),
f as (select machine, size * n / 5 as mem, cost, com from (values (0, 7, 1.0::DOUBLE, 1.0::DOUBLE), (1, 7, 2.0, 2.0), (2, 5, 1.0, 1.0)) t(machine, size, cost, com), n),
a as materialized (select 1 as split, src, dst, ((src * 1000003 + dst * 7919) % 2147483647 % 3)::INTEGER as machine from g union all select 2, src, dst, (src // 16 % 3)::INTEGER from g),
h as materialized (select distinct split, v, machine from (select split, src as v, machine from a union all select split, dst, machine from a)),
e as (select split, machine, count(*) as ne from a group by 1, 2), v as (select split, machine, count(*) as nv from h group by 1, 2),
c as (select i.split, i.machine, sum(fi.com + fj.com) as t_com from h i join h j on i.split = j.split and i.v = j.v and i.machine <> j.machine join f fi on fi.machine = i.machine join f fj on fj.machine = j.machine group by 1, 2)
select s.split, f.machine, coalesce(ne, 0) * cost as t_cal, coalesce(t_com, 0.0) as t_com, coalesce(nv, 0) + 2 * coalesce(ne, 0) <= mem as fits
 from (values (1), (2)) s(split) cross join f left join e on e.split = s.split and e.machine = f.machine left join v on v.split = s.split and v.machine = f.machine left join c on c.split = s.split and c.machine = f.machine"""


@query("example_costs", _EXAMPLE)
def _example(s, d):
    """The running example's three machines, with memory to scale, and two splits of the
    customers' orders: edge by edge and by the lesser end."""
    e = edges(s, d, "g6")
    n = e.count()
    fleet = replace(machines.THREE, machines=tuple(replace(m, mem=m.mem * n / 5) for m in machines.THREE.machines))
    out = None
    for k, a in ((1, hash_placement(e, 3)), (2, e.withColumn("machine", (F.floor(F.col("src") / 16) % 3).cast("int")))):
        c = costs.costs(a, fleet).join(fleet.df(s).select("machine", "mem"), "machine")
        c = c.select(F.lit(k).alias("split"), "machine", "t_cal", "t_com", (F.col("mem_used") <= F.col("mem")).alias("fits"))
        out = c if out is None else out.unionByName(c)
    return out
