"""DuckDB texts of graphs, placements and fleets, to build checks from."""

from __future__ import annotations

from ..functions.columns import mixed_sql
from ..sources.graphs import EDGES_PER_VERTEX, QUADRANTS


def pair(a: str, b: str, source: str) -> str:
    return f"select distinct least(a, b) as src, greatest(a, b) as dst from (select ({a})::BIGINT as a, ({b})::BIGINT as b from {source}) where a <> b"


LINES = "orders join lineitem on o_orderkey = l_orderkey"
SUCC = "(select user_id, lead(user_id) over (order by ts, event_id) as nxt from events) where nxt is not null"
TURNS = "(select conv_id, turn, lead(turn) over (partition by conv_id order by turn) as nxt from conversations) where nxt is not null"
TERMS = """(select page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) as t from pages)"""
TERM_ID = "(('0x' || substr(md5(t), 1, 8))::BIGINT * 16 + 9)"
NEAREST = """(select a.vec_id as x, b.vec_id as y, row_number() over (partition by a.vec_id order by list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) desc, b.vec_id) as r
 from embeddings a, embeddings b where a.vec_id <> b.vec_id) where r <= 8"""

EDGES = {
    "g1": pair("l_partkey * 16 + 3", "l_suppkey * 16 + 4", "lineitem"),
    "g2": pair("o_custkey * 16 + 1", "l_partkey * 16 + 3", LINES),
    "g3": pair("o_custkey * 16 + 1", "l_suppkey * 16 + 4", LINES),
    "g4": pair("l_orderkey * 16 + 2", "l_partkey * 16 + 3", "lineitem"),
    "g5": pair("x.l_partkey * 16 + 3", "y.l_partkey * 16 + 3", "lineitem x join lineitem y on x.l_orderkey = y.l_orderkey and x.l_partkey < y.l_partkey"),
    "g6": pair("o_custkey * 16 + 1", "o_orderkey * 16 + 2", "orders"),
    "g7": pair("user_id * 16 + 5", "floor(value)::BIGINT * 16 + 6", "events"),
    "g8": pair("user_id * 16 + 5", "nxt * 16 + 5", SUCC),
    "g9": pair("x * 16 + 7", "y * 16 + 7", NEAREST),
    "g10": pair("page_id * 16 + 8", TERM_ID, TERMS),
    "g12": pair("(conv_id * 1000 + turn) * 16 + 12", "(conv_id * 1000 + nxt) * 16 + 12", TURNS),
}


def grid(n: int, m: int) -> str:
    return f"select i as src, i + 1 as dst from range({n * m}) t(i) where i % {m} < {m - 1} union all select i, i + {m} from range({(n - 1) * m}) t(i)"


def rmat(scale: int, seed: int = 1) -> str:
    a, b, _ = QUADRANTS
    c = sum(QUADRANTS)
    draws = ", ".join(f"{mixed_sql('i', seed * 64 + k)} % 1000 as u{k}" for k in range(scale))
    src = " + ".join(f"(case when u{k} >= {a + b} then {1 << k} else 0 end)" for k in range(scale))
    dst = " + ".join(f"(case when (u{k} >= {a} and u{k} < {a + b}) or u{k} >= {c} then {1 << k} else 0 end)" for k in range(scale))
    return pair(src, dst, f"(select i, {draws} from range({EDGES_PER_VERTEX << scale}) t(i))")


def placed(graph: str, p: int = 30) -> str:
    return f"select src, dst, ((src * 1000003 + dst * 7919) % 2147483647 % {p})::INTEGER as machine from ({EDGES[graph]})"


def small_fleet(graph: str) -> str:
    e = f"(select count(*) from ({EDGES[graph]}))"
    return f"select i::INTEGER as machine, ceil((case when i < 10 then 1e7 else 3e6 end)::DOUBLE * {e} / 33099465) as mem, (case when i < 10 then 10 else 5 end)::DOUBLE as c_node, (case when i < 10 then 15 else 10 end)::DOUBLE as c_edge, (case when i < 10 then 15 else 10 end)::DOUBLE as c_com, case when i < 10 then 'super' else 'normal' end as kind from range(30) t(i)"


def setting(graph: str, p: int = 30) -> str:
    """Common tables: a (assignment), f (fleet), h (holders), s (sizes), k (costs).
    Communication is the pairwise definition, on purpose unlike the engine's."""
    return f"""with a as materialized ({placed(graph, p)}), f as materialized ({small_fleet(graph)}),
h as materialized (select distinct v, machine from (select src as v, machine from a union all select dst, machine from a)),
s as (select f.machine, coalesce(nv, 0) as n_vertices, coalesce(ne, 0) as n_edges from f
 left join (select machine, count(*) as nv from h group by 1) x on x.machine = f.machine left join (select machine, count(*) as ne from a group by 1) y on y.machine = f.machine),
c as (select i.machine, sum(fi.c_com + fj.c_com) as t_com from h i join h j on i.v = j.v and i.machine <> j.machine join f fi on fi.machine = i.machine join f fj on fj.machine = j.machine group by 1),
k as (select s.machine, f.kind, s.n_vertices, s.n_edges, (s.n_vertices + 2 * s.n_edges)::DOUBLE as mem_used, f.c_edge * s.n_edges + f.c_node * s.n_vertices as t_cal, coalesce(c.t_com, 0)::DOUBLE as t_com, f.c_edge * s.n_edges + f.c_node * s.n_vertices + coalesce(c.t_com, 0) as t
 from s join f on f.machine = s.machine left join c on c.machine = s.machine)
"""


def count_terms(graph: str) -> str:
    """Common tables: n (e, v), t (machine, cost, cap)."""
    return f"""with g as materialized ({EDGES[graph]}), n as (select count(*)::DOUBLE as e, (select count(distinct v) from (select src as v from g union all select dst from g))::DOUBLE as v from g),
f as ({small_fleet(graph)}), t as (select machine, c_edge + v / e * c_node as cost, mem / (2 + v / e) as cap from f, n)
"""


def waterfill(graph: str) -> str:
    return count_terms(graph) + """, o as (select *, coalesce(sum(cap) over (order by cost * cap, machine rows between unbounded preceding and 1 preceding), 0) as filled, sum(1 / cost) over (order by cost * cap, machine rows between current row and unbounded following) as speed from t),
l as (select (e - filled) / speed as level from o, n where (e - filled) / speed <= cost * cap * (1 + 1e-12) order by cost * cap, machine limit 1)
"""
