"""Relational surroundings of the methods on the given tables, as Spark plans.

Where Spark SQL and DuckDB read the same text alike, the text is shared by name; the
engines differ. Frames are passed by name, so nothing is registered in the session."""

from __future__ import annotations

import re

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators.partitioners import hash_placement
from ..sources import files, graphs
from ..sources.graphs import read
from . import oracle as O

QUERIES: dict = {}
SQL: dict[str, str] = {}
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def query(name, sql=None):
    def put(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


def both(name: str, sql: str, spark_sql: str | None = None) -> None:
    """One relational query; spark_sql where the dialects differ."""
    text = spark_sql or sql
    used = [t for t in TABLES if re.search(rf"\b{t}\b", text)]
    for t in used:
        text = re.sub(rf"(?<![\w.{{]){t}\b(?!\w|\.)", "{" + t + "}", text)
    query(name, sql)(lambda s, d: s.sql(text, **{t: read(s, d, t) for t in used}))


# scans: counts and key bounds; only the keys are read
_KEYS = dict(region="r_regionkey", nation="n_nationkey", customer="c_custkey", supplier="s_suppkey", part="p_partkey", orders="o_orderkey", lineitem="l_orderkey", events="event_id", documents="doc_id", embeddings="vec_id", pages="page_id", benchmark="item_id", labels="doc_id", conversations="conv_id")
for _t, _k in _KEYS.items():
    query(f"scan_{_t}", f"select count(*) as n, min({_k})::BIGINT as lo, max({_k})::BIGINT as hi from {_t}")(lambda s, d, t=_t, k=_k: read(s, d, t).agg(F.count(F.lit(1)).alias("n"), F.min(k).cast("long").alias("lo"), F.max(k).cast("long").alias("hi")))

query("proj_edge_canonical", O.EDGES["g1"])(graphs.part_supplier)
both("filter_shipdate", "select distinct l_partkey * 16 + 3 as src, l_suppkey * 16 + 4 as dst from lineitem where l_shipdate >= timestamp '1995-01-01' and l_shipdate < timestamp '1996-01-01' and l_returnflag = 'N'")
query("filter_degree_core", f"with g as materialized ({O.EDGES['g4']}), d as (select v from (select src as v from g union all select dst from g) group by 1 having count(*) >= 5) select src, dst from g where src in (select v from d) and dst in (select v from d)")(lambda s, d: _core(s, d))


def _core(s, d, k=5):
    e = graphs.order_part(s, d)
    keep = graphs.degrees(e).where(F.col("degree") >= k).select("v")
    return e.join(keep.withColumnRenamed("v", "src"), "src", "left_semi").join(keep.withColumnRenamed("v", "dst"), "dst", "left_semi").select("src", "dst")


query("join_inner", O.EDGES["g2"])(graphs.customer_part)
both("join_left", "select c_custkey, count(o_orderkey) as n from customer left join orders on o_custkey = c_custkey group by c_custkey")
both("join_right", "select o_orderkey, c_custkey from customer right join orders on o_custkey = c_custkey and c_acctbal > 5000")
_A, _B = O.placed("g4", 5), O.placed("g4", 7)
query("join_full", f"select count(*) filter (a.machine = b.machine) as same, count(*) filter (a.machine <> b.machine) as moved, count(*) filter (a.src is null) as only_b, count(*) filter (b.src is null) as only_a from (select * from ({_A}) where src % 3 <> 0) a full join (select * from ({_B}) where src % 3 <> 1) b on a.src = b.src and a.dst = b.dst")(lambda s, d: _full(s, d))


def _full(s, d):
    e = graphs.order_part(s, d)
    a = hash_placement(e, 5).where("src % 3 <> 0").withColumnRenamed("machine", "a")
    b = hash_placement(e, 7).where("src % 3 <> 1").withColumnRenamed("machine", "b")
    return a.join(b, ["src", "dst"], "full_outer").agg(F.count_if(F.col("a") == F.col("b")).alias("same"), F.count_if(F.col("a") != F.col("b")).alias("moved"), F.count_if(F.col("a").isNull()).alias("only_b"), F.count_if(F.col("b").isNull()).alias("only_a"))


both("join_semi", "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey)")
both("join_anti", "select o_orderkey from orders where not exists (select 1 from lineitem where l_orderkey = o_orderkey and l_quantity > 45)")
query("join_cross", "select i::INTEGER as machine, n_nationkey, ((i + 1) * (n_nationkey + 1))::BIGINT as cost from range(9) t(i), nation")(lambda s, d: s.range(9).select(F.col("id").cast("int").alias("machine")).crossJoin(F.broadcast(read(s, d, "nation").select("n_nationkey"))).select("machine", "n_nationkey", ((F.col("machine") + 1) * (F.col("n_nationkey") + 1)).cast("long").alias("cost")))
_NATION = "select c_custkey, n_name from customer join nation on n_nationkey = c_nationkey"
for _h in ("broadcast", "merge", "shuffle_hash"):
    query(f"join_{_h}", _NATION)(lambda s, d, h=_h: read(s, d, "customer").join(read(s, d, "nation").hint(h), F.col("n_nationkey") == F.col("c_nationkey")).select("c_custkey", "n_name"))
both("join_theta", "select a.n_nationkey as x, b.n_nationkey as y from nation a join nation b on a.n_nationkey % 7 > b.n_nationkey % 7 and a.n_nationkey < b.n_nationkey")
both("join_range", "select o_orderkey, s_suppkey from orders join supplier on floor(o_totalprice / 1000) = s_suppkey and o_totalprice between s_suppkey * 1000 and s_suppkey * 1000 + 500")
_ASOF = "select event_id, before from (select event_id, event_type, lag(event_id) over (partition by user_id order by ts, event_id) as before from events) where event_type = (select min(event_type) from events)"


@query("join_asof", _ASOF)
def _asof(s, d):
    """Last event of the same user before each event of one type: union of both sides and
    the last id seen, one shuffle by user."""
    e = read(s, d, "events").select("user_id", "ts", "event_id", "event_type")
    kind = e.agg(F.min("event_type").alias("kind"))
    sides = e.withColumn("is_left", F.lit(0)).withColumn("seen", F.col("event_id")).unionByName(e.join(F.broadcast(kind), F.col("event_type") == F.col("kind"), "left_semi").withColumn("is_left", F.lit(1)).withColumn("seen", F.lit(None).cast("long")))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id", F.desc("is_left")).rowsBetween(Window.unboundedPreceding, -1)
    return sides.withColumn("before", F.last("seen", ignorenulls=True).over(w)).where("is_left = 1").select("event_id", "before")


@query("join_interval", "select distinct least(a.user_id, b.user_id) as x, greatest(a.user_id, b.user_id) as y from events a join events b on b.ts between a.ts and a.ts + interval 60 second and a.user_id <> b.user_id")
def _interval(s, d, seconds=60):
    """Users active within a minute of each other: minutes as keys, each event in its own
    and the next one."""
    e = read(s, d, "events").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    size = seconds * 1_000_000
    a = e.select(F.col("user_id").alias("u"), F.col("us").alias("a"), F.explode(F.array(F.floor(F.col("us") / size), F.floor(F.col("us") / size) + 1)).alias("m"))
    b = e.select(F.col("user_id").alias("v"), F.col("us").alias("b"), F.floor(F.col("us") / size).alias("m"))
    return a.join(b, "m").where((F.col("b") >= F.col("a")) & (F.col("b") <= F.col("a") + size) & (F.col("u") != F.col("v"))).select(F.least("u", "v").alias("x"), F.greatest("u", "v").alias("y")).distinct()


query("join_self", O.EDGES["g5"])(graphs.part_part)
query("join_lateral", f"select v, machine, (count(*) over (partition by v))::INTEGER as holders from (select distinct v, machine from (select src as v, machine from ({_A}) union all select dst, machine from ({_A})))")(lambda s, d: _lateral(s, d))


def _lateral(s, d):
    from ..operators.costs import replicas

    return replicas(hash_placement(graphs.order_part(s, d), 5)).select("v", F.explode("machines").alias("machine"), F.size("machines").alias("holders"))


# aggregates
both("agg_basic", "select l_suppkey, count(*) as n, sum(cast(l_quantity as bigint)) as qty, sum(cast(round(l_extendedprice * 100) as bigint)) as cents, min(l_discount) as lo, max(l_tax) as hi from lineitem group by l_suppkey".replace("sum(cast(l_quantity as bigint))", "cast(sum(cast(l_quantity as bigint)) as bigint)").replace("sum(cast(round(l_extendedprice * 100) as bigint))", "cast(sum(cast(round(l_extendedprice * 100) as bigint)) as bigint)"))
both("agg_distinct", "select l_suppkey, count(distinct l_partkey) as parts, count(distinct l_orderkey) as orders_ from lineitem group by l_suppkey")


@query("agg_approx", "select true as within")
def _approx(s, d):
    r = read(s, d, "lineitem").agg(F.count_distinct("l_partkey").alias("a"), F.approx_count_distinct("l_partkey", 0.02).alias("b"))
    return r.select((F.abs(F.col("b") / F.col("a") - 1) <= 0.1).alias("within"))


_CUST = "customer join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey"
for _n, _g in (("cube", "cube (r_name, c_mktsegment)"), ("rollup", "rollup (r_name, n_name)"), ("gsets", "grouping sets ((r_name), (c_mktsegment), (r_name, c_mktsegment), ())")):
    _c = "r_name, n_name" if _n == "rollup" else "r_name, c_mktsegment"
    both(f"agg_{_n}", f"select {_c}, count(*) as n, cast(sum(cast(round(c_acctbal * 100) as bigint)) as bigint) as cents from {_CUST} group by {_g}")
query("agg_pivot", "select l_linestatus, count(*) filter (l_returnflag = 'A') as A, count(*) filter (l_returnflag = 'N') as N, count(*) filter (l_returnflag = 'R') as R from lineitem group by 1")(lambda s, d: read(s, d, "lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count(F.lit(1))).fillna(0))
query("agg_collect", "select l_suppkey, array_to_string(list_sort(list(distinct l_linestatus || l_returnflag)), ',') as kinds from lineitem group by 1")(lambda s, d: read(s, d, "lineitem").groupBy("l_suppkey").agg(F.array_join(F.sort_array(F.collect_set(F.concat("l_linestatus", "l_returnflag"))), ",").alias("kinds")))
query("agg_minby", "select p_brand, arg_min(p_partkey, p_retailprice * 1000000 + p_partkey) as cheapest from part group by 1")(lambda s, d: read(s, d, "part").groupBy("p_brand").agg(F.min_by("p_partkey", F.col("p_retailprice") * 1000000 + F.col("p_partkey")).alias("cheapest")))
query("agg_quantile", f"with g as ({O.EDGES['g4']}), d as (select v, count(*) as n from (select src as v from g union all select dst from g) group by 1) select round(quantile_cont(n, 0.5), 6) as p50, round(quantile_cont(n, 0.9), 6) as p90 from d")(lambda s, d: graphs.degrees(graphs.order_part(s, d)).agg(F.round(F.percentile("degree", 0.5), 6).alias("p50"), F.round(F.percentile("degree", 0.9), 6).alias("p90")))
query("agg_regr", f"with g as ({O.EDGES['g4']}), d as (select n, count(*) as k from (select v, count(*) as n from (select src as v from g union all select dst from g) group by 1) group by 1) select round(regr_slope(ln(k), ln(n)), 6) as slope, round(corr(ln(k), ln(n)), 6) as corr from d")(
    lambda s, d: graphs.degrees(graphs.order_part(s, d)).groupBy("degree").agg(F.count(F.lit(1)).alias("k")).agg(F.round(F.regr_slope(F.ln("k"), F.ln("degree")), 6).alias("slope"), F.round(F.corr(F.ln("k"), F.ln("degree")), 6).alias("corr"))
)
query("agg_bitor", f"select v, bit_or(1::BIGINT << machine) as mask from (select src as v, machine from ({_A}) union all select dst, machine from ({_A})) group by 1")(lambda s, d: hash_placement(graphs.order_part(s, d), 5).select(F.explode(F.array("src", "dst")).alias("v"), "machine").groupBy("v").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("machine"))).alias("mask")))
both("agg_having", "select l_suppkey, count(*) as n from lineitem group by l_suppkey having count(*) > (select 1.2 * count(*) / count(distinct l_suppkey) from lineitem)")

# windows
for _f, _e in (("rownum", "row_number()"), ("rank", "rank()"), ("dense", "dense_rank()"), ("ntile", "ntile(4)"), ("pct", "percent_rank()")):
    _o = "p_size" if _f in ("rank", "dense", "pct") else "p_size, p_partkey"
    both(f"win_{_f}", f"select p_partkey, {'round(' if _f == 'pct' else 'cast('}{_e} over (partition by p_brand order by {_o}){', 9)' if _f == 'pct' else ' as bigint)'} as r from part")
both("win_lag", "select o_orderkey, lag(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) as before from orders")
both("win_lead", "select o_orderkey, lead(o_orderkey, 2) over (partition by o_custkey order by o_orderdate, o_orderkey) as after from orders")
both("win_firstlast", "select o_orderkey, first_value(o_orderkey) over w as f, last_value(o_orderkey) over w as l from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and unbounded following)")
both("win_rows", "select l_orderkey, l_linenumber, cast(sum(cast(l_quantity as bigint)) over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_extendedprice rows between 2 preceding and current row) as bigint) as q from lineitem")
_RANGE = "select o_orderkey, count(*) over (partition by o_custkey order by cast(o_totalprice as bigint) range between 50000 preceding and current row) as n from orders"
# DuckDB's cast rounds, halves to the even side; Spark's cuts off
both("win_range", _RANGE, _RANGE.replace("o_totalprice", "rint(o_totalprice)"))
query("win_prefix", O.waterfill("g4") + "select machine, round(filled, 4) as filled, round(speed, 9) as speed from o")(lambda s, d: _prefix(s, d))


def _prefix(s, d):
    from ..operators import capacity, machines
    from ..operators.partitioners import graph_size

    n, v = graph_size(graphs.order_part(s, d))
    w = Window.orderBy(F.col("cost") * F.col("cap"), "machine")
    t = capacity.terms_df(machines.small(n), s, n, v)
    return t.select("machine", F.round(F.coalesce(F.sum("cap").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)), 4).alias("filled"), F.round(F.sum(1 / F.col("cost")).over(w.rowsBetween(0, Window.unboundedFollowing)), 9).alias("speed"))


both("sort_topk", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 10")
both("sort_topk_group", "select p_brand, p_partkey from (select p_brand, p_partkey, row_number() over (partition by p_brand order by p_retailprice desc, p_partkey) as r from part) t where r <= 3")

# sets
_X, _Y = "select l_partkey, l_suppkey from lineitem where l_returnflag = 'A'", "select l_partkey, l_suppkey from lineitem where l_returnflag = 'R'"
for _n, _op in (("union", "union"), ("unionall", "union all"), ("intersect", "intersect"), ("except", "except"), ("intersectall", "intersect all"), ("exceptall", "except all")):
    both(f"set_{_n}", f"{_X} {_op} {_Y}")

# subqueries
both("sub_exists", "select o_orderkey from orders where exists (select 1 from lineitem where l_orderkey = o_orderkey and l_discount > 0.09)")
both("sub_in", "select count(*) as n from lineitem where l_partkey in (select p_partkey from part where p_size > 40)")
both("sub_scalar", "select count(*) as n from orders where o_totalprice > (select avg(o_totalprice) from orders)")
both("sub_correlated", "select count(*) as n from lineitem l where l_quantity > (select avg(l_quantity) from lineitem where l_partkey = l.l_partkey)", "select count(*) as n from lineitem l join (select l_partkey as k, avg(l_quantity) as a from lineitem group by l_partkey) m on m.k = l.l_partkey where l_quantity > a")

# scalar functions
both("fn_math", "select p_partkey, floor(p_retailprice) as f, ceil(p_retailprice) as c, round(ln(p_retailprice), 9) as l, p_partkey % 7 as m, greatest(p_size, 10) as g, least(p_size, 40) as h from part", "select p_partkey, floor(p_retailprice) as f, ceil(p_retailprice) as c, round(ln(p_retailprice), 9) as l, p_partkey % 7 as m, greatest(p_size, 10) as g, least(p_size, 40) as h from part")
SQL["fn_math"] = SQL["fn_math"].replace("floor(p_retailprice)", "floor(p_retailprice)::BIGINT").replace("ceil(p_retailprice)", "ceil(p_retailprice)::BIGINT")
both("fn_string", "select p_partkey, upper(p_name) as u, length(p_name) as n, substr(p_type, 1, 5) as s, replace(p_brand, '#', '-') as b, reverse(p_type) as r from part")
SQL["fn_string"] = SQL["fn_string"].replace("length(p_name)", "length(p_name)::INTEGER")
query("fn_regexp", "select page_id, regexp_extract(url, '^https?://([^/]+)', 1) as host, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))::INTEGER as links from pages")(lambda s, d: read(s, d, "pages").select("page_id", F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("links")))
query("fn_date", "select o_orderkey, year(o_orderdate)::INTEGER as y, month(o_orderdate)::INTEGER as m, epoch_us(date_trunc('month', o_orderdate)) as us from orders")(lambda s, d: read(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.unix_micros(F.date_trunc("month", F.col("o_orderdate").cast("timestamp"))).alias("us")))


@query("fn_array", f"with h1 as (select v, list_sort(list(distinct machine)) as m from (select src as v, machine from ({_A}) union all select dst, machine from ({_A})) group by 1), e as ({O.EDGES['g4']}) select src, dst, len(list_intersect(x.m, y.m))::INTEGER as both_, len(list_distinct(list_concat(x.m, y.m)))::INTEGER as either_ from e join h1 x on x.v = src join h1 y on y.v = dst")
def _array(s, d):
    from ..operators.costs import replicas

    e = graphs.order_part(s, d)
    h = replicas(hash_placement(e, 5))
    x = e.join(h.select(F.col("v").alias("src"), F.col("machines").alias("x")), "src").join(h.select(F.col("v").alias("dst"), F.col("machines").alias("y")), "dst")
    return x.select("src", "dst", F.size(F.array_intersect("x", "y")).alias("both_"), F.size(F.array_union("x", "y")).alias("either_"))


query("fn_map", "select n_nationkey, (n_nationkey % 3) * 10 as cost from nation")(lambda s, d: read(s, d, "nation").select("n_nationkey", F.element_at(F.map_from_arrays(F.array(F.lit(0), F.lit(1), F.lit(2)), F.array(F.lit(0), F.lit(10), F.lit(20))), F.col("n_nationkey") % 3).alias("cost")))
query("fn_struct", "select p_brand, min(p_retailprice) as price, arg_min(p_partkey, (p_retailprice, p_partkey)) as part from part group by 1")(lambda s, d: read(s, d, "part").groupBy("p_brand").agg(F.min(F.struct("p_retailprice", "p_partkey")).alias("x")).select("p_brand", F.col("x.p_retailprice").alias("price"), F.col("x.p_partkey").alias("part")))
query("fn_json", "select event_id, (props->>'$.k')::BIGINT as k from events")(lambda s, d: read(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")))
both("fn_null_case", "select c_custkey, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') as s, case when c_acctbal < 0 then 'low' when c_acctbal < 5000 then 'mid' else 'high' end as band, cast(round(c_acctbal * 100) as bigint) as cents from customer")
query("fn_hash", "select l_orderkey, l_linenumber, (l_orderkey * 1000003 + l_linenumber * 7919) % 2147483647 % 30 as m from lineitem")(lambda s, d: read(s, d, "lineitem").select("l_orderkey", "l_linenumber", ((F.col("l_orderkey") * 1000003 + F.col("l_linenumber") * 7919) % 2147483647 % 30).alias("m")))

# UDFs
query("udf_arrow", "select n_nationkey, (list_sum(list_transform(range(1, length(n_name) + 1), lambda i: i * ascii(substr(n_name, i::INT, 1)))) % 2147483647)::BIGINT as code from nation")(lambda s, d: _udf(s, d))


def _udf(s, d):
    from ..functions.udfs import shingle_code

    return read(s, d, "nation").select("n_nationkey", shingle_code("n_name").alias("code"))


query("udaf_pandas", O.setting("g4") + "select max(t) as tc from k")(lambda s, d: _udaf(s, d))


def _udaf(s, d):
    from ..functions.udfs import slowest
    from ..operators import costs
    from .core import setting

    return costs.costs(*setting(s, d)).select("t_cal", "t_com").agg(slowest("t_cal", "t_com").alias("tc"))


@query("udtf_replicas", f"select v, machine, (count(*) over (partition by v))::INTEGER as holders from (select distinct v, machine from (select src as v, machine from ({_A}) union all select dst, machine from ({_A})))")
def _udtf(s, d):
    from ..functions.udfs import register
    from ..operators.costs import replicas

    register(s)
    return s.sql("SELECT t.* FROM {r} r, LATERAL expand_replicas(r.v, r.machines) t", r=replicas(hash_placement(graphs.order_part(s, d), 5)))


@query("udtf_waterfill", "select * from (values (0, 20.0::DOUBLE), (1, 10.0::DOUBLE)) t(machine, amount)")
def _udtf_fill(s, d):
    from ..functions.udfs import register

    register(s)
    return s.sql("SELECT * FROM waterfill(array(1D, 2D), array(100D, 100D), 30)")


@query("grouped_map", "select o_custkey, count(*) as n from orders group by 1")
def _grouped(s, d):
    import pyarrow as pa

    return read(s, d, "orders").select("o_custkey").groupBy("o_custkey").applyInArrow(lambda t: pa.table({"o_custkey": [t.column(0)[0].as_py()], "n": [t.num_rows]}), "o_custkey long, n long")


# sinks
@query("csv_edges_roundtrip", O.EDGES["g6"])
def _csv(s, d):
    from ..session import fresh_folder

    at = fresh_folder(s, "edges")
    files.write_edge_list(graphs.customer_order(s, d), at)
    return files.read_edge_list(s, at)


@query("partitioned_write", O.placed("g4", 8))
def _written(s, d):
    from ..session import fresh_folder

    at = fresh_folder(s, "assignment")
    a = hash_placement(graphs.order_part(s, d), 8)
    files.write_assignment(a.withColumn("seq", F.col("src")), at)
    return files.read_assignment(s, at).select("src", "dst", "machine")


for _f in ("orc", "json"):
    def _format(s, d, f=_f):
        from ..session import fresh_folder

        at = fresh_folder(s, f)
        graphs.customer_order(s, d).write.format(f).save(at)
        return s.read.format(f).schema("src long, dst long").load(at)

    query(f"{_f}_edges_roundtrip", O.EDGES["g6"])(_format)
