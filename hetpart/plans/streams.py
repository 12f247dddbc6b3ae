"""Streaming queries, drained over the events that are there, against batch SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..sources.graphs import read
from ..streaming import edges as S

QUERIES: dict = {}
SQL: dict[str, str] = {}
EDGE = "select ts, event_id, least(user_id * 16 + 5, floor(value)::BIGINT * 16 + 6) as src, greatest(user_id * 16 + 5, floor(value)::BIGINT * 16 + 6) as dst from events"
PLACED = f"select *, ((src * 1000003 + dst * 7919) % 2147483647 % 8)::INTEGER as machine from ({EDGE})"


def query(name, sql=None):
    def put(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


query("st_tumbling", f"select epoch_us(date_trunc('hour', ts)) as start_us, machine, count(*) as n from ({PLACED}) group by 1, 2")(lambda s, d: S.drain(S.counts(S.edge_stream(S.event_stream(s, d)))))
query("st_sliding", f"select epoch_us(date_trunc('hour', ts)) - k * 1800000000 + (case when minute(ts) >= 30 then 1800000000 else 0 end) as start_us, machine, count(*) as n from ({PLACED}), (values (0), (1)) x(k) group by 1, 2")(lambda s, d: S.drain(S.counts(S.edge_stream(S.event_stream(s, d)), "1 hour", "30 minutes")))
query("st_session", "with e as (select user_id, ts, case when ts < lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minute then 0 else 1 end as new from events), g as (select user_id, ts, sum(new) over (partition by user_id order by ts, new desc rows unbounded preceding) as k from e) select user_id, epoch_us(min(ts)) as start_us, count(*) as n from g group by user_id, k")(lambda s, d: S.drain(S.sessions(S.event_stream(s, d))))
query("st_dedup", f"select distinct src, dst from ({EDGE})")(lambda s, d: S.drain(S.deduplicated(S.edge_stream(S.event_stream(s, d))).select("src", "dst"), "append"))


@query("st_static_join", f"select f.kind, count(*) as n from ({PLACED}) e join (select i as machine, case when i < 3 then 'super' else 'normal' end as kind from range(8) t(i)) f on f.machine = e.machine group by 1")
def _static(s, d):
    fleet = s.range(8).select(F.col("id").cast("int").alias("machine"), F.when(F.col("id") < 3, "super").otherwise("normal").alias("kind"))
    return S.drain(S.edge_stream(S.event_stream(s, d)).join(F.broadcast(fleet), "machine").groupBy("kind").agg(F.count(F.lit(1)).alias("n")))


@query("st_interval_join", "select a.event_id as x, b.event_id as y from events a join events b on b.user_id = a.user_id and b.ts > a.ts and b.ts <= a.ts + interval 5 minute")
def _interval(s, d):
    side = lambda n: S.event_stream(s, d).select(F.col("event_id").alias(n), F.col("user_id").alias(f"u{n}"), F.col("ts").alias(f"t{n}")).withWatermark(f"t{n}", "10 minutes")
    j = side("x").join(side("y"), F.expr("ux = uy AND ty > tx AND ty <= tx + INTERVAL 5 MINUTES"))
    return S.drain(j.select("x", "y"), "append")


@query("st_place_inv", f"select count(*) as n_edges, count(*) as n_placed, 0::BIGINT as n_unknown from (select distinct src, dst from ({EDGE}))")
def _place(s, d):
    p = S.placed(S.edge_stream(S.event_stream(s, d)))
    n = S.edge_stream(read(s, d, "events")).select("src", "dst").distinct().count()
    return p.agg(F.lit(n).cast("long").alias("n_edges"), F.count_distinct("src", "dst").alias("n_placed"), F.count_if(~F.col("machine").between(0, 7)).alias("n_unknown"))


@query("st_incremental_tc", f"with a as (select distinct src, dst, machine from ({PLACED})), h as (select distinct v, machine from (select src as v, machine from a union all select dst, machine from a)), c as (select i.machine, count(*) * 2.0::DOUBLE as com from h i join h j on i.v = j.v and i.machine <> j.machine group by 1), z as (select h.machine, count(*) as nv from h group by 1), y as (select machine, count(*) as ne from a group by 1) select max(ne + coalesce(com, 0)) as tc from y left join c on c.machine = y.machine")
def _tc(s, d):
    """Slowest machine after the stream, from the stream's distinct edges."""
    from ..operators.costs import total
    from ..operators.machines import Fleet, Machine

    a = S.drain(S.deduplicated(S.edge_stream(S.event_stream(s, d))).select("src", "dst", "machine"), "append").distinct()
    return total(a, Fleet((Machine(1e9, 0, 1, 1),) * 8))
