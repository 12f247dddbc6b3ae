"""Directed, labelled and vertex-centric graphs, and conversions between both partitions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut
from .capacity import Infeasible
from .costs import replicas
from .machines import Fleet
from .rounds import by_machine, quota_rank


def directed_degrees(arcs: DataFrame) -> DataFrame:
    """v, n_in, n_out."""
    ends = arcs.select(F.col("src").alias("v"), F.lit(1).alias("o"), F.lit(0).alias("i")).unionByName(arcs.select(F.col("dst").alias("v"), F.lit(0).alias("o"), F.lit(1).alias("i")))
    return ends.groupBy("v").agg(F.sum("i").alias("n_in"), F.sum("o").alias("n_out"))


def attach_labels(assign: DataFrame, labels: DataFrame) -> DataFrame:
    """machine, v, label columns: labels follow the structure to each holder."""
    return replicas(assign).select("v", F.explode("machines").alias("machine")).join(labels, "v")


def label_volume(assign: DataFrame, labels: DataFrame) -> DataFrame:
    """Label bytes that each machine stores; labels: v, bytes."""
    return attach_labels(assign, labels).groupBy("machine").agg(F.count(F.lit(1)).alias("n_labels"), F.sum("bytes").alias("bytes"))


def labelled_costs(assign: DataFrame, labels: DataFrame, fleet: Fleet, unit: float = 1.0) -> DataFrame:
    """Costs of a labelled graph: a vertex's labels (v, bytes) weigh as much memory and
    compute as bytes / unit further vertices on each machine that holds it, as what is sent
    between its holders grows by the same factor. machine, mem_used, t_cal, t_com, t."""
    cost = fleet.values("c_com")
    held = replicas(assign).join(labels.groupBy("v").agg(F.sum("bytes").alias("bytes")), "v", "left")
    held = held.withColumn("w", 1 + F.coalesce("bytes", F.lit(0)) / unit).withColumn("all", F.aggregate("machines", F.lit(0.0), lambda a, m: a + F.get(cost, m)))
    each = held.select(F.explode("machines").alias("machine"), F.size("machines").alias("n"), "all", "w")
    com = F.when(F.col("n") > 1, (F.col("n") - 2) * F.get(cost, F.col("machine")) + F.col("all")).otherwise(0.0) * F.col("w")
    v = each.groupBy("machine").agg(F.sum("w").alias("w"), F.sum(com).alias("t_com"))
    e = assign.groupBy("machine").agg(F.count(F.lit(1)).alias("n_edges"))
    out = fleet.df(assign.sparkSession).join(e, "machine", "left").join(v, "machine", "left").na.fill(0, ["n_edges", "w", "t_com"])
    out = out.withColumn("mem_used", fleet.m_node * F.col("w") + fleet.m_edge * F.col("n_edges")).withColumn("t_cal", F.col("c_edge") * F.col("n_edges") + F.col("c_node") * F.col("w"))
    return out.select("machine", "mem_used", "t_cal", "t_com", (F.col("t_cal") + F.col("t_com")).alias("t"))


def to_vertex_partition(assign: DataFrame, capacity: int | None = None, p: int | None = None) -> DataFrame:
    """v, machine: where most of a vertex's edges are (share of deg + 1), least machine on
    ties. With a capacity, a machine takes no more vertices: in rounds, each vertex asks the
    best of its machines that has room (any with room, by hash, if none of them has), and a
    machine takes those of the best scores. Ranks come from counts of score bands, not from
    one task a machine. Raises Infeasible if the capacities don't hold all vertices."""
    ends = assign.select(F.explode(F.array("src", "dst")).alias("v"), "machine")
    part = ends.groupBy("v", "machine").agg(F.count(F.lit(1)).alias("n"))
    deg = part.groupBy("v").agg(F.sum("n").alias("degree"))
    score = part.join(deg, "v").withColumn("score", F.col("n") / (F.col("degree") + 1))
    best = F.max_by("machine", F.struct("score", -F.col("machine")))
    if capacity is None:
        return score.groupBy("v").agg(best.alias("machine"))
    score = cut(score)
    p = p or (score.agg(F.max("machine")).first()[0] or 0) + 1
    left = cut(deg.select("v"))
    n = left.count()
    if n > p * capacity:
        raise Infeasible(f"{n} vertices; {p} machines of {capacity} hold {p * capacity}")
    rooms, out = [capacity] * p, None
    while not left.isEmpty():
        open_ = [i for i in range(p) if rooms[i]]
        asked = score.where(F.col("machine").isin(open_)).join(left, "v", "left_semi").groupBy("v").agg(best.alias("machine"), F.max("score").alias("score"))
        anywhere = F.get(F.array(*[F.lit(i) for i in open_]), F.pmod(F.xxhash64("v"), F.lit(len(open_))).cast("int"))
        asked = left.join(asked, "v", "left").select("v", F.coalesce("machine", anywhere).alias("machine"), F.coalesce("score", F.lit(0.0)).alias("score"))
        ranked = quota_rank(asked, "machine", F.xxhash64("v"), F.floor((1 - F.col("score")) * 64))
        got = cut(ranked.where(F.col("rank") <= by_machine(rooms, "long")).select("v", "machine"))
        for r in got.groupBy("machine").count().collect():  # p rows
            rooms[r["machine"]] -= r["count"]
        out = got if out is None else out.unionByName(got)
        left = cut(left.join(got, "v", "left_anti"))
    return out if out is not None else score.select("v", "machine")


def edges_at_homes(edges: DataFrame, homes: DataFrame) -> DataFrame:
    """src, dst, machine: a vertex partition's edges, stored at the homes of both ends, once
    where these are one."""
    a, b = homes.select(F.col("v").alias("src"), F.col("machine").alias("ms")), homes.select(F.col("v").alias("dst"), F.col("machine").alias("md"))
    both = edges.join(a, "src").join(b, "dst")
    return both.select("src", "dst", F.explode(F.array_distinct(F.array("ms", "md"))).alias("machine"))


def to_edge_partition(edges: DataFrame, homes: DataFrame, seed: int = 1) -> DataFrame:
    """Each edge at the home of one end, by a seeded arithmetic coin."""
    a, b = homes.select(F.col("v").alias("src"), F.col("machine").alias("ms")), homes.select(F.col("v").alias("dst"), F.col("machine").alias("md"))
    coin = (F.col("src") * 31 + F.col("dst") * 17 + seed) % 2 == 0
    return edges.join(a, "src").join(b, "dst").select("src", "dst", F.when(coin, F.col("ms")).otherwise(F.col("md")).alias("machine"))


def map_partitions(costs: DataFrame, fleet: Fleet, how: str = "sorted", seed: int = 1) -> DataFrame:
    """part, machine: partitions of a homogeneous split dealt to machines at random, or the
    largest to the fastest. p rows."""
    spark, rows = costs.sparkSession, sorted((-r["n_edges"], r["machine"]) for r in costs.select("machine", "n_edges").collect())
    if how == "sorted":
        order = sorted(range(len(fleet)), key=lambda i: (fleet.machines[i].c_edge, i))
    else:
        order = sorted(range(len(fleet)), key=lambda i: ((i + 1) * 7919 + seed * 104729) % 1009)
    return spark.createDataFrame([(part, m) for (_, part), m in zip(rows, order, strict=True)], "part int, machine int")
