"""Cost measures of an assignment (src, dst, machine).

A machine's compute time is c_edge for each of its edges and c_node for each vertex they
touch; its communication time is, for each vertex it shares, the sum over the other
holders of both ends' cost. That pairwise sum equals (|S| - 2) c_i + sum of c over the
holders S, so one aggregate over replicas gives it, and a hub that all machines hold
costs p terms, not p squared.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .machines import Fleet


def replicas(assign: DataFrame) -> DataFrame:
    """(v, machines): the sorted machines that hold each vertex; one shuffle, combined before."""
    ends = assign.select(F.explode(F.array("src", "dst")).alias("v"), "machine")
    return ends.groupBy("v").agg(F.sort_array(F.collect_set("machine")).alias("machines"))


def sizes(assign: DataFrame, fleet: Fleet) -> DataFrame:
    """machine, n_vertices, n_edges; machines without edges have zeros."""
    v = replicas(assign).select(F.explode("machines").alias("machine")).groupBy("machine").agg(F.count(F.lit(1)).alias("n_vertices"))
    e = assign.groupBy("machine").agg(F.count(F.lit(1)).alias("n_edges"))
    spark = assign.sparkSession
    out = fleet.df(spark).select("machine").join(e, "machine", "left").join(v, "machine", "left")
    return out.select("machine", F.coalesce("n_vertices", F.lit(0).cast("long")).alias("n_vertices"), F.coalesce("n_edges", F.lit(0).cast("long")).alias("n_edges"))


def memory(assign: DataFrame, fleet: Fleet) -> DataFrame:
    used = fleet.m_node * F.col("n_vertices") + fleet.m_edge * F.col("n_edges")
    return sizes(assign, fleet).join(F.broadcast(fleet.df(assign.sparkSession)), "machine").select("machine", used.alias("mem_used"), "mem", (used <= F.col("mem")).alias("fits"))


def t_cal(assign: DataFrame, fleet: Fleet) -> DataFrame:
    return sizes(assign, fleet).join(F.broadcast(fleet.df(assign.sparkSession)), "machine").select("machine", (F.col("c_edge") * F.col("n_edges") + F.col("c_node") * F.col("n_vertices")).alias("t_cal"))


def t_com(assign: DataFrame, fleet: Fleet) -> DataFrame:
    cost = fleet.values("c_com")
    shared = replicas(assign).where(F.size("machines") > 1).withColumn("all", F.aggregate("machines", F.lit(0.0), lambda a, m: a + F.get(cost, m)))
    each = shared.select(F.explode("machines").alias("machine"), (F.size("machines") - 2).alias("n"), "all")
    sums = each.groupBy("machine").agg(F.sum(F.col("n") * F.get(cost, F.col("machine")) + F.col("all")).alias("t_com"))
    return fleet.df(assign.sparkSession).select("machine").join(sums, "machine", "left").select("machine", F.coalesce("t_com", F.lit(0.0)).alias("t_com"))


def costs(assign: DataFrame, fleet: Fleet) -> DataFrame:
    """machine, n_vertices, n_edges, mem_used, t_cal, t_com, t. Replicas are made once."""
    cost = fleet.values("c_com")
    held = replicas(assign).withColumn("all", F.aggregate("machines", F.lit(0.0), lambda a, m: a + F.get(cost, m)))
    each = held.select(F.explode("machines").alias("machine"), F.size("machines").alias("n"), "all")
    com = F.when(F.col("n") > 1, (F.col("n") - 2) * F.get(cost, F.col("machine")) + F.col("all")).otherwise(0.0)
    v = each.groupBy("machine").agg(F.count(F.lit(1)).alias("n_vertices"), F.sum(com).alias("t_com"))
    e = assign.groupBy("machine").agg(F.count(F.lit(1)).alias("n_edges"))
    zero = lambda c, x: F.coalesce(F.col(c), x).alias(c)
    out = fleet.df(assign.sparkSession).join(e, "machine", "left").join(v, "machine", "left")
    out = out.select("machine", "c_node", "c_edge", "kind", zero("n_vertices", F.lit(0).cast("long")), zero("n_edges", F.lit(0).cast("long")), zero("t_com", F.lit(0.0)))
    out = out.withColumn("mem_used", fleet.m_node * F.col("n_vertices") + fleet.m_edge * F.col("n_edges")).withColumn("t_cal", F.col("c_edge") * F.col("n_edges") + F.col("c_node") * F.col("n_vertices"))
    return out.select("machine", "kind", "n_vertices", "n_edges", "mem_used", "t_cal", "t_com", (F.col("t_cal") + F.col("t_com")).alias("t"))


def total(assign: DataFrame, fleet: Fleet, mode: str = "superstep") -> DataFrame:
    """tc: the slowest machine; with mode 'barrier_split' the slowest of each part."""
    goal = F.max("t") if mode == "superstep" else F.max("t_cal") + F.max("t_com")
    return costs(assign, fleet).agg(goal.alias("tc"))


def replication_factor(assign: DataFrame) -> DataFrame:
    return replicas(assign).agg((F.sum(F.size("machines")) / F.count(F.lit(1))).alias("rf"))


def balance(assign: DataFrame, fleet: Fleet, by: str = "n_edges") -> DataFrame:
    """Largest share over the even share."""
    return costs(assign, fleet).agg((F.max(by) * len(fleet) / F.sum(by)).alias("ratio"))


def border_count(assign: DataFrame) -> DataFrame:
    return replicas(assign).agg(F.sum((F.size("machines") > 1).cast("long")).alias("n_border"), F.count(F.lit(1)).alias("n_vertices"))


def edge_cut(edges: DataFrame, homes: DataFrame) -> DataFrame:
    """Edges whose ends live on different machines; homes: v, machine."""
    a, b = homes.select(F.col("v").alias("src"), F.col("machine").alias("ms")), homes.select(F.col("v").alias("dst"), F.col("machine").alias("md"))
    return edges.join(a, "src").join(b, "dst").agg(F.sum((F.col("ms") != F.col("md")).cast("long")).alias("n_cut"), F.count(F.lit(1)).alias("n_edges"))


def comm_share(assign: DataFrame, fleet: Fleet) -> DataFrame:
    return costs(assign, fleet).select("machine", F.when(F.col("t") == 0, 0.0).otherwise(F.col("t_com") / F.col("t")).alias("share"))


def histogram(assign: DataFrame, fleet: Fleet, bins: int = 10) -> DataFrame:
    """Machines by band of their time between zero and the slowest."""
    c = costs(assign, fleet)
    top = c.agg(F.max("t").alias("top"))
    band = F.least(F.floor(F.col("t") * bins / F.col("top")), F.lit(bins - 1)).cast("long")
    return c.crossJoin(F.broadcast(top)).groupBy(band.alias("band")).agg(F.count(F.lit(1)).alias("machines"), F.sum("t_cal").alias("t_cal"), F.sum("t_com").alias("t_com"))


def homogeneous_identity(assign: DataFrame, fleet: Fleet) -> DataFrame:
    """With unit communication costs, all machines' communication over the sum of
    |S| (|S| - 1): always 2."""
    com = t_com(assign, fleet).agg(F.sum("t_com").alias("com"))
    pairs = replicas(assign).agg(F.sum(F.size("machines") * (F.size("machines") - 1)).alias("pairs"))
    return com.crossJoin(pairs).select(F.when(F.col("pairs") == 0, 2.0).otherwise(F.col("com") / F.col("pairs")).alias("ratio"))


def overlap(assign: DataFrame, machine: int) -> DataFrame:
    """Vertices that each other machine shares with one."""
    held = replicas(assign).where(F.array_contains("machines", machine))
    return held.select(F.explode("machines").alias("other")).where(F.col("other") != machine).groupBy("other").agg(F.count(F.lit(1)).alias("n"))


def invariants(assign: DataFrame, edges: DataFrame, fleet: Fleet) -> DataFrame:
    """One row that must read: all edges assigned, none twice, none foreign, none on an
    unknown machine, no machine over its memory."""
    each = assign.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))
    both = edges.withColumn("e", F.lit(1)).join(each, ["src", "dst"], "full_outer")
    counts = both.agg(F.sum("e").cast("long").alias("n_edges"), F.sum(F.when(F.col("e") == 1, F.coalesce("n", F.lit(0)))).cast("long").alias("n_assigned"), F.sum((F.col("n") > 1).cast("long")).alias("_d"), F.sum(F.col("e").isNull().cast("long")).alias("n_foreign"))
    unknown = assign.agg(F.sum((~F.col("machine").between(0, len(fleet) - 1)).cast("long")).alias("n_unknown"))
    over = memory(assign, fleet).agg(F.sum((~F.col("fits")).cast("long")).alias("n_over_memory"))
    return counts.crossJoin(unknown).crossJoin(over).select("n_edges", "n_assigned", F.coalesce("_d", F.lit(0).cast("long")).alias("n_duplicate"), "n_foreign", "n_unknown", "n_over_memory")
