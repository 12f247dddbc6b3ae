"""Superstep simulation: what a run costs on a fleet, from which vertices are active when."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .costs import replicas
from .machines import Fleet


def dense_activity(assign: DataFrame, steps: int) -> DataFrame:
    """Every vertex in every step, as in PageRank."""
    return assign.select(F.explode(F.array("src", "dst")).alias("v")).distinct().select(F.explode(F.sequence(F.lit(1), F.lit(steps))).alias("step"), "v")


def level_activity(levels: DataFrame) -> DataFrame:
    """A vertex is active in the step after the one that reached it, as in breadth-first search."""
    return levels.select((F.col("level") + 1).alias("step"), "v")


def simulate(assign: DataFrame, fleet: Fleet, activity: DataFrame, mode: str = "superstep") -> DataFrame:
    """step, t_cal, t_com, t of the slowest machines. A machine works for its active
    vertices and the edges with an active end, and talks for its active shared vertices."""
    cost = fleet.values("c_com")
    held = replicas(assign).withColumn("all", F.aggregate("machines", F.lit(0.0), lambda a, m: a + F.get(cost, m)))
    each = activity.join(held, "v").select("step", F.explode("machines").alias("machine"), F.size("machines").alias("n"), "all")
    com = F.when(F.col("n") > 1, (F.col("n") - 2) * F.get(cost, F.col("machine")) + F.col("all")).otherwise(0.0)
    v = each.groupBy("step", "machine").agg(F.count(F.lit(1)).alias("n_vertices"), F.sum(com).alias("t_com"))
    ends = assign.select("src", "dst", "machine")
    act = ends.select(F.col("src").alias("v"), "src", "dst", "machine").unionByName(ends.select(F.col("dst").alias("v"), "src", "dst", "machine")).join(activity, "v")
    e = act.select("step", "src", "dst", "machine").distinct().groupBy("step", "machine").agg(F.count(F.lit(1)).alias("n_edges"))
    node, edge = fleet.values("c_node"), fleet.values("c_edge")
    m = F.col("machine")
    both = v.join(e, ["step", "machine"], "left").select("step", (F.get(node, m) * F.col("n_vertices") + F.get(edge, m) * F.coalesce("n_edges", F.lit(0))).alias("t_cal"), "t_com")
    t = F.max(F.col("t_cal") + F.col("t_com")) if mode == "superstep" else F.max("t_cal") + F.max("t_com")
    return both.groupBy("step").agg(F.max("t_cal").alias("t_cal"), F.max("t_com").alias("t_com"), t.alias("t"))
