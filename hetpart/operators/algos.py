"""Workloads over partitioned graphs: PageRank, triangles, levels, distances, components.

Answers don't depend on the partition. Iterative ones run as a driver loop of plans; each
round's state is written to the shared checkpoint folder, so lost executors cost one round."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut
from ..sources.graphs import both_ways, degrees


def pagerank(assign: DataFrame, iterations: int = 5, damping: float = 0.85, cut_every: int = 4) -> DataFrame:
    """(v, rank). Each machine sums what its edges bring; the partial sums meet by vertex."""
    deg = cut(degrees(assign.select("src", "dst")))
    n = deg.count()
    arcs = assign.select(F.explode(F.array(F.struct(F.col("src").alias("u"), F.col("dst").alias("v")), F.struct(F.col("dst").alias("u"), F.col("src").alias("v")))).alias("x"), "machine").select("x.*", "machine")
    rank = deg.select("v", F.lit(1.0 / max(n, 1)).alias("rank"), "degree")
    for k in range(iterations):
        out = rank.select(F.col("v").alias("u"), (F.col("rank") / F.col("degree")).alias("share"))
        partial = arcs.join(out, "u").groupBy("machine", "v").agg(F.sum("share").alias("s"))
        total = partial.groupBy("v").agg(F.sum("s").alias("s"))
        rank = deg.join(total, "v", "left").select("v", ((1 - damping) / n + damping * F.coalesce("s", F.lit(0.0))).alias("rank"), "degree")
        if (k + 1) % cut_every == 0:
            rank = cut(rank)
    return rank.select("v", "rank")


def triangles(edges: DataFrame) -> DataFrame:
    """n_triangles. Edges point from the lower to the higher (degree, id) end, so a hub is
    the centre of few wedges."""
    d = degrees(edges)
    e = edges.join(d.withColumnRenamed("v", "src").withColumnRenamed("degree", "ds"), "src").join(d.withColumnRenamed("v", "dst").withColumnRenamed("degree", "dd"), "dst")
    up = F.struct("ds", "src") < F.struct("dd", "dst")
    e = e.select(F.when(up, F.col("src")).otherwise(F.col("dst")).alias("a"), F.when(up, F.col("dst")).otherwise(F.col("src")).alias("b"))
    wedge = e.join(e.select("a", F.col("b").alias("c")), "a").where("b < c")
    close = edges.select(F.col("src").alias("b"), F.col("dst").alias("c"))
    return wedge.select("b", "c").join(close, ["b", "c"]).agg(F.count(F.lit(1)).alias("n_triangles"))


def bfs(edges: DataFrame, source: int) -> DataFrame:
    """(v, level) of all vertices that the source reaches."""
    arcs = cut(both_ways(edges))
    seen = edges.sparkSession.createDataFrame([(source, 0)], "v long, level int")
    frontier, level = seen, 0
    while True:
        level += 1
        new = arcs.join(frontier.select("v"), "v").select(F.col("u").alias("v")).distinct().join(seen, "v", "left_anti")
        frontier = cut(new.withColumn("level", F.lit(level)))
        if frontier.isEmpty():
            return seen
        seen = seen.unionByName(frontier)  # each level is written once
        if level % 32 == 0:
            seen = cut(seen)


def sssp(weighted: DataFrame, source: int, activity: list[DataFrame] | None = None) -> DataFrame:
    """(v, dist) with non-negative integer weights; only vertices that improved are active.
    activity gets the active vertices (step, v) of each round."""
    arcs = weighted.select(F.col("src").alias("v"), F.col("dst").alias("u"), "weight").unionByName(weighted.select(F.col("dst").alias("v"), F.col("src").alias("u"), "weight"))
    dist = weighted.sparkSession.createDataFrame([(source, 0)], "v long, dist long")
    active = dist
    while True:
        if activity is not None:
            activity.append(active.select(F.lit(len(activity) + 1).alias("step"), "v"))
        offer = arcs.join(active, "v").groupBy("u").agg(F.min(F.col("dist") + F.col("weight")).alias("offer")).withColumnRenamed("u", "v")
        both = cut(dist.join(offer, "v", "full_outer").select("v", F.col("dist").alias("old"), F.least("dist", "offer").alias("dist")))
        active = both.where("old IS NULL OR dist < old").select("v", "dist")
        dist = both.select("v", "dist")
        if active.isEmpty():
            return dist


def components(edges: DataFrame) -> DataFrame:
    """(v, component): least vertex id of each component, by turns of large and small stars."""
    all_ = edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
    e = cut(edges.select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).distinct())
    before = None
    while True:
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        small = large.join(large.groupBy("a").agg(F.min("b").alias("m")), "a")
        e = cut(small.select("a", F.col("m").alias("b")).unionByName(small.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))).distinct())
        state = e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if state == before:
            return all_.join(e.withColumnRenamed("a", "v"), "v", "left").select("v", F.coalesce("b", "v").alias("component"))
        before = state
