"""Edge streams from events: windows, de-duplication, joins, stateful placement.

Every function takes a streaming or a batch DataFrame of events where that makes sense;
``drain`` runs a stream over what is there now and returns its last state."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import hash_machine, vertex
from ..session import fresh_folder

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
LATE = "10 minutes"


def event_stream(spark: SparkSession, sf_dir: str, files: int | None = None) -> DataFrame:
    """The events table replayed as a stream of files in order of time. A stream reads a
    folder, so the table is written to one in the shared folder first."""
    folder = fresh_folder(spark, "events")
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    events = events.withColumn("ts", F.col("ts").cast("timestamp"))
    events.repartitionByRange(files or 4, "ts").write.parquet(folder)
    reader = spark.readStream.schema(events.schema)
    return (reader.option("maxFilesPerTrigger", 1) if files else reader).parquet(folder)


def edge_stream(events: DataFrame, p: int = 8) -> DataFrame:
    """ts, src, dst, machine of the user-bucket edge of each event."""
    a, b = vertex(F.col("user_id"), 5), vertex(F.floor("value"), 6)
    e = events.where("user_id IS NOT NULL AND value IS NOT NULL").select("ts", "event_id", F.least(a, b).alias("src"), F.greatest(a, b).alias("dst"))
    return e.withColumn("machine", hash_machine(F.col("src"), F.col("dst"), p))


def counts(edges: DataFrame, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return edges.withWatermark("ts", LATE).groupBy(w.alias("w"), "machine").agg(F.count(F.lit(1)).alias("n")).select(F.unix_micros("w.start").alias("start_us"), "machine", "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    s = events.withWatermark("ts", LATE).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return s.select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


def deduplicated(edges: DataFrame) -> DataFrame:
    """Each edge once within the watermark's reach."""
    return edges.withWatermark("ts", LATE).dropDuplicatesWithinWatermark(["src", "dst"])


def drain(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over all available input; returns the last complete state, or all rows
    that an append stream has put out."""
    spark = stream.sparkSession
    out, at = fresh_folder(spark, "stream"), fresh_folder(spark, "progress")
    if mode == "complete":
        q = stream.writeStream.outputMode("complete").option("checkpointLocation", at).trigger(availableNow=True).foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(out)).start()
    else:
        q = stream.writeStream.outputMode("append").format("parquet").option("checkpointLocation", at).option("path", out).trigger(availableNow=True).start()
    q.awaitTermination()
    if q.exception():
        raise q.exception()
    return spark.read.schema(stream.schema).parquet(out)


def placed(stream: DataFrame, p: int = 8, folder: str | None = None) -> DataFrame:
    """One-pass placement in micro-batches: each new edge goes to a machine that holds both
    its ends, else one, else any, by least load; replicas and loads live in a snapshot that
    each batch reads and replaces. Returns src, dst, machine of all distinct edges.

    Batch k reads the snapshot of batch k - 1 and writes its own, so a batch that runs
    again after a failure gives the same snapshot; with a ``folder`` a later run goes on
    from there."""
    spark = stream.sparkSession
    folder = folder or fresh_folder(spark, "placement")
    last: dict[str, int] = {}

    def batch(df: DataFrame, k: int) -> None:
        new = df.select("src", "dst").distinct()
        old = spark.read.parquet(f"{folder}/state/{k - 1}") if k else spark.createDataFrame([], "src long, dst long, machine int")
        new = new.join(old, ["src", "dst"], "left_anti")
        loads = {r["machine"]: r["count"] for r in old.groupBy("machine").count().collect()}  # p rows
        load = F.array(*[F.lit(int(loads.get(i, 0))) for i in range(p)])
        held = old.select(F.explode(F.array("src", "dst")).alias("v"), "machine").groupBy("v").agg(F.sort_array(F.collect_set("machine")).alias("m"))
        x = new.join(held.select(F.col("v").alias("src"), F.col("m").alias("a")), "src", "left").join(held.select(F.col("v").alias("dst"), F.col("m").alias("b")), "dst", "left")
        none = F.array().cast("array<int>")
        a, b = F.coalesce("a", none), F.coalesce("b", none)
        options = F.when(F.size(F.array_intersect(a, b)) > 0, F.array_intersect(a, b)).when(F.size(F.array_union(a, b)) > 0, F.array_union(a, b)).otherwise(F.array(hash_machine(F.col("src"), F.col("dst"), p)))
        pick = F.array_min(F.transform(options, lambda m: F.struct(F.get(load, m), m.alias("m"))))["m"]
        old.unionByName(x.select("src", "dst", pick.alias("machine"))).write.mode("overwrite").parquet(f"{folder}/state/{k}")
        last["batch"] = k

    q = stream.writeStream.option("checkpointLocation", f"{folder}/progress").trigger(availableNow=True).foreachBatch(batch).start()
    q.awaitTermination()
    if q.exception():
        raise q.exception()
    if "batch" not in last:
        return spark.createDataFrame([], "src long, dst long, machine int")
    return spark.read.parquet(f"{folder}/state/{last['batch']}")
