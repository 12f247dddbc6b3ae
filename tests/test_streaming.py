from pyspark.sql import functions as F

from hetpart.streaming import edges as S


def write(spark, folder, rows):
    spark.createDataFrame(rows, "src long, dst long").coalesce(1).write.mode("append").parquet(folder)


def test_placement_goes_on_after_a_restart(spark, tmp_path):
    data, folder = str(tmp_path / "data"), str(tmp_path / "run")
    write(spark, data, [(k, 1000 + k % 7) for k in range(60)])
    stream = lambda: spark.readStream.schema("src long, dst long").parquet(data)
    one = {(r["src"], r["dst"]): r["machine"] for r in S.placed(stream(), 4, folder).collect()}
    write(spark, data, [(k, 1000 + k % 7) for k in range(50, 100)])
    two = {(r["src"], r["dst"]): r["machine"] for r in S.placed(stream(), 4, folder).collect()}
    assert len(one) == 60 and len(two) == 100 and all(two[e] == m for e, m in one.items())
    assert set(two.values()) <= {0, 1, 2, 3}


def test_placement_keeps_edges_of_a_vertex_together(spark, tmp_path):
    data = str(tmp_path / "data")
    write(spark, data, [(1, 2)])
    write(spark, data, [(1, 3), (2, 3)])
    stream = spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(data)
    assert S.placed(stream, 4).select("machine").distinct().count() <= 2


def test_stream_equals_batch(spark, sf):
    batch = S.counts(S.edge_stream(spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))))
    stream = S.drain(S.counts(S.edge_stream(S.event_stream(spark, sf, files=3))))
    assert stream.exceptAll(batch).count() == 0 and batch.exceptAll(stream).count() == 0
