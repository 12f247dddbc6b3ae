"""Edge lists from files and assignments to files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .graphs import as_edges


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", comment: str = "#") -> DataFrame:
    """Text edge lists, one pair a line, with comment lines; malformed lines are dropped."""
    raw = spark.read.schema("src long, dst long").options(sep=sep, comment=comment, mode="DROPMALFORMED", ignoreLeadingWhiteSpace=True, ignoreTrailingWhiteSpace=True).csv(path)
    return as_edges(raw)


def write_edge_list(edges: DataFrame, path: str, sep: str = "\t") -> None:
    edges.select("src", "dst").write.mode("overwrite").options(sep=sep).csv(path)


def write_assignment(assign: DataFrame, path: str, format: str = "parquet") -> None:
    """One folder a machine, so that a machine's reader lists and reads its own files only."""
    assign.repartition("machine").sortWithinPartitions("machine", "seq").write.mode("overwrite").partitionBy("machine").format(format).save(path)


def read_assignment(spark: SparkSession, path: str, format: str = "parquet") -> DataFrame:
    out = spark.read.format(format).load(path)
    return out.select("src", "dst", out["machine"].cast("int").alias("machine"), "seq")
