"""Small helpers that the corpus operators share."""

from __future__ import annotations

import gc
import tempfile

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType


#: Bytes of an Arrow batch: with two workers an executor, what both sides hold stays small.
ARROW_BYTES = 8 << 20


def bounded_batches(spark: SparkSession) -> None:
    """Lowers the session's Arrow batch size, a setting that may change at any time."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(ARROW_BYTES))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    bounded_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def at_rest(spark: SparkSession) -> None:
    """Returns to the system what the driver's Python and JVM hold of finished work: their
    memory counts together, and neither gives any back by itself."""
    from .textbuf import give_back

    gc.collect()
    give_back()
    spark.sparkContext._jvm.System.gc()


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Uses the cluster's shared folder; one of this machine only where Spark runs on it alone."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if not shared and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="hetpart-checkpoint-"))


def shared_folder(spark: SparkSession) -> str:
    """A folder that driver and executors share, for tables that are written and read again."""
    ensure_checkpoint_dir(spark)
    return spark.sparkContext.getCheckpointDir()


def checkpointed(df: DataFrame) -> DataFrame:
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def plan_bytes(df: DataFrame) -> int:
    """The planner's estimate of a plan's size: of files, what they take on disk."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def fold(doc_id: str = "doc_id", parts: int = 5):
    """crc32 of the id as text, modulo the number of parts."""
    return F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(parts)).cast("int")


def position(df: DataFrame, name: str) -> int:
    """Where a column stands: the one of exactly this name, else the only one that has it
    in other letter case."""
    exact = [i for i, c in enumerate(df.columns) if c == name]
    same = exact or [i for i, c in enumerate(df.columns) if c.lower() == name.lower()]
    if len(same) != 1:
        raise ValueError(f"{len(same)} columns are named {name}")
    return same[0]


def picked(df: DataFrame, /, **names: str) -> DataFrame:
    """Only the named columns, new name = old name. Found by place, so extra columns may have
    any names: with blanks, dots or colons, or equal to these in other letter case."""
    at = {new: position(df, old) for new, old in names.items()}
    numbered = df.toDF(*[f"c{i}" for i in range(len(df.columns))])
    return numbered.select(*[F.col(f"c{i}").alias(new) for new, i in at.items()])


def boxed(df: DataFrame, /, **names: str) -> DataFrame:
    """The whole row as one struct ``box``, with fields by place, and the named columns."""
    at = {new: position(df, old) for new, old in names.items()}
    numbered = df.toDF(*[f"c{i}" for i in range(len(df.columns))])
    return numbered.select(F.struct(*numbered.columns).alias("box"), *[F.col(f"c{i}").alias(new) for new, i in at.items()])


def unboxed(df: DataFrame, columns: list[str], /, **changed: Column) -> DataFrame:
    """The rows of ``boxed`` again; changed: columns to replace, by name."""
    return df.select(*[changed.get(c, F.col("box").getField(f"c{i}")) for i, c in enumerate(columns)]).toDF(*columns)


def schema_of(df: DataFrame, keep: list[str], more: str) -> StructType:
    """Fields of the kept columns, then those that ``more`` declares."""
    kept = [StructField(c, df.schema.fields[position(df, c)].dataType) for c in keep]
    return StructType(kept + StructType.fromDDL(more).fields)


#: Rows of one key from which it may count as hot, and the share of all rows that makes it so.
HOT_ROWS, HOT_SHARE = 2_000, 1_000


def hot_join(rows: DataFrame, small: DataFrame, on: list[str], size: str, total: int) -> DataFrame:
    """Inner join with a table of one row a key that says in ``size`` how many rows the key
    has. Keys with a thousandth of all rows (``total``) or more, a thousand at most, are
    broadcast, so that their rows stay where they are; the others are shuffled by key."""
    limit = max(HOT_ROWS, total // HOT_SHARE)
    hot = F.broadcast(small.where(F.col(size) >= limit))
    cold = rows.join(F.broadcast(hot.select(*on)), on, "left_anti").join(small.where(F.col(size) < limit), on)
    return rows.join(hot, on).unionByName(cold)
