"""A corpus pipeline of five stages over ``documents``.

Each stage takes (spark, docs, sf_dir) and works on every row that its predecessor kept.
All but the last return the columns of documents; the last returns token ids.
"""

from __future__ import annotations

import functools
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hetpart.llm import bpe, decontaminate, near_dup, pii, toxicity
from hetpart.llm.common import at_rest, boxed, picked, position, shared_folder, table, unboxed

#: SQL can't express the trained and sampled stages; tests/llm holds each against brute force.
ORACLE_SQL = None


def toxic_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier chain takes as toxic go. It learns from the labels of
    the documents that are here."""
    chain = toxicity.train(docs, table(spark, sf_dir, "labels"))
    return unboxed(toxicity.score(boxed(docs, text="text"), chain, ["box"]).where(~F.col("is_toxic")), docs.columns)


def near_copies_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near-duplicates the document with the least id stays, once; a
    document without an id stays."""
    rows = boxed(docs, doc_id="doc_id")
    kept = near_dup.near_duplicates(picked(docs, doc_id="doc_id", text="text")).where("is_kept AND doc_id IS NOT NULL").select("doc_id").distinct()
    named = rows.join(kept, "doc_id", "left_semi").dropDuplicates(["doc_id"])
    return unboxed(named.unionByName(rows.where("doc_id IS NULL")), docs.columns)


def benchmark_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go."""
    verdict = decontaminate.contamination(boxed(docs, text="text"), table(spark, sf_dir, "benchmark"), key="box")
    return unboxed(verdict.where(~F.col("contaminated")), docs.columns)


def personal_data_masked(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data is masked, terms that disclose it are generalised or removed."""
    out = pii.sanitised(docs)
    if "n_chars" not in docs.columns:
        return out
    kind = docs.schema.fields[position(docs, "n_chars")].dataType
    return unboxed(boxed(out, new="text"), docs.columns, n_chars=F.char_length("new").cast(kind))


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document, with digests of ids and decoded text."""
    return bpe.encode(docs, ids=True, digests=True).drop("decoded")


def _rested(stage):
    """A stage that begins with the driver's memory free of the stages before it."""

    @functools.wraps(stage)
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        at_rest(spark)
        return stage(spark, docs, sf_dir)

    return run_stage


STAGES = [
    ("toxicity", _rested(toxic_out)),
    ("near_duplicates", _rested(near_copies_out)),
    ("decontamination", _rested(benchmark_out)),
    ("personal_data", _rested(personal_data_masked)),
    ("bpe", _rested(encoded)),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written as Parquet and read again."""
    docs = table(spark, sf_dir, "documents")
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        at = f"{folder}/{k}-{name}"
        stage(spark, docs, sf_dir).write.parquet(at)
        docs = spark.read.parquet(at)
    return docs
