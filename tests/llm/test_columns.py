"""Extra columns of any name, equal to the needed ones in other letter case too."""

import pytest
from pyspark.sql import functions as F

from hetpart.llm import bpe, decontaminate, langid, line_rules, near_dup, pii, quality_cnn, suffix_dedup, toxicity

NAMES = ["my col", "a:b", "a.b", "TEXT", "Doc_ID", "box", "key", "_key", "id", "_t", "c0", "n_chars"]
ROWS = [(1, "Write to some.one@example.com about gardens " * 4, "en", "s"), (2, None, None, None), (3, "", "en", "s"), (None, "short text", "en", "s"), (3, "", "en", "s")]


@pytest.fixture(scope="module")
def odd(spark):
    docs = spark.createDataFrame(ROWS, "doc_id long, text string, lang string, source string")
    more = [F.lit(k).alias(n) for k, n in enumerate(NAMES)]
    return docs.select(F.lit(True).alias("first one"), "doc_id", "text", "lang", "source", *more)


def plain(df):
    return sorted(map(str, df.select("doc_id", "text", "lang", "source").collect()))


CALLS = {
    "op2": lambda d: quality_cnn.score(d, 0.5, ["doc_id"]),
    "op3": pii.findings,
    "op4": lambda d: bpe.encode(d, digests=True),
    "op5": lambda d: toxicity.score(d, None, ["doc_id"]),
    "op6": suffix_dedup.deduplicate,
    "op7": lambda d: langid.identify(d, langid.learn_samples(d), ["doc_id"]),
    "op8": lambda d: decontaminate.contamination(d, d.sparkSession.createDataFrame([(1, "about gardens write to")], "item_id int, text string")),
    "op8 joined": lambda d: decontaminate.contamination(d, d.sparkSession.createDataFrame([(1, "about gardens write to")], "item_id int, text string"), max_bytes=0),
    "op9": near_dup.near_duplicates,
    "op10": line_rules.judge,
}


@pytest.mark.parametrize("name", CALLS)
def test_operators(spark, odd, name):
    docs = spark.createDataFrame(ROWS, "doc_id long, text string, lang string, source string")
    one, two = CALLS[name](odd), CALLS[name](docs)
    assert one.columns == two.columns and one.columns[0] == "doc_id"
    assert sorted(map(str, one.collect())) == sorted(map(str, two.collect())) and two.count() == len(ROWS)


def test_rewriting_operators_return_all_columns(odd):
    for out in (pii.sanitised(odd), line_rules.cleaned(odd, min_kept=0.0)):
        assert out.columns == odd.columns
        assert all(r[odd.columns.index(n)] == k for r in out.collect() for k, n in enumerate(NAMES))


def test_stages(spark, odd, sf):
    pipeline = pytest.importorskip("corpus_pipeline")
    for name, stage in pipeline.STAGES:
        out = stage(spark, odd, sf)
        assert out.count() >= 4, name
        if name != "bpe":
            assert out.columns == odd.columns, name
            assert all(r[5 + k] == k for r in out.collect() for k, n in enumerate(NAMES) if n != "n_chars"), name
