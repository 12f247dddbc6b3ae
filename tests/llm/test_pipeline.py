import hashlib

import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")
from hetpart.llm import bpe  # noqa: E402
from hetpart.llm.common import table  # noqa: E402

SF = "/root/testdata/sf0.01"


def test_stages_in_order_and_decisions_take_effect(spark, sf):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "decontamination", "personal_data", "bpe"] and corpus_pipeline.ORACLE_SQL is None
    docs = table(spark, sf, "documents")
    first = docs.orderBy("doc_id").first()
    item = table(spark, sf, "benchmark").orderBy("item_id").first()["text"]
    extra = [(10_000, first["text"]), (10_001, item + " " + " ".join(f"own{k}" for k in range(40))), (10_002, "Write to someone.else@example.com about " + " ".join(f"gardens{k}" for k in range(60))), (10_003, None), (10_004, "")]
    more = spark.createDataFrame([(i, t, "en", "s", len(t or ""), "clash") for i, t in extra], "doc_id long, text string, lang string, source string, n_chars long, is_toxic string")
    from pyspark.sql import functions as F

    now = docs.withColumn("is_toxic", F.lit("clash")).unionByName(more)
    columns, kept = now.columns, []
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, now, sf)
        if k < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == columns, name
        now = spark.createDataFrame(out.collect(), out.schema)
        kept.append({r["doc_id"] for r in now.select("doc_id").collect()})
    assert kept[0] >= {10_000, 10_001, 10_002, 10_003, 10_004}
    assert 10_000 not in kept[1] or first["doc_id"] not in kept[0]
    assert 10_001 in kept[1] and 10_001 not in kept[2]
    assert kept[2] == kept[3] == kept[4] and {10_002, 10_003, 10_004} <= kept[4]
    texts = {r["doc_id"]: r["text"] for r in bpe.decode(now).collect()}
    assert "[EMAIL]" in texts[10_002] and "someone.else@" not in texts[10_002] and texts[10_003] == texts[10_004] == ""


def test_run_over_the_small_tables(spark):
    rows = corpus_pipeline.run(spark, SF).collect()
    n = table(spark, SF, "documents").count()
    assert 0.5 * n < len(rows) < n and len({r["doc_id"] for r in rows}) == len(rows)
    enc = bpe.encoder(bpe.default_path())
    for r in rows[:50]:
        import numpy as np

        text = enc.tokenizer.decode(np.array(r["ids"], np.int64))
        assert r["decoded_sha256"] == hashlib.sha256(text.encode()).hexdigest() and enc.encode([text])[0].tolist() == r["ids"]
    labels = {r["doc_id"]: r["toxic"] for r in table(spark, SF, "labels").collect()}
    left = {r["doc_id"] for r in rows}
    toxic = [i for i, t in labels.items() if t == 1]
    assert sum(i in left for i in toxic) <= 0.1 * len(toxic)


def test_driver_does_not_learn_and_rests_between_stages(spark, sf, monkeypatch):
    from hetpart.llm import toxicity

    def on_driver(*_):
        raise AssertionError("the driver learns")

    monkeypatch.setattr(toxicity, "logistic", on_driver)  # tasks import their own
    rested = []
    monkeypatch.setattr(corpus_pipeline, "at_rest", lambda s: rested.append(s))
    docs = table(spark, SF, "documents")
    dict(corpus_pipeline.STAGES)["toxicity"](spark, docs, SF).count()
    for _, stage in corpus_pipeline.STAGES[2:]:
        stage(spark, docs, SF)
    assert len(rested) == 4
