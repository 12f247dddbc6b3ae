"""Classifiers: held-out accuracy, exact kernels, odd rows."""

import numpy as np
import pytest

from hetpart.llm import langid, quality_cnn, toxicity
from hetpart.llm.common import fold, table

MEDIUM = "/root/testdata/sf0.01"


def test_quality_beats_the_base_rate_on_held_out_rows(spark):
    r = quality_cnn.op2_quality_cnn(spark, MEDIUM).join(table(spark, MEDIUM, "labels"), "doc_id").toPandas()
    held = r[r.held_out]
    assert ((r.score >= 0) & (r.score <= 1)).all() and (r.predicted == (r.score >= 0.3)).all()
    assert (held.predicted == held.quality).mean() >= 0.93 > held.quality.mean()


def test_gradient_of_the_net():
    net = quality_cnn.Net(3)
    for k in net.p:
        net.p[k] = net.p[k].astype(np.float64)
    net.p["bias"] += np.random.default_rng(1).normal(0, 0.1, net.p["bias"].shape)  # off the kink
    raw = [b"some text of a few bytes " * 9, b"", b"short", bytes(range(256)) * 3]
    lay = quality_cnn.Layout(np.frombuffer(b"".join(raw), np.uint8), np.concatenate([[0], np.cumsum([len(x) for x in raw])]))
    y, w = np.array([1.0, 0, 1, 0]), np.array([1.0, 2, 1, 1])

    def loss():
        _, mean, top = net.pooled(lay, np.maximum(net.strips(lay)[1].max(1), 0))
        z = mean @ net.p["mean"] + top @ net.p["top"] + net.p["out"]
        return float((w * (np.logaddexp(0, z) - y * z)).sum() / w.sum())

    got = net.gradient(lay, y, w)
    rng = np.random.default_rng(0)
    for name in net.p:
        flat = net.p[name].reshape(-1)
        for i in rng.integers(0, flat.size, 4).tolist():
            if name == "emb" and i >= 256 * quality_cnn.DIM:
                continue
            old = flat[i]
            flat[i] = old + 1e-5
            up = loss()
            flat[i] = old - 1e-5
            down = loss()
            flat[i] = old
            assert got[name].reshape(-1)[i] == pytest.approx((up - down) / 2e-5, abs=1e-5)


def test_chunks_cover_the_document():
    for size in (0, 1, 63, 64, 65, 255, 256, 257, 1000, 4096):
        lay = quality_cnn.Layout(np.zeros(size, np.uint8), np.array([0, size]))
        strips = {s for a, b in zip(lay.start, lay.end, strict=True) for s in range(a, b)}
        assert strips == set(range(max(1, -(-size // 64))))


def test_language_on_held_out_rows(spark):
    r = langid.op7_langid(spark, MEDIUM).join(table(spark, MEDIUM, "documents").select("doc_id", "lang"), "doc_id").toPandas()
    assert (r[r.held_out].lang_pred == r[r.held_out].lang).mean() >= 0.98
    assert ((r.score >= 0) & (r.score <= 1)).all()


def test_phrases_equal_greedy_parsing():
    sample = b"the cat sat on the mat and the dog ate the cat"
    auto = langid.Automaton(sample)

    def brute(t):
        n = i = 0
        while i < len(t):
            k = i + 1
            while k <= len(t) and t[i:k] in sample:
                k += 1
            n, i = n + 1, max(k - 1, i + 1)
        return n

    texts = [b"the dog sat", b"zzz", b"", b"matcatq the", b"a", b"the cat sat on the mat and the dog ate the cat"]
    m = langid.Model({"x": sample})
    got = m.rates(texts)[:, 0] * np.maximum([len(t) for t in texts], 1)
    assert auto.classes > 1 and got.round().astype(int).tolist() == [brute(t) for t in texts]


def test_language_of_odd_rows(spark, frame, awkward):
    samples = langid.learn_samples(table(spark, MEDIUM, "documents"))
    r = {x["doc_id"]: x for x in langid.identify(frame(awkward), samples, ["doc_id"]).collect()}
    assert r[900_000]["lang_pred"] == r[900_001]["lang_pred"] == r[900_008]["lang_pred"] == "und" and r[900_000]["score"] == 0
    assert r[900_007]["lang_pred"] == "en"
    assert {x["lang_pred"] for x in langid.identify(frame(awkward), {}, ["doc_id"]).collect()} == {"und"}
    assert langid.identify(frame([]), samples, ["doc_id"]).count() == 0
    assert langid.learn_samples(frame([(1, None)])) == {}


def test_toxicity_on_held_out_rows(spark):
    sf = "/root/testdata/sf0.1"
    r = toxicity.op5_toxicity(spark, sf).join(table(spark, sf, "labels"), "doc_id").toPandas()
    held = r[r.fold == 0]
    hit = (held.is_toxic & (held.toxic == 1)).sum()
    assert hit / held.is_toxic.sum() >= 0.93 and hit / (held.toxic == 1).sum() >= 0.85


def test_toxic_words_are_learned_and_odd_rows_pass(spark, frame, awkward):
    docs = [(k, f"plain words about number {k} and gardens{' vile grublin' * (k % 4 == 0)}") for k in range(200)]
    labels = spark.createDataFrame([(k, int(k % 4 == 0)) for k in range(200)] + [(10**9, 1), (5, None)], "doc_id long, toxic int")
    chain = toxicity.train(frame(docs), labels)
    got = {r["doc_id"]: r["is_toxic"] for r in toxicity.score(frame([*docs, *awkward]), chain, ["doc_id"]).collect()}
    assert all(got[k] == (k % 4 == 0) for k in range(200)) and not any(got[i] for i, _ in awkward)
    assert toxicity.train(frame(docs), labels.where("toxic = 0")) is None
    assert toxicity.score(frame(docs), None, ["doc_id"]).where("is_toxic").count() == 0
    assert toxicity.score(frame([]), chain, ["doc_id"]).count() == 0


def test_scores_equal_a_plain_chain(spark, frame, awkward):
    """Features word by word, models one after another: the scores of the vectorised chain."""
    import re

    docs = [(k, f"plain words about number {k} and gardens{' vile grublin' * (k % 4 == 0)}") for k in range(120)]
    chain = toxicity.train(frame(docs), spark.createDataFrame([(k, int(k % 4 == 0)) for k in range(120)], "doc_id long, toxic int"))

    def feature(raw, head):
        data = np.frombuffer(raw, np.uint8)
        h = int(toxicity.run_hashes(toxicity.prefix_sums(data), np.array([0]), np.array([len(raw)]))[0])
        return (h ^ (0xA5A5A5A5A5A5A5A5 if head else 0)) >> (64 - toxicity.BITS)

    def plain(text):
        words = re.findall(rb"[0-9a-z\x80-\xff]+", bytes(b + 32 if 65 <= b <= 90 else b for b in (text or "").encode()))
        found = {feature(x, False) for x in words} | {feature(x[:k], True) for x in words for k in toxicity.HEADS if len(x) > k}
        cols, p = {int(chain.lut[f]) for f in found} - {-1}, []
        for w in chain.weights:
            z = sum(w[c] for c in cols) + sum(a * b for a, b in zip(p, w[toxicity.FEATURES :], strict=False)) + w[-1]
            p.append(1 / (1 + np.exp(-np.clip(z, -30, 30))))
        return p

    rows = [(i, t) for i, t in [*docs, *awkward] if i != 900_100]
    got = {r["doc_id"]: [r[f"p_{c}"] for c in toxicity.CATEGORIES] + [r["is_toxic"]] for r in toxicity.score(frame(rows), chain, ["doc_id"]).collect()}
    for i, t in rows:
        p = plain(t)
        assert got[i][:-1] == pytest.approx(p, abs=1e-9) and got[i][-1] == (p[-1] >= chain.threshold)


def test_out_of_fold_probabilities_never_see_their_fold():
    """With labels that only a row's own features could tell, held-out scores know nothing."""
    rng = np.random.default_rng(3)
    n = 240
    part, truth = np.arange(n) % toxicity.FOLDS, (rng.random(n) < 0.5).astype(np.float32)
    asked = []

    def view(k):
        asked.append(k)
        x = np.zeros((n, toxicity.FEATURES), np.float32)
        x[np.arange(n), np.arange(n)] = 1
        y = np.stack([truth, truth, truth], 1)
        if k is not None:
            y[part == k] = np.nan  # a model of this fold must not read them
        return x, y

    weights, threshold = toxicity.fit_chain(view, np.ones(n, np.float32), part, truth)
    assert set(asked) == {None, *range(toxicity.FOLDS)} and len(weights) == 3
    assert all(np.isfinite(w).all() for w in weights) and 0 <= threshold <= 1


def test_scores_equal_a_plain_convolution():
    """The net's score byte by byte, filter by filter and chunk by chunk, without its layout."""
    net = quality_cnn.Net(5)
    net.p["bias"] += np.random.default_rng(2).normal(0, 0.1, net.p["bias"].shape).astype(np.float32)
    emb, filters = net.p["emb"].astype(float), np.concatenate([net.p["near"], net.p["far"]]).astype(float)
    for text in (b"", b"short", b"some text " * 40, bytes(range(256)) * 2, b"x" * 64, b"yz" * 129):
        strips = max(1, -(-len(text) // 64))
        padded = [*text, *[256] * (64 * (strips + 1) - len(text))]
        best = []
        for s in range(strips):
            at = [np.concatenate([emb[padded[i + k]] for k in range(8)]) @ filters + net.p["bias"] for i in range(64 * s, 64 * s + 64, 4)]
            best.append(np.maximum(np.max(at, axis=0), 0))
        chunks = [np.max(best[3 * c : 3 * c + 4], axis=0) for c in range(max(1, -(-(strips - 4) // 3) + 1))]
        z = float(np.mean(chunks, axis=0) @ net.p["mean"] + np.max(chunks, axis=0) @ net.p["top"] + net.p["out"][0])
        assert net.scores(np.frombuffer(text, np.uint8), np.array([0, len(text)]))[0] == pytest.approx(1 / (1 + np.exp(-z)), abs=1e-5)


def test_quality_without_labels(spark, frame, awkward):
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert {r["score"] for r in quality_cnn.score(frame(awkward), quality_cnn.train(frame(awkward), none), ["doc_id"]).collect()} == {0.5}
    assert all(0 <= r["score"] <= 1 for r in quality_cnn.score(frame(awkward), quality_cnn.Net(), ["doc_id"]).collect())
    assert quality_cnn.score(frame([]), quality_cnn.Net(), ["doc_id"]).count() == 0


def test_folds_are_crc32(spark):
    import zlib

    r = spark.range(50).select("id", fold("id", 5).alias("f")).collect()
    assert all(x["f"] == zlib.crc32(str(x["id"]).encode()) % 5 for x in r)
