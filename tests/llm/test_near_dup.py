import collections

import numpy as np

from hetpart.llm import near_dup as N


def brute(docs, idf, similarity=0.8):
    sh = N.Shingles(*N._buffer([(t or "").encode() for _, t in docs]), idf)
    ids = [i for i, _ in docs]
    parent = {i: i for i in ids}

    def find(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for q in range(len(ids)):
        for p in np.flatnonzero(N.weighted_jaccard(sh.of(q), sh) >= similarity):
            a, b = find(ids[p]), find(ids[q])
            if a != b:
                parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_classes_equal_brute_force(frame, sample, awkward, edited):
    docs = dict(sample) | dict(awkward)
    for b, text in enumerate(sorted(sample.values(), key=len)[100:104]):
        docs |= {700_000 + 100 * b + k: edited(text, (0.005, 0.01, 0.03, 0.1)[k % 4], k) for k in range(30)}
        docs[720_000 + b] = text
    docs = list(docs.items())
    df = frame(docs)
    counts, n = N.document_frequency(df)
    assert n == len(docs)
    want = brute(docs, N.idf_table(counts, n))
    got = {r["doc_id"]: r["class_id"] for r in N.near_duplicates(df).collect()}
    sizes = collections.Counter(want.values())
    wrong = [i for i in want if got[i] != want[i]]
    assert len(wrong) <= 0.01 * len(docs), wrong
    assert max(sizes.values()) > 5


def test_unrelated_texts_stay_apart_and_edge_rows(spark, frame):
    t = "one two three four five six seven eight"
    r = {x["doc_id"]: x for x in N.near_duplicates(frame([(1, t), (2, t.upper() + "!"), (3, "nothing like it at all here"), (4, None), (5, ""), (6, "two words"), (7, "Two. Words."), (None, t)])).collect()}
    assert r[1]["class_id"] == r[2]["class_id"] == 1 and r[1]["is_kept"] and not r[2]["is_kept"]
    assert r[3]["class_id"] == 3 and r[4]["class_id"] == 4 and r[5]["class_id"] == 5
    assert r[6]["class_id"] == r[7]["class_id"] == 6
    assert r[None]["class_id"] is None and r[None]["is_kept"]
    assert N.near_duplicates(frame([])).count() == 0


def test_samples_agree_as_often_as_weights_do():
    words = [f"w{k}" for k in range(400)]
    a, b = " ".join(words), " ".join(words[:360] + [f"v{k}" for k in range(40)])
    sh = N.Shingles(*N._buffer([a.encode(), b.encode()]), None)
    keys = N.band_keys(sh, bands=600, rows=1)
    share = (keys[0] == keys[1]).mean()
    assert abs(share - N.weighted_jaccard(sh.of(0), sh)[1]) < 0.06


def test_small_blocks_give_the_same_classes(frame, sample, edited, monkeypatch):
    text = sorted(sample.values(), key=len)[120]
    docs = [(k, edited(text, (0.01, 0.02, 0.08)[k % 3], k)) for k in range(40)]
    one = {tuple(r) for r in N.near_duplicates(frame(docs)).collect()}
    monkeypatch.setattr(N, "PART_WORDS", 1500)
    assert {tuple(r) for r in N.near_duplicates(frame(docs)).collect()} == one


def test_recall_of_pairs(frame, sample, edited):
    """Pairs of different texts at 0.8 or more, by brute force, end up in one class: nine in ten or more."""
    docs = list(sample.items())
    for b, text in enumerate(sorted(sample.values(), key=len)[60:160:5]):
        docs += [(800_000 + 20 * b + k, edited(text, (0.003, 0.006, 0.012, 0.02, 0.03)[k % 5], 31 * b + k)) for k in range(12)]
    df = frame(docs)
    counts, n = N.document_frequency(df)
    sh = N.Shingles(*N._buffer([(t or "").encode() for _, t in docs]), N.idf_table(counts, n))
    ids = [i for i, _ in docs]
    pairs = [(ids[q], ids[p]) for q in range(len(ids)) for p in np.flatnonzero(N.weighted_jaccard(sh.of(q), sh) >= 0.8).tolist() if p > q and docs[p][1] != docs[q][1]]
    got = {r["doc_id"]: r["class_id"] for r in N.near_duplicates(df).collect()}
    recall = sum(got[a] == got[b] for a, b in pairs) / len(pairs)
    print(f"recall of {len(pairs)} pairs: {recall:.4f}")
    assert len(pairs) > 300 and recall >= 0.99


def test_sketch_never_counts_too_few_and_rarely_too_many(frame, sample):
    docs = list(sample.items())
    counts, n = N.document_frequency(frame(docs))
    sh = N.Shingles(*N._buffer([(t or "").encode() for _, t in docs]))
    h, true = np.unique(sh.hash, return_counts=True)
    told = np.minimum(counts[0][N.slot(h, 0)], counts[1][N.slot(h, 1)])
    assert (told >= true).all() and (told - true <= n / N.RARE).mean() > 0.95


def test_structured_words_and_texts_stay_apart(frame):
    word = lambda flip, n: "".join("ab"[(bin(i).count("1") + flip) % 2] for i in range(n))
    long = lambda flip: " ".join(("x", "y")[(bin(i).count("1") + flip) % 2] for i in range(4096))
    r = {x["doc_id"]: x["class_id"] for x in N.near_duplicates(frame([(1, word(0, 2048)), (2, word(1, 2048)), (3, long(0) + " end"), (4, long(1) + " end")])).collect()}
    assert r[1] == 1 and r[2] == 2
    sh = N.Shingles(*N._buffer([long(0).encode(), long(1).encode()]))
    assert (sh.digests()[0] != sh.digests()[1]).any()


def test_one_id_with_several_texts(frame):
    a, b = " ".join(f"p{k}" for k in range(40)), " ".join(f"q{k}" for k in range(40))
    r = [tuple(x) for x in N.near_duplicates(frame([(1, a), (1, b), (2, b), (3, "else where")])).collect()]
    assert sorted(r) == [(1, 1, True), (1, 1, True), (2, 1, False), (3, 3, True)]
