import hashlib

import numpy as np

from hetpart.llm import suffix_dedup as S


def brute(docs):
    first = {}
    for i, t in sorted(docs.items()):
        b = (t or "").encode()
        for p in range(len(b) - 49):
            first.setdefault(b[p : p + 50], i)
    out = {}
    for i, t in docs.items():
        b = (t or "").encode()
        gone = bytearray(len(b))
        for p in range(len(b) - 49):
            if first[b[p : p + 50]] < i:
                gone[p : p + 50] = b"\1" * 50
        spans = sum(1 for k in range(len(b)) if gone[k] and (k == 0 or not gone[k - 1]))
        out[i] = (len(b), sum(gone), spans, hashlib.sha256(bytes(x for x, r in zip(b, gone, strict=True) if not r)).hexdigest())
    return out


def test_equals_brute_force(frame, sample, awkward, edited):
    docs = dict(sample) | dict(awkward)
    base = max(sample.values(), key=len)[:6000]
    docs |= {800_000 + k: edited(base, 0.01, k) for k in range(40)}
    docs |= {-5: base[200:400], 810_000: "ab" * 400, 810_001: "ab" * 300, 810_002: "é" * 60, 810_003: "z" * 49, 810_004: "q" * 50, 810_005: "q" * 50}
    for buckets in (3, 40):
        got = S.deduplicate(frame(list(docs.items()), 5), texts=True, buckets=buckets).collect()
        want = brute(docs)
        assert len(got) == len(docs)
        for r in got:
            assert tuple(r)[1:5] == want[r["doc_id"]]
            assert hashlib.sha256(r["kept"]).hexdigest() == r["kept_sha256"]


def test_full_buckets_take_hot_anchors_apart(frame, sample, edited):
    """Very many contexts around one short phrase, and one passage in many documents: a
    bound of a few segments gives what brute force gives."""
    rng = np.random.default_rng(5)
    noise = lambda n: "".join(chr(c) for c in rng.integers(97, 123, n))
    phrase, passage = "all rights of this short phrase", "a passage of more than fifty bytes that a third of the documents hold, word by word"
    docs = {k: noise(60) + phrase + noise(60) + (noise(9) + passage + noise(9)) * (k % 3 == 0) for k in range(300)}
    docs |= {300 + k: docs[k][20:160] for k in range(0, 300, 7)}
    docs |= {-1: "ab" * 300, 900: "ab" * 200, 901: "é" * 60, 902: None}
    base = max(sample.values(), key=len)[:3000]
    docs |= {1000 + k: edited(base, 0.01, k) for k in range(20)}
    want = brute(docs)
    for held in (300, 5_000, 50_000):
        got = S.deduplicate(frame(list(docs.items()), 4), texts=False, buckets=2, held=held).collect()
        assert {r[0]: tuple(r)[1:5] for r in got} == want


def test_a_hot_anchor_leaves_its_bucket():
    rng = np.random.default_rng(2)
    phrase = np.frombuffer(b"one short phrase in all of them", np.uint8)
    data = np.concatenate([np.concatenate([rng.integers(97, 123, 40), phrase, rng.integers(97, 123, 40)]) for _ in range(2000)]).astype(np.uint8)
    out = S.Sender(1)
    out.add(np.arange(2000), data, np.arange(2001) * (80 + len(phrase)))
    here, kinds = S.Held(1, 100_000), []
    for kind, _, blob in list(out.flush()):
        if kind == 0:
            kinds += [k for k, _, _ in here.add(S.unpack(blob, *S.SEGMENTS))]
    assert 3 in kinds and here.size <= 100_000 and len(here.hot) > 0


def test_nulls_repeats_and_empty_tables(spark, frame):
    t = "a passage that is surely longer than fifty bytes, so it counts as a repeat"
    got = S.deduplicate(frame([(1, t), (1, t), (2, t), (None, t), (3, None)]), texts=False).collect()
    by = sorted((r["doc_id"] if r["doc_id"] is not None else -1, r["n_removed"]) for r in got)
    assert by == [(-1, 0), (1, len(t)), (1, len(t)), (2, len(t)), (3, 0)]
    assert S.deduplicate(frame([]), texts=False).count() == 0


def test_suffix_sort_finds_equal_suffixes_of_smaller_owners():
    rng = np.random.default_rng(1)
    rows = rng.integers(0, 2, (400, 50)).astype(np.uint8)
    rows[:, :34] = 7  # a long common prefix: all is left to the tries
    rows[:, 34:44] = rows[0, 34:44]
    buf, owner = rows.ravel(), rng.integers(0, 30, 400)
    pos = np.arange(400) * 50
    hit = np.sort(np.concatenate(list(S.sort_suffixes(np.append(buf, np.zeros(8, np.uint8)), pos, np.zeros(400, np.int64), owner))))
    least = {}
    for r, o in zip(rows, owner, strict=True):
        k = r.tobytes()
        least[k] = min(least.get(k, 99), o)
    want = [i for i in range(400) if owner[i] > least[rows[i].tobytes()]]
    assert hit.tolist() == want
