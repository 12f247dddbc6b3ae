import hashlib
import re

import pytest

from hetpart.llm import decontaminate as D

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def low(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (t or ""))


def brute(docs, items):
    windows = {}
    for i, t in items:
        w = WORD.findall(low(t))
        n = min(10, len(w))
        for s in range(len(w) - n + 1 if n else 0):
            windows.setdefault(n, {}).setdefault(tuple(w[s : s + n]), set()).add("null" if i is None else str(i))
    out = {}
    for d, t in docs:
        w, hit, found = WORD.findall(low(t)), set(), set()
        for n, table in windows.items():
            for s in range(len(w) - n + 1):
                g = table.get(tuple(w[s : s + n]))
                if g:
                    hit.update(range(s, s + n))
                    found |= g
        out[d] = (len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit))
    return out


@pytest.mark.parametrize("bound", [1 << 25, 0])
def test_equals_brute_force(spark, frame, sample, awkward, sf, bound):
    import pandas as pd

    b = pd.read_parquet(f"{sf}/benchmark.parquet")
    items = [*zip(b.item_id.tolist(), b.text.tolist(), strict=True), (900, "of the and"), (901, None), (902, "of the and"), (10, "thed"), (903, ""), (None, "to be of the in that it"), (900, "of the and")]
    docs = [*sample.items(), *awkward, (5_000_000, f"{b.text[0]} {b.text[1]}"), (5_000_001, b.text[0].upper()), (5_000_002, "TO be, of the in that it!")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    want = brute(docs, items)
    got = D.contamination(frame(docs), bench, max_bytes=bound).collect()
    assert len(got) == len(docs)
    assert all(tuple(r)[1:] == want[r["doc_id"]] for r in got)


@pytest.mark.parametrize("bound", [1 << 25, 0])
def test_empty_benchmark_and_empty_table(spark, frame, bound):
    none = spark.createDataFrame([], "item_id long, text string")
    r = D.contamination(frame([(1, "a b"), (2, None)]), none, max_bytes=bound).orderBy("doc_id").collect()
    assert [x["n_words"] for x in r] == [2, 0] and not any(x["contaminated"] for x in r)
    assert D.contamination(frame([]), none, max_bytes=bound).count() == 0


def _structured(flip, n=1024):
    """A word of two letters by the parity of ones in each place's number: two such words
    agree in every polynomial hash modulo 2 ** 64."""
    return "".join("ab"[(bin(i).count("1") + flip) % 2] for i in range(n))


@pytest.mark.parametrize("bound", [1 << 25, 0])
def test_equality_is_decided_by_bytes(spark, frame, bound):
    a, b = _structured(0), _structured(1)
    tail = " ".join(f"w{k}" for k in range(12))
    items = [(1, a), (2, f"{a} {tail}"), (3, f"{b} {tail}")]
    docs = [(1, b), (2, a), (3, f"{b} {tail}"), (4, f"{a} {tail}"), (5, f"x {b} y")]
    want = brute(docs, items)
    got = {r["doc_id"]: tuple(r)[1:] for r in D.contamination(frame(docs), spark.createDataFrame(items, "item_id long, text string"), max_bytes=bound).collect()}
    assert got == want and not want[1][4] and not want[5][4] and want[2][4]


@pytest.mark.parametrize("bound", [1 << 25, 0])
def test_repeated_and_null_ids_are_judged_by_their_own_texts(spark, bound):
    item = " ".join(f"q{k}" for k in range(12))
    docs = spark.createDataFrame([(None, item), (None, "clean text"), (3, item + " more"), (3, "other"), (3, "other")], "doc_id long, text string")
    got = D.contamination(docs, spark.createDataFrame([("i", item)], "item_id string, text string"), max_bytes=bound).collect()
    assert sorted(((r["doc_id"] or -1), r["n_words"], r["n_hit"], r["contaminated"]) for r in got) == [(-1, 2, 0, False), (-1, 12, 12, True), (3, 1, 0, False), (3, 1, 0, False), (3, 13, 12, True)]
